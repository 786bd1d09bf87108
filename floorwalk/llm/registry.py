"""Queries and oracle SQL of the training-data operators."""

from __future__ import annotations

from floorwalk.llm import byte_cnn, cap_filters, chat_format, context_mixing, mixing, packing, quality_rules, simhash_dedup, suffix_dedup, weak_labels


def queries() -> dict:
    return {
        "op1_weak_labels": weak_labels.query,
        "op2_suffix_dedup": suffix_dedup.query,
        "op3_chat_trees": chat_format.query,
        "op4_online_packing": packing.query,
        "op5_byte_cnn": byte_cnn.query,
        "op6_quality_rules": quality_rules.query,
        "op7_source_mixing": mixing.query,
        "op8_simhash_dedup": simhash_dedup.query,
        "op9_context_mixing": context_mixing.query,
        "op10_cap_filters": cap_filters.query,
    }


def oracle_sql() -> dict[str, str]:
    return {"op3_chat_trees": chat_format.ORACLE, "op6_quality_rules": quality_rules.ORACLE, "op7_source_mixing": mixing.ORACLE}
