"""The corpus pipeline: quality rules, near-dedup, repeated passages, mixing to target weights, packing.

Every stage reads all that the one before it kept, and all but the last return the columns of documents.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from floorwalk.llm import mixing, packing, quality_rules, simhash_dedup, suffix_dedup
from floorwalk.llm.runtime import materialize


def quality_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that pass the rules, without their hosts' boilerplate lines."""
    return quality_rules.clean(docs)


def near_duplicate_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document, the least id, of each group of near copies: five-word shingles, Jaccard similarity 0.8 and more."""
    return simhash_dedup.keep_one(docs)


def repeated_passage_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Texts without the passages that stand earlier in the corpus."""
    return suffix_dedup.clean(docs)


def mixing_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Every source at its target: whole epochs, then documents in random order up to the exact budget."""
    return mixing.mixed_corpus(docs)


def packing_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Pieces of the tokenised documents with their places in fixed windows."""
    return packing.pack(docs)


STAGES = [
    ("quality_rules", quality_stage),
    ("simhash_dedup", near_duplicate_stage),
    ("suffix_dedup", repeated_passage_stage),
    ("source_mixing", mixing_stage),
    ("packing", packing_stage),
]

# The stages hash, index and tokenise in ways SQL does not express; tests hold run() against brute force instead.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    for _, stage in STAGES[:-1]:
        docs = materialize(stage(spark, docs, sf_dir))
    return STAGES[-1][1](spark, docs, sf_dir)
