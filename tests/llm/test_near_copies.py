"""The pipeline's near-copy stage against brute-force Jaccard similarities of five-word shingles."""

import random

import numpy as np
import pyarrow as pa

import corpus_pipeline
from floorwalk.llm import simhash_dedup
from floorwalk.llm.runtime import materialize
from tests.llm.test_operators import SCHEMA, brute_suffix, lower, words


def shingles(text):
    ws = words(lower(text))
    return {tuple(ws[i : i + 5]) for i in range(max(1, len(ws) - 4))} if ws else set()


def near(a, b):
    return 5 * len(a & b) >= 4 * len(a | b)


def brute_groups(texts):
    sets, left, out = [shingles(t) for t in texts], set(range(len(texts))), []
    while left:
        group, queue = set(), [left.pop()]
        while queue:
            i = queue.pop()
            group.add(i)
            found = {j for j in left if near(sets[i], sets[j])}
            left -= found
            queue += found
        out.append(group)
    return out


def variants(seed=5):
    """Forty texts, each with five near copies of falling similarity around and above 0.8."""
    rng = random.Random(seed)
    word = lambda: "".join(rng.choice("bcdfgklmnprst") + rng.choice("aeiou") for _ in range(3))
    out = []
    for _ in range(40):
        base = [word() for _ in range(rng.randint(150, 400))]
        out.append(" ".join(base))
        for edits in (1, 2, 3, 4, 6):
            copy = list(base)
            for at in rng.sample(range(len(copy)), edits):
                copy[at] = word()
            out.append("  ".join(copy).upper() if edits == 2 else " ".join(copy))
    return out


def stage(spark, rows):
    frame = spark.createDataFrame(rows, SCHEMA).repartition(3)
    return dict(corpus_pipeline.STAGES)["simhash_dedup"](spark, frame, "").collect()


def row(doc_id, text):
    return (doc_id, text, "en", "s", len(text or ""), 0.5, "x")


def test_near_copies_from_080(spark):
    texts = variants()
    found = stage(spark, [row(i, t) for i, t in enumerate(texts)])
    groups = brute_groups(texts)
    close = [len(a & b) / len(a | b) for g in groups for a, b in [(shingles(texts[min(g)]), shingles(texts[max(g)]))] if len(g) > 1]
    assert min(close) < 0.9 and 40 < len(groups) < 240
    assert sorted(r.doc_id for r in found) == sorted(min(g) for g in groups)


def test_near_copies_in_many_slices_and_full_ones(spark, monkeypatch):
    """Slices of eight codes and parts of four: links are found across tables and across the cuts of full slices."""
    monkeypatch.setattr(simhash_dedup, "SLICE", 8)
    monkeypatch.setattr(simhash_dedup, "MEMBERS", 4)
    monkeypatch.setattr(simhash_dedup, "sampled_tables", lambda n: real(n, miss=1e-4, slice_size=8))
    texts = variants(9)
    groups = brute_groups(texts)
    assert sorted(r.doc_id for r in stage(spark, [row(i, t) for i, t in enumerate(texts)])) == sorted(min(g) for g in groups)


real = simhash_dedup.sampled_tables


def test_stages_with_the_similarity_rule(spark, small):
    docs = spark.read.parquet(f"{small}/documents.parquet")
    stages = dict(corpus_pipeline.STAGES)
    kept = materialize(stages["quality_rules"](spark, docs, small))
    rows = sorted((r.doc_id, r.text) for r in kept.collect())
    one = materialize(stages["simhash_dedup"](spark, kept, small))
    assert {r.doc_id for r in one.collect()} == {rows[min(g)][0] for g in brute_groups([t for _, t in rows])}
    cut = materialize(stages["suffix_dedup"](spark, one, small))
    want = brute_suffix([(r.doc_id, r.text) for r in one.collect()])
    assert all(abs(len(r.text.encode()) - (want[r.doc_id][0] - want[r.doc_id][1])) <= 6 * want[r.doc_id][2] for r in cut.collect())
    mixed = materialize(stages["source_mixing"](spark, cut, small))
    assert corpus_pipeline.run(spark, small).count() == stages["packing"](spark, mixed, small).count()


def family(n, edits, seed=11):
    """Texts of 150 words, each with its own few words changed: within the radius, most of them below 0.8 of each other."""
    rng = random.Random(seed)
    word = lambda: "".join(rng.choice("bcdfgklmnprst") + rng.choice("aeiou") for _ in range(3))
    base, out = [word() for _ in range(150)], []
    for i in range(n):
        copy = list(base)
        for at in rng.sample(range(150), edits[i % len(edits)]):
            copy[at] = word()
        out.append(" ".join(copy))
    return out


def test_families_are_not_compared_pair_by_pair(spark, monkeypatch):
    checked = []

    def counted(pairs, texts):
        checked.append(pairs.count())
        return verified(pairs, texts)

    verified = simhash_dedup.verified
    monkeypatch.setattr(simhash_dedup, "verified", counted)
    texts = family(300, (1, 2, 3, 4, 5, 6))
    groups = brute_groups(texts)
    assert 30 < len(groups) < 280
    assert sorted(r.doc_id for r in stage(spark, [row(i, t) for i, t in enumerate(texts)])) == sorted(min(g) for g in groups)
    assert sum(checked) <= 5 * len(texts)


def test_first_neighbours_reach_every_code_that_has_one():
    """0 has the neighbours 1 and 2, which lie too far from each other; all three are named."""
    codes = np.array([[0], [0b11], [0b1100]], dtype=np.uint64)
    batch = pa.RecordBatch.from_pydict({"key": [0] * 3, "part": [0] * 3, "id": [0, 1, 2], "label": [0, 1, 2], "member": [True] * 3, "w0": pa.array(codes[:, 0].view(np.int64))})
    tables = simhash_dedup.Tables(np.arange(64)[None, :], 0)
    for order in ([0, 1, 2], [1, 2, 0], [2, 0, 1]):
        found = simhash_dedup._search(tables, 1, 2, simhash_dedup.FIRST)(iter([batch.take(pa.array(order))]))
        assert {x for links in found for c in ("a", "b") for x in links.column(c).to_pylist()} == {0, 1, 2}
