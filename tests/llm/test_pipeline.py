"""The pipeline's stages, each against a brute-force version on its own input."""

import corpus_pipeline
from floorwalk.llm import packing, quality_rules
from floorwalk.llm.runtime import materialize
from tests.llm.test_near_copies import brute_groups
from tests.llm.test_operators import brute_suffix, words


def test_stages(spark, small):
    docs = spark.read.parquet(f"{small}/documents.parquet")
    columns = docs.columns
    stages = dict(corpus_pipeline.STAGES)
    assert list(stages) == ["quality_rules", "simhash_dedup", "suffix_dedup", "source_mixing", "packing"]
    kept = materialize(stages["quality_rules"](spark, docs, small))
    good = {r.doc_id for r in quality_rules.judge(docs).where("kept").collect()}
    assert kept.columns == columns and {r.doc_id for r in kept.collect()} == good
    one = materialize(stages["simhash_dedup"](spark, kept, small))
    rows = sorted((r.doc_id, r.text) for r in kept.collect())
    assert {r.doc_id for r in one.collect()} == {rows[min(g)][0] for g in brute_groups([t for _, t in rows])}
    cut = materialize(stages["suffix_dedup"](spark, one, small))
    want = brute_suffix([(r.doc_id, r.text) for r in one.collect()])
    assert cut.columns == columns
    for r in cut.collect():
        n_bytes, n_removed, *_ = want[r.doc_id]
        assert abs(len(r.text.encode()) - (n_bytes - n_removed)) <= 6 * want[r.doc_id][2]
        assert r.n_chars == len(r.text)
    mixed = materialize(stages["source_mixing"](spark, cut, small))
    total = lambda frame: sum(len(words(r.text)) for r in frame.collect())
    assert mixed.columns == columns and abs(total(mixed) - total(cut)) <= 40
    pieces = stages["packing"](spark, mixed, small)
    assert pieces.groupBy("sequence_id").agg({"length": "sum"}).where(f"`sum(length)` > {packing.WINDOW}").isEmpty()
    assert corpus_pipeline.run(spark, small).count() == pieces.count()
