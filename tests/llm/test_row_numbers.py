"""Quality and near-copy stages decide by row: null ids, repeated ids and different texts under one id."""

import corpus_pipeline
from tests.llm.test_near_copies import row, variants
from tests.llm.test_operators import SCHEMA


def run(spark, name, rows):
    frame = spark.createDataFrame(rows, SCHEMA).repartition(3)
    return sorted((r.doc_id is None, r.doc_id or 0, r.text) for r in dict(corpus_pipeline.STAGES)[name](spark, frame, "").collect())


def test_one_row_of_each_group_stays(spark):
    a, b, c, d = variants()[::6][:4]
    rows = [row(None, a), row(None, b), row(None, b), row(5, c), row(5, c), row(5, d), row(9, d), row(None, d)]
    assert run(spark, "simhash_dedup", rows) == sorted([(True, 0, a), (True, 0, b), (False, 5, c), (False, 5, d)])


def test_rejected_rows_do_not_follow_a_kept_one(spark):
    a, b = variants()[::6][:2]
    rows = [row(None, a), row(None, "too short"), row(None, None), row(7, b), row(7, "short too"), row(7, "w x y z v " * 40)]
    assert run(spark, "quality_rules", rows) == sorted([(True, 0, a), (False, 7, b)])
