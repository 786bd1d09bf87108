import glob
import os

import duckdb
import pytest

from floorwalk import catalog

TABLES = "region nation customer supplier part orders lineitem events".split()
KEYS = ["door_pairs", "door_reach", "venue_stats", "first_hops", "rq_btd", "spdq_dm", "knn_ag", "variant_merged_sdq", "positions_as_of", "stream_range_monitor", "keyword_knn", "uncertain_range", "bt_hops", "validate_broken", "connectivity", "query_memory", "task_b5", "sql_range", "stream_alerts", "generated_pairs", "route_timed"]


def plain(rows, names):
    order = sorted(range(len(names)), key=names.__getitem__)
    return sorted(tuple(str(r[i]) for i in order) for r in rows)


@pytest.mark.parametrize("key", KEYS)
def test_against_sql(spark, small, key):
    db = duckdb.connect()
    for name in TABLES:
        path = f"{small}/{name}.parquet"
        db.execute(f"create view {name} as select * from '{path + '/*.parquet' if os.path.isdir(path) else path}'")
    frame = catalog.queries()[key](spark, small)
    found = db.execute(catalog.oracle_sql()[key])
    names = [d[0] for d in found.description]
    assert sorted(names) == sorted(frame.columns)
    assert plain(found.fetchall(), names) == plain(frame.collect(), frame.columns)


def test_every_oracle_has_a_query():
    assert set(catalog.oracle_sql()) <= set(catalog.queries())


def test_no_trace_of_optional_package():
    for path in glob.glob("floorwalk/**/*.py", recursive=True):
        if "/llm/" not in path:
            assert "floorwalk.llm" not in open(path).read()
