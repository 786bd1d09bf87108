"""Searches of each method on graphs too large for the compiled kernel, and streams whose rows arrive out of order."""

import datetime

import pytest

from floorwalk.operators import knn, route
from floorwalk.operators import range as ranges
from floorwalk.plans import border, matrix, relax
from floorwalk.sources import venue as V
from floorwalk.streaming import occupancy
from tests.test_long_leg import corridor


def rows(frame):
    return sorted(map(tuple, frame.collect()))


PAIRS = "qid long, s_floor long, s_x long, s_y long, t_floor long, t_x long, t_y long"


@pytest.mark.parametrize("method", ("ag", "lr", "bt", "btd"))
def test_relational_engines_give_the_same_routes(spark, monkeypatch, method):
    pairs = spark.createDataFrame([(1, 0, 5_000, 2_000, 0, 515_000, 2_000), (2, 0, 515_000, 1_000, 0, 5_000, 2_000), (3, 0, 5_000, 2_000, 0, 300_000, 2_000), (4, 0, 5_000, 2_000, 0, 6_000, 2_000)], PAIRS)
    want = rows(route.route_query("dm", corridor(spark), pairs, False))
    assert [r[2] for r in want] == [[11, 12], [12, 11], [11], []]
    monkeypatch.setattr(relax, "LOCAL_LEGS", -1)
    assert rows(route.route_query(method, corridor(spark), pairs, False)) == want


def test_matrix_of_both_engines(spark, small, monkeypatch):
    here = matrix.door_matrix(V.build_venue(spark, small))
    monkeypatch.setattr(matrix, "is_local", lambda legs: False)
    there = V.build_venue(spark, small)
    fresh = V.Venue(spark, small, 5, "base", there.partitions, there.doors, there.moves)
    again = matrix.door_matrix(fresh).select(*here.columns)
    assert here.exceptAll(again).isEmpty() and again.exceptAll(here).isEmpty()


def test_relational_border_cells(spark, small, monkeypatch):
    there = V.build_venue(spark, small)
    tree = border.build_border_tree(there)
    fresh = V.Venue(spark, small, 5, "base", there.partitions, there.doors, there.moves)
    monkeypatch.setattr(border, "is_local", lambda legs: False)
    again = border.build_border_tree(fresh)
    for name in ("leaf_out", "leaf_in", "leaf_pairs", "inner", "deep_out", "deep_in"):
        columns = [c for c in getattr(tree, name).columns if not c.endswith("hop")]
        left, right = getattr(tree, name).select(*columns), getattr(again, name).select(*columns)
        assert left.exceptAll(right).isEmpty() and right.exceptAll(left).isEmpty(), name


def test_bounds_hold_the_kth_neighbour(spark, small):
    venue = V.build_venue(spark, small)
    points, things = V.query_points(venue), V.objects(venue)
    placed = ranges.placed_points(venue, points)
    far = {r.qid: r.dist_mm for r in knn.brute_knn(venue, points, things, 5).where("rank = 5").collect()}
    for method in ("ag", "dm", "lr", "bt", "btd"):
        bound = {r.qid: r.bound for r in knn.knn_bounds(method, venue, placed, things, 5).collect()}
        assert set(bound) == set(far) and all(bound[q] >= far[q] for q in far), method


def test_initialisations_agree(spark, small):
    venue = V.build_venue(spark, small)
    found = [rows(ranges.placed_points(venue, V.query_points(venue), how).select("qid", "part_id")) for how in ("grid", "scan", "rtree")]
    assert found[0] == found[1] == found[2]


def test_alerts_follow_event_time(spark, tmp_path):
    """Rows of later files may lie before those of earlier ones; what the watermark has passed comes out in order."""
    at = lambda m: datetime.datetime(2024, 1, 1, 0, 0) + datetime.timedelta(minutes=m)
    schema = "event_id long, user_id long, ts timestamp, inside boolean"
    files = ([(1, 7, at(0), False), (2, 7, at(30), True), (3, 7, at(50), True), (4, 8, at(10), True)], [(5, 7, at(40), False), (6, 8, at(20), False), (7, 9, at(300), True)], [(8, 7, at(5), True), (9, 9, at(900), False)])
    for i, part in enumerate(files):
        spark.createDataFrame(part, schema).coalesce(1).write.parquet(f"file://{tmp_path}/in/{i}")
    stream = spark.readStream.schema(schema).option("maxFilesPerTrigger", 1).option("recursiveFileLookup", True).parquet(f"file://{tmp_path}/in")
    found = [(r.user_id, r.ts, r.event) for r in occupancy.run_once(occupancy.alerts(stream, "60 minutes")).collect()]
    # Event 8 comes last of user 7 but before any of them has been told; the last row of all is still waiting.
    want = [(7, at(5), "enter"), (7, at(40), "leave"), (7, at(50), "enter"), (8, at(10), "enter"), (8, at(20), "leave"), (9, at(300), "enter")]
    assert sorted(found) == sorted(want)


def test_upserts_keep_the_last_version(spark, tmp_path):
    schema = "user_id long, ts timestamp, event_id long, part_id long"
    at = lambda m: datetime.datetime(2024, 1, 1) + datetime.timedelta(minutes=m)
    for i, part in enumerate(([(1, at(5), 1, 10), (2, at(1), 2, 20)], [(1, at(3), 3, 11)], [(1, at(9), 4, 12), (3, at(0), 5, 30)])):
        spark.createDataFrame(part, schema).coalesce(1).write.parquet(f"file://{tmp_path}/in/{i}")
    stream = spark.readStream.schema(schema).option("maxFilesPerTrigger", 1).option("recursiveFileLookup", True).parquet(f"file://{tmp_path}/in")
    assert rows(occupancy.upserts(stream, ["user_id"], occupancy.latest).select("user_id", "part_id")) == [(1, 12), (2, 20), (3, 30)]
