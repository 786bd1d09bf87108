import pytest
from pyspark.sql import functions as F

from floorwalk.operators import surrounding, topology
from floorwalk.operators.host import locate_grid, locate_scan
from floorwalk.plans import matrix, relax, rtree
from floorwalk.sources import store
from floorwalk.sources import venue as V


@pytest.mark.parametrize(("variant", "parts", "doors", "one_way"), [("base", 167, 243, 30), ("sparse", 167, 180, 9), ("dense", 167, 309, 63), ("fine", 176, 252, None), ("nocut", 166, 242, None)])
def test_counts(spark, middle, variant, parts, doors, one_way):
    venue = V.build_venue(spark, middle, 5, variant)
    assert venue.partitions.count() - 1 == parts
    assert venue.doors.count() == doors
    if one_way is not None:
        assert topology.one_way_doors(venue.moves).count() == one_way


def test_all_pairs_golden(spark, middle):
    venue = V.build_venue(spark, middle)
    assert topology.door_legs(venue).count() == 1482
    assert tuple(matrix.matrix_dist(venue).agg(F.count("*"), F.sum("dist_mm"), F.max("dist_mm")).first()) == (58807, 5241120486, 211764)


def test_kernels_agree(spark, small):
    venue = V.build_venue(spark, small)
    legs, doors = topology.graph_legs(venue), venue.doors.select("door_id")
    frames = [relax.all_pairs(legs, doors, e) for e in ("local", "relax", "square")]
    total = [tuple(f.agg(F.count("*"), F.sum("dist_mm"), F.max("dist_mm")).first()) for f in frames]
    assert total == [(8557, 665902966, 181764)] * 3


def test_merged_keeps_distances(spark, small):
    base, merged = V.build_venue(spark, small), V.build_venue(spark, small, 5, "merged")
    left = matrix.matrix_dist(merged)
    kept = merged.doors.select("door_id")
    right = matrix.matrix_dist(base).join(kept.toDF("a_door"), "a_door", "left_semi").join(kept.toDF("b_door"), "b_door", "left_semi").select("a_door", "b_door", "dist_mm")
    assert left.exceptAll(right).isEmpty() and right.exceptAll(left).isEmpty()


def test_decomposition_order(spark, small):
    """Forced passing through more centre points never shortens a way."""
    frames = []
    for variant in ("nocut", "base", "fine"):
        venue = V.build_venue(spark, small, 5, variant)
        rooms = venue.doors.where("kind <> 'segment'").select("door_id")
        frames.append(matrix.matrix_dist(venue).join(rooms.toDF("a_door"), "a_door", "left_semi").join(rooms.toDF("b_door"), "b_door", "left_semi").withColumnRenamed("dist_mm", variant))
    both = frames[0].join(frames[1], ["a_door", "b_door"]).join(frames[2], ["a_door", "b_door"])
    assert both.where("nocut > base or base > fine").isEmpty()


def test_hosts_agree(spark, middle):
    venue = V.build_venue(spark, middle)
    points = V.query_points(venue)
    found = [sorted(map(tuple, f.select("qid", "part_id").collect())) for f in (locate_scan(points, venue.partitions), locate_grid(points, venue.partitions), rtree.locate_rtree(points, rtree.build_rtree(venue)))]
    assert found[0] == found[1] == found[2]
    assert found[0][:3] == [(0, 10000000), (1, 410000040), (2, 301013000)]


def test_half_open_edges_and_outside(spark, small):
    venue = V.build_venue(spark, small)
    hall = venue.partitions.where("kind = 'hall' and floor = 0").orderBy("part_id").first()
    rows = [(1, 0, hall.xmin, hall.ymin), (2, 0, hall.xmax + 10**9, hall.ymin), (3, 99, hall.xmin, hall.ymin)]
    points = spark.createDataFrame(rows, "qid long, floor long, x_mm long, y_mm long")
    placed = locate_grid(points, venue.partitions)
    assert [tuple(r) for r in placed.select("qid", "part_id").collect()] == [(1, hall.part_id)]
    assert sorted(r.qid for r in surrounding.validate_points(points, placed).collect()) == [2, 3]


def test_floorplan_round_trip(spark, small, tmp_path):
    venue = V.build_venue(spark, small)
    for form in ("csv", "json"):
        store.save_floorplan(venue, f"file://{tmp_path}/{form}", form)
        again = store.load_floorplan(spark, f"file://{tmp_path}/{form}", form)
        assert topology.door_legs(again).exceptAll(topology.door_legs(venue)).isEmpty()


def test_tower_source(spark):
    store.register(spark)
    made = spark.read.format("floorwalk_tower").option("venues", 2).option("floors", 3).option("rooms", 4).load()
    assert made.count() == 2 * 3 * 5


def test_invariants(spark, middle):
    venue = V.build_venue(spark, middle)
    full = matrix.door_matrix(venue)
    assert full.where("a_door = b_door and (dist_mm <> 0 or first_hop is not null)").isEmpty()
    assert full.where("rank = 1 and dist_mm <> 0").isEmpty()
    spot = venue.doors.select("door_id", "floor", "x_mm", "y_mm")
    line = full.join(spot.toDF("a_door", "af", "ax", "ay"), "a_door").join(spot.toDF("b_door", "bf", "bx", "by"), "b_door").where("af = bf")
    from floorwalk.functions.geometry import leg_mm

    assert line.where(F.col("dist_mm") < leg_mm("ax", "ay", "bx", "by")).isEmpty()
    assert surrounding.validate_venue(venue).isEmpty()
