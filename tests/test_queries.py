import pytest
from pyspark.sql import functions as F

from floorwalk.operators import extend, knn, metrics, route
from floorwalk.operators import range as ranges
from floorwalk.operators.labels import METHODS
from floorwalk.plans.border import build_border_tree
from floorwalk.plans.matrix import with_ranks
from floorwalk.operators.topology import crucial_parts
from floorwalk.sources import venue as V



def rows(frame):
    return sorted(map(tuple, frame.collect()))


@pytest.mark.parametrize("method", ("dm", "lr", "bt"))
def test_golden_range_knn(spark, middle, method):
    venue = V.build_venue(spark, middle)
    points, things = V.query_points(venue), V.objects(venue)
    assert tuple(ranges.range_query(method, venue, points, things, 60_000).agg(F.count("*"), F.sum("dist_mm")).first()) == (2751, 100074140)
    assert tuple(knn.knn_query(method, venue, points, things, 10).agg(F.count("*"), F.sum("dist_mm")).first()) == (100, 356360)


@pytest.mark.parametrize("method", ("ag", "dm", "btd"))
def test_golden_routes(spark, middle, method):
    venue = V.build_venue(spark, middle)
    found = route.route_query(method, venue, V.query_pairs(venue))
    total = found.agg(F.sum("dist_mm"), F.sum(F.size("door_path")), F.sum("nvd")).first()
    assert total[:2] == (3551081, 371)
    assert {"ag": 4406, "dm": 172, "lr": 4406}.get(method, total[2]) == total[2]
    longest = found.where("qid = 66").first()
    assert longest.dist_mm == 156290 and longest.door_path[:3] == [10000000, 3000003, 4000003] and len(longest.door_path) == 16


def test_visited_doors_order(spark, small):
    """Look-ups visit fewest doors, the deep tree fewer than the plain one, expansion most."""
    venue = V.build_venue(spark, small)
    n, pairs = {}, V.query_pairs(venue)
    best = route.distance_query("dm", venue, pairs).where("dist_mm is not null")
    for method in METHODS:
        n[method] = route.visited_doors(method, venue, *route.sides(venue, pairs), best).agg(F.sum("nvd")).first()[0]
    assert n["dm"] <= n["btd"] <= n["bt"] and n["btd"] < n["ag"] == n["lr"]


@pytest.mark.parametrize("radius", [30_000])
def test_methods_agree_on_ranges(spark, small, radius):
    venue = V.build_venue(spark, small)
    points, things = V.query_points(venue), V.objects(venue)
    want = rows(ranges.brute_range(venue, points, things, radius))
    for method in METHODS:
        assert rows(ranges.range_query(method, venue, points, things, radius)) == want
    ids = sorted({(q, o) for q, o, _ in want})
    assert rows(ranges.range_ids("ag", venue, points, things, radius)) == ids


def test_knn_prefix_and_shortage(spark, small):
    venue = V.build_venue(spark, small)
    points, things = V.query_points(venue), V.objects(venue)
    few = things.where("object_id < 7")
    want = rows(knn.brute_knn(venue, points, few, 50))
    for method in METHODS:
        assert rows(knn.knn_query(method, venue, points, few, 50)) == want
    five, ten = rows(knn.knn_query("btd", venue, points, things, 5)), rows(knn.knn_query("btd", venue, points, things, 10))
    assert set(five) <= set(ten)


def test_same_point_and_unreachable(spark, small):
    venue = V.build_venue(spark, small)
    p = V.query_points(venue).orderBy("qid").first()
    pair = spark.createDataFrame([(1, p.floor, p.x_mm, p.y_mm, p.floor, p.x_mm, p.y_mm)], "qid long, s_floor long, s_x long, s_y long, t_floor long, t_x long, t_y long")
    for method in ("ag", "dm", "bt"):
        got = route.route_query(method, venue, pair, False).first()
        assert (got.dist_mm, got.door_path) == (0, [])
    rooms = venue.partitions.where("kind = 'room'").select("part_id")
    sealed = venue.moves.join(rooms.toDF("to_part"), "to_part", "left_anti").select(*venue.moves.columns)
    closed = V.Venue(spark, small, 5, "sealed", venue.partitions, venue.doors, sealed)
    source, target = route.sides(closed, V.query_pairs(venue))
    same = source.join(target.select("qid", "part_id"), ["qid", "part_id"]).count()
    assert route.distance_query("ag", closed, V.query_pairs(venue)).where("dist_mm is not null").count() == same


def test_tree_shape(spark, middle):
    venue = V.build_venue(spark, middle)
    tree = build_border_tree(venue)
    crucial = tree.members.join(crucial_parts(venue, 6), "part_id").groupBy("leaf").count()
    assert crucial.where("count > 1").isEmpty()
    assert tree.nodes.where("parent_id is null").count() == 1
    assert tree.nodes.where("parent_id is not null").groupBy("parent_id").count().where("count < 2").isEmpty()
    assert tree.members.count() == venue.partitions.count() - 1


def test_rank_ties(spark):
    frame = spark.createDataFrame([(1, 1, 0), (1, 3, 20), (1, 2, 20), (1, 4, 10)], "a_door long, b_door long, dist_mm long")
    assert [r.b_door for r in with_ranks(frame).orderBy("rank").collect()] == [1, 4, 2, 3]


def test_model_sizes(spark, middle):
    venue = V.build_venue(spark, middle)
    size = {r["method"]: r["b"] for r in metrics.model_size(venue).groupBy("method").agg(F.sum("n_bytes").alias("b")).collect()}
    assert size["access_graph"] < size["layered_rtree"] < size["border_tree"] < size["border_tree_deep"] < size["door_matrix"]


def test_schedules(spark, middle):
    venue, always = V.build_venue(spark, middle), 12 * 3600 - 60
    pairs = V.query_pairs(venue)
    open_now = route.distance_query("ag", venue, pairs)
    noon = extend.route_open_at("lr", venue, pairs, always)
    assert rows(noon) == rows(extend.route_open_at("ag", venue, pairs, always))
    worse = noon.withColumnRenamed("dist_mm", "d").join(open_now, "qid").where("d < dist_mm")
    assert worse.isEmpty()
    with pytest.raises(ValueError):
        extend.route_open_at("dm", venue, pairs, always)


def test_uncertain_contains_certain(spark, small):
    venue = V.build_venue(spark, small)
    points, things = V.query_points(venue), V.objects(venue)
    got = extend.uncertain_range(venue, points, extend.uncertain_objects(things), 60_000)
    exact = ranges.range_query("dm", venue, points, things, 60_000)
    sure = got.where("certain = 1").select("qid", "object_id")
    assert sure.join(exact, ["qid", "object_id"], "left_anti").isEmpty()
    assert exact.join(got, ["qid", "object_id"], "left_anti").isEmpty()


def test_keyword_route_not_shorter(spark, small):
    venue = V.build_venue(spark, small)
    words = extend.object_words(venue)
    covered = extend.keyword_route(venue, V.query_pairs(venue), V.objects(venue), words, ["building"])
    plain = route.distance_query("dm", venue, V.query_pairs(venue))
    assert covered.join(plain, "qid").where("total_mm < dist_mm").isEmpty()
