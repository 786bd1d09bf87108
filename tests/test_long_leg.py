"""A corridor whose doors stand farther apart than the doubling search's first two radii."""

from floorwalk.operators import route
from floorwalk.sources import store
from floorwalk.sources import venue as V


def corridor(spark):
    part = lambda i, kind, low, high: (1, i, kind, 0, low, 0, high, 4_000, None, None)
    parts = spark.createDataFrame([part(1, "room", 0, 10_000), part(2, "hall", 10_000, 510_000), part(3, "room", 510_000, 520_000)], store.SCHEMAS["partitions"])
    doors = spark.createDataFrame([(1, i, "door", 0, x, 2_000) for i, x in ((11, 10_000), (12, 510_000))], store.SCHEMAS["doors"])
    moves = spark.createDataFrame([(1, d, a, b) for d, x, y in ((11, 1, 2), (12, 2, 3)) for a, b in ((x, y), (y, x))], store.SCHEMAS["moves"])
    return V.Venue(spark, "long-leg", 1, "imported", parts, doors, moves)


def test_long_leg_is_walked(spark):
    venue = corridor(spark)
    pairs = spark.createDataFrame([(1, 0, 5_000, 2_000, 0, 515_000, 2_000), (2, 0, 515_000, 1_000, 0, 5_000, 2_000), (3, 0, 5_000, 2_000, 0, 6_000, 2_000)], "qid long, s_floor long, s_x long, s_y long, t_floor long, t_x long, t_y long")
    want = dict(map(tuple, route.distance_query("dm", venue, pairs).collect()))
    assert want[1] == 510_000
    for method in ("ag", "lr"):
        assert dict(map(tuple, route.distance_query(method, venue, pairs).collect())) == want
