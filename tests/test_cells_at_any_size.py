"""Cells and their hops do not depend on the size of the leg table, and parts of the ladder give what whole rows give."""

import random

from floorwalk.plans import border, relax
from floorwalk.sources import venue as V


def test_cells_keep_hops_beyond_the_limits(spark, small, monkeypatch):
    there = V.build_venue(spark, small)
    tree = border.build_border_tree(there)
    fresh = V.Venue(spark, small, 5, "base", there.partitions, there.doors, there.moves)
    for module in (relax, border):
        monkeypatch.setattr(module, "is_local", lambda legs: False)
    again = border.build_border_tree(fresh)
    for name in ("inner", "deep_out"):
        left, right = ({tuple(r) for r in getattr(t, name).collect()} for t in (tree, again))
        assert left == right and any(r[-1] is not None for r in right), name


def test_parts_of_the_ladder_give_whole_rows(spark, monkeypatch):
    rng = random.Random(11)
    n = 60
    legs = {(a, b): rng.choice([0, 3, 5, 8]) for a, b in ((rng.randrange(n), rng.randrange(n)) for _ in range(150)) if a != b}
    frame = spark.createDataFrame([(a, b, d) for (a, b), d in legs.items()], "a_door long, b_door long, leg_mm long")
    whole = {tuple(r) for r in relax.local_hops(spark.range(n).withColumnRenamed("id", "door_id"), frame).collect()}
    asked = [(b, rng.sample(range(n), rng.choice([1, 3, 20, 50]))) for b in range(n)]
    for name, size in (("DEAL_DOORS", 7), ("BLOCK_CELLS", 90)):
        monkeypatch.setattr(relax, name, size)
    found = [tuple(r) for r in relax.local_hops(spark.createDataFrame(asked, "door_id long, starts array<long>"), frame).collect()]
    want = {(b, a) for b, starts in asked for a in starts}
    assert len(found) == len(set(found)) and set(found) == {r for r in whole if (r[1], r[0]) in want}
