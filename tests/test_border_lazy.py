"""The border tree over arrays equals the relational one, and its hierarchy is made without any cell."""

import random

import numpy as np
import pandas as pd

from floorwalk import catalog
from floorwalk.plans import border, matrix, relax
from floorwalk.sources import venue as V


def rows(frame, *columns):
    return sorted(map(tuple, frame.select(*columns).collect()), key=str)


def test_hierarchy_over_arrays_is_the_relational_one(spark):
    for variant in ("base", "nocut"):
        venue = V.build_venue(spark, "/root/testdata/sf0.001", 5, variant)
        for gamma in (6, 1_000):
            ours, theirs = border._local_hierarchy(venue, gamma), border._relational_hierarchy(venue, gamma)
            for i, columns in enumerate((("part_id", "leaf"), ("node_id", "level", "parent_id", "ancestors"), ("node_id", "door_id"), ("node_id", "ancestors"))):
                assert rows(ours[i], *columns) == rows(theirs[i], *columns)
                assert ours[i].select(*columns).dtypes == theirs[i].select(*columns).dtypes
            assert ours[4] == theirs[4]


def test_nodes_need_no_cells(spark, monkeypatch):
    def refuse(*_):
        raise AssertionError("cells were made")

    monkeypatch.setattr(border, "local_hops", refuse)
    tree = border._build(V.build_venue(spark, "/root/testdata/sf0.001"), 6)
    assert tree.nodes.count() and tree.members.count() and tree.access.count()


def test_hops_need_no_ranks(spark, monkeypatch):
    def refuse(*_):
        raise AssertionError("rows were ranked")

    venue = V.build_venue(spark, "/root/testdata/sf0.001")
    whole = rows(matrix.door_matrix(venue), "a_door", "b_door", "dist_mm", "first_hop", "stride_hop")
    fresh = V.Venue(spark, venue.sf_dir, venue.floors, "fresh", venue.partitions, venue.doors, venue.moves)
    monkeypatch.setattr(matrix, "with_ranks", refuse)
    assert rows(matrix.door_hops(fresh), "a_door", "b_door", "dist_mm", "first_hop", "stride_hop") == whole
    assert catalog._cell_hops(fresh).count() == sum(1 for r in whole if r[3] is not None)


def test_cells_are_counted_without_making_them(spark, monkeypatch):
    venue = V.build_venue(spark, "/root/testdata/sf0.001")
    fresh = V.Venue(spark, venue.sf_dir, venue.floors, "counted", venue.partitions, venue.doors, venue.moves)
    for gamma in (4, 1_000):
        made = border._build(venue, gamma)
        want = (made.leaf_out.count() + made.leaf_in.count(), made.inner.count())
        with monkeypatch.context() as m:
            m.setattr(border, "local_hops", lambda *_: 1 / 0)
            assert border._build(fresh, gamma).cell_counts() == want


def test_reach_on_random_one_way_graphs():
    rng = random.Random(7)
    for _ in range(40):
        n = rng.randint(2, 25)
        rows = [(rng.randrange(n), rng.randrange(n), 1) for _ in range(rng.randint(1, 2 * n))]
        graph = relax._Legs(pd.DataFrame(rows, columns=["a_door", "b_door", "leg_mm"]), np.arange(n))
        label = np.full((n, n), relax.FAR)
        label[np.arange(n), np.arange(n)] = 0
        a, b = np.indices((n, n)).reshape(2, -1)
        assert (border._Reach(graph)(a, b) == (relax._Ladder(graph).settle(label) < relax.FAR).ravel()).all()


def test_rows_of_few_doors_need_no_matrix(spark, monkeypatch):
    venue = V.build_venue(spark, "/root/testdata/sf0.001")
    fresh = V.Venue(spark, venue.sf_dir, venue.floors, "few", venue.partitions, venue.doors, venue.moves)
    starts = venue.doors.select("door_id").orderBy("door_id").limit(3)
    want = rows(matrix.door_matrix(venue).join(starts.withColumnRenamed("door_id", "a_door"), "a_door", "left_semi"), "a_door", "b_door", "dist_mm")
    assert rows(matrix.matrix_rows(venue, starts), "a_door", "b_door", "dist_mm") == want
    monkeypatch.setattr(matrix, "door_matrix", lambda *_: 1 / 0)
    assert rows(matrix.matrix_rows(fresh, starts), "a_door", "b_door", "dist_mm") == want
