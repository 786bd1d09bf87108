"""Rows of few doors, with ranks and hops, are those of the whole matrix and are made without it."""

from floorwalk.plans import matrix
from floorwalk.sources import venue as V


def test_ranked_rows_of_few_doors(spark, small, monkeypatch):
    base = V.build_venue(spark, small)
    starts = base.doors.select("door_id").orderBy("door_id").limit(2)
    whole = matrix.door_matrix(base)
    want = {tuple(r) for r in whole.join(starts.withColumnRenamed("door_id", "a_door"), "a_door", "left_semi").select(*sorted(whole.columns)).collect()}
    fresh = V.Venue(spark, small, base.floors, base.variant, base.partitions, base.doors, base.moves)
    monkeypatch.setattr(matrix, "DOOR_BUDGET", 0)
    for venue in (fresh, base):
        found = matrix.door_matrix(venue, starts)
        assert {tuple(r) for r in found.select(*sorted(whole.columns)).collect()} == want
    assert "matrix" not in fresh.cache
