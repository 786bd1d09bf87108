"""The end of a generated pair is searched outwards from the door, by the wanted distance from the point."""

from collections import defaultdict

import pytest

from floorwalk import workload
from floorwalk.operators import range as ranges
from floorwalk.plans import matrix
from floorwalk.sources import venue as V


@pytest.mark.parametrize("s2t", (30_000, 90_000))
def test_ends_against_brute_force(spark, small, monkeypatch, s2t):
    base = V.build_venue(spark, small)
    points, things = V.query_points(base), V.objects(base)
    away = {(r.qid, r.object_id): r.dist_mm for r in ranges.brute_range(base, points, things, 10**9).collect()}
    doors = {(r.a_door, r.b_door): r.dist_mm for r in matrix.matrix_dist(base).collect()}
    placed = ranges.placed_points(base, points)
    reach = {(r.qid, r.door): r.dist for r in workload.point_labels("ag", base, placed).collect()}
    held, enters = defaultdict(list), defaultdict(set)
    for r in things.collect():
        held[r.part_id].append(r)
    for r in base.moves.collect():
        enters[r.door_id].add(r.to_part)
    want = {}
    for q in {q for q, _ in reach}:
        door = min((abs(d - s2t), x) for (p, x), d in reach.items() if p == q)[1]
        way = [(d, p) for (a, b), d in doors.items() if a == door for p in enters[b] if held[p]]
        parts = {p for d, p in way if d == min(way)[0]}
        _, _, end = min((abs(away[q, o.object_id] - s2t), o.object_id, o) for p in parts for o in held[p])
        want[q] = (end.floor, end.x_mm, end.y_mm)
    fresh = V.Venue(spark, small, base.floors, base.variant, base.partitions, base.doors, base.moves)
    monkeypatch.setattr(matrix, "DOOR_BUDGET", 0)  # no whole matrix is needed
    assert {r.qid: (r.t_floor, r.t_x, r.t_y) for r in workload.generated_pairs(fresh, s2t).collect()} == want
