"""Timed routes: rounds within tasks give what a job per round gives, closed doors and late openings included."""

from floorwalk.operators import extend
from floorwalk.plans import relax
from floorwalk.sources import venue as V


def test_rounds_within_tasks_are_those_of_jobs(spark, monkeypatch):
    venue = V.build_venue(spark, "/root/testdata/sf0.001")
    pairs = V.query_pairs(venue)
    for depart in (0, 6 * 3600 - 60, 7 * 3600 + 1800):
        with monkeypatch.context() as m:
            m.setattr(relax, "ROUND_LEGS", -1)
            want = {tuple(r) for r in extend.route_timed(venue, pairs, depart).collect()}
        with monkeypatch.context() as m:
            m.setattr(extend, "_timed_jobs", lambda *_: 1 / 0)
            assert {tuple(r) for r in extend.route_timed(venue, pairs, depart).collect()} == want and want
