"""Keyword routes: searches within tasks give what a job per round gives, on random graphs and on the venue."""

import random

from floorwalk import catalog
from floorwalk.operators import extend
from floorwalk.plans import relax
from floorwalk.sources import venue as V


def _ranked(frame, k):
    best = {}
    for qid, total, path in {(r[0], r[1], tuple(r[2])) for r in frame.collect()}:
        best.setdefault(qid, []).append((total, path))
    return {qid: sorted(rows)[:k] for qid, rows in best.items()}


def test_searches_on_random_graphs_with_ties(spark):
    rng = random.Random(11)
    for turn in range(2):
        n = 12
        edges = {(rng.randrange(n), rng.randrange(n), rng.choice([0, 0, 1, 2])): rng.choice([0, 1, 1, 2]) if turn else rng.choice([1, 2]) for _ in range(40)}
        legs = spark.createDataFrame([(a, b, d, m) for (a, b, m), d in edges.items() if a != b], "a_door long, b_door long, leg_mm long, seen long")
        starts = spark.createDataFrame([(q, rng.randrange(n + 1), rng.randrange(3), q % 2) for q in range(12)], "qid long, door long, dist long, mask long").dropDuplicates(["qid", "door"])
        ends = spark.createDataFrame([(q, d, rng.randrange(3), q % 3) for q in range(12) for d in rng.sample(range(n + 1), 2)], "qid long, door long, rest long, mask long")
        want = _ranked(extend._cover_jobs(starts, ends, legs, 3, 1000), 2)
        assert _ranked(relax.cover_ways(starts, ends, legs, 3, 2), 2) == want and want


def test_keyword_route_needs_no_job_per_round(spark, monkeypatch):
    venue = V.build_venue(spark, "/root/testdata/sf0.001")
    ask = lambda: {tuple(map(str, r)) for r in extend.keyword_route(venue, V.query_pairs(venue), V.objects(venue), extend.object_words(venue), list(catalog.WORDS), 2).collect()}
    with monkeypatch.context() as m:
        m.setattr(relax, "ROUND_LEGS", -1)
        want = ask()
    monkeypatch.setattr(extend, "_cover_jobs", lambda *_: 1 / 0)
    assert ask() == want and want


def test_words_asked_for_are_those_of_all(spark):
    venue = V.build_venue(spark, "/root/testdata/sf0.001")
    every = {tuple(r) for r in extend.object_words(venue).collect()}
    for words in (catalog.WORDS, ("green",), ()):
        assert {tuple(r) for r in extend.object_words(venue, words).collect()} == {r for r in every if r[1] in words}
