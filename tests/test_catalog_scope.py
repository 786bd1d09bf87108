"""Registered queries that once took a part of their doors, thresholds, methods or words."""

from floorwalk import catalog
from floorwalk.operators import extend
from floorwalk.operators.labels import METHODS, NAMES
from floorwalk.plans import relax
from floorwalk.operators import topology
from floorwalk.sources import venue as V


def test_kernel_from_every_door(spark, small):
    venue = V.build_venue(spark, small)
    found = sorted(map(tuple, catalog.queries()["kernel_relax_all"](spark, small).select("a_door", "b_door", "dist_mm").collect()))
    want = relax.all_pairs(topology.graph_legs(venue), venue.doors.select("door_id"), engine="square")
    assert found == sorted(map(tuple, want.select("a_door", "b_door", "dist_mm").collect()))
    assert {a for a, _, _ in found} == {r.door_id for r in venue.doors.collect()}


def test_all_thresholds(spark, small):
    assert sorted(r.gamma for r in catalog.queries()["border_report"](spark, small).collect()) == [4, 5, 6, 7]


def test_all_methods_of_task_a(spark, small):
    assert {r.method for r in catalog.queries()["bench_task_a"](spark, small).select("method").distinct().collect()} == {NAMES[m] for m in METHODS}


def test_all_methods_against_brute_force(spark, small, monkeypatch):
    asked, run = [], catalog.ranges.range_query
    monkeypatch.setattr(catalog.ranges, "range_query", lambda method, *rest: asked.append(method) or run(method, *rest))
    assert catalog.queries()["rq_disagreement"](spark, small).first().rows_different == 0
    assert set(asked) == set(METHODS)


def test_all_words(spark, small):
    venue = V.build_venue(spark, small)
    placed = extend.object_words(venue).join(V.objects(venue), "object_id").where("part_id is not null").select("word").distinct()
    found = catalog.queries()["node_words"](spark, small).select("word").distinct()
    assert found.count() > 2 and placed.exceptAll(found).isEmpty()
