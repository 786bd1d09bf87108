"""Searches from all doors in one climb and descent, and merges of long chains of nodes in few rounds."""

import random

import numpy as np
import pandas as pd

from floorwalk.plans import border, relax

LEGS = "a_door long, b_door long, leg_mm long"


def test_long_chain_both_ways(spark):
    n = 600
    legs = spark.createDataFrame([(i, i + 1, 7) for i in range(n - 1)] + [(i + 1, i, 9) for i in range(n - 1)], LEGS)
    doors = spark.range(n).withColumnRenamed("id", "door_id")
    wrong = "dist_mm <> case when b_door > a_door then 7 * (b_door - a_door) else 9 * (a_door - b_door) end"
    found = relax.all_pairs(legs, doors, "local")
    assert (found.count(), found.where(wrong).count()) == (n * n, 0)
    hops = relax.local_hops(doors, legs)
    assert (hops.count(), hops.where(wrong).count()) == (n * n, 0)
    assert hops.where("not first_hop <=> if(a_door = b_door, null, a_door + sign(b_door - a_door))").count() == 0


def test_ladder_on_random_one_way_graphs():
    rng = random.Random(3)
    for _ in range(20):
        n = rng.randint(2, 40)
        rows = [(rng.randrange(n), rng.randrange(n), rng.choice([0, 3, 5, 11, 40])) for _ in range(rng.randint(1, 3 * n))]
        graph = relax._Legs(pd.DataFrame(rows, columns=["a_door", "b_door", "leg_mm"]), np.arange(n))
        label = np.full((n, n), relax.FAR)
        label[np.arange(n), np.arange(n)] = 0
        for backward in (False, True):
            want = graph.settle(label.copy(), lambda new, live: new < relax.FAR, backward)
            assert (relax._Ladder(graph).settle(label, backward) == want).all()


def test_only_the_starts_asked_for(spark):
    legs = spark.createDataFrame([(1, 2, 5), (2, 3, 0), (3, 4, 5), (4, 1, 9)], LEGS)
    whole = {tuple(r) for r in relax.local_hops(spark.createDataFrame([(3,), (4,)], "door_id long"), legs).collect()}
    asked = relax.local_hops(spark.createDataFrame([(3, [1, 99]), (4, [2, 4])], "door_id long, starts array<long>"), legs)
    assert {tuple(r) for r in asked.collect()} == {r for r in whole if r[:2] in {(1, 3), (2, 4), (4, 4)}}


def test_chains_of_nodes_merge_in_few_rounds(spark, monkeypatch):
    n, calls = 200, []
    access = spark.createDataFrame([(i + k, i) for i in range(n - 1) for k in (0, 1)], "node_id long, door_id long")
    members = spark.range(n).withColumnRenamed("id", "node_id")
    real = border.materialize
    monkeypatch.setattr(border, "materialize", lambda frame: calls.append(1) or real(frame))
    up = border._merge(access, members, 1).collect()
    assert {r["parent_id"] for r in up} == {border.LEVEL_STEP} and len(up) == n
    assert len(calls) < 20


def test_hops_of_pairs_are_those_of_whole_rows():
    rng = random.Random(5)
    for _ in range(30):
        n = rng.randint(2, 30)
        rows = [(rng.randrange(n), rng.randrange(n), rng.choice([0, 0, 3, 3, 6])) for _ in range(rng.randint(1, 4 * n))]
        table = pd.DataFrame([r for r in rows if r[0] != r[1]], columns=["a_door", "b_door", "leg_mm"]).astype("int64").groupby(["a_door", "b_door"], as_index=False).min()
        graph = relax._Legs(table, np.arange(n))
        label = np.full((n, n), relax.FAR)
        label[np.arange(n), np.arange(n)] = 0
        rest = relax._Ladder(graph).settle(label, backward=True)
        tight = (rest[:, graph.target] < relax.FAR) & (rest[:, graph.source] == graph.length + rest[:, graph.target])
        first, stride = graph.hops(tight, np.eye(n, dtype=bool))
        b, a = np.nonzero((rest < relax.FAR) & ~np.eye(n, dtype=bool))
        ours = graph.pair_hops(rest, b, a, b)
        assert (ours[0] == first[b, a]).all() and (ours[1] == stride[b, a]).all()


def test_hops_of_pairs_leave_other_doors_alone(spark, monkeypatch):
    def refuse(*_):
        raise AssertionError("hops of whole rows were made")

    monkeypatch.setattr(relax._Legs, "hops", refuse)
    legs = spark.createDataFrame([(1, 2, 5), (2, 3, 0), (3, 4, 5), (4, 1, 9)], LEGS)
    asked = relax.local_hops(spark.createDataFrame([(3, [1, 99]), (4, [2, 4])], "door_id long, starts array<long>"), legs)
    assert {tuple(r) for r in asked.collect()} == {(1, 3, 5, 2, 2), (2, 4, 5, 3, None), (4, 4, 0, None, None)}


def test_rounds_of_all_doors_run_within_tasks(spark, monkeypatch):
    legs = spark.createDataFrame([(i, (i + k) % 50, 3 * k + i % 2) for i in range(49) for k in (1, 7)], LEGS)
    doors = spark.range(51).withColumnRenamed("id", "door_id")
    want = {tuple(r) for r in relax.all_pairs(legs, doors, "local").collect()}
    jobs = {tuple(r) for r in relax.relax(doors.selectExpr("door_id as qid", "door_id as door", "0L as dist"), legs).collect()}
    monkeypatch.setattr(relax, "relax", lambda *_: 1 / 0)
    assert {tuple(r) for r in relax.all_pairs(legs, doors, "relax").collect()} == want == jobs


def test_doors_are_dealt_over_tasks_at_any_number_of_shuffle_partitions(spark):
    before = spark.conf.get("spark.sql.shuffle.partitions")
    try:
        for n in ("4", "64"):
            spark.conf.set("spark.sql.shuffle.partitions", n)
            rows = relax._dealt(spark.range(200).withColumnRenamed("id", "door_id").distinct())
            assert rows.selectExpr("spark_partition_id() as p").distinct().count() >= spark.sparkContext.defaultParallelism
    finally:
        spark.conf.set("spark.sql.shuffle.partitions", before)


def test_doubling_of_a_core_on_random_one_way_graphs(spark, monkeypatch):
    rng = random.Random(5)
    n = 40
    rows = [(rng.randrange(n), rng.randrange(n), rng.choice([0, 3, 5, 11, 40])) for _ in range(90)]
    legs = spark.createDataFrame(rows, LEGS).groupBy("a_door", "b_door").min("leg_mm").toDF("a_door", "b_door", "leg_mm")
    doors = spark.range(n + 1).withColumnRenamed("id", "door_id")  # one door without a leg
    want = {tuple(r) for r in relax.all_pairs(legs, doors, "local").collect()}
    for core, most in ((0, 0), (6, 36), (128, (n + 1) ** 2)):
        monkeypatch.setattr(relax, "CORE_DOORS", core)
        with monkeypatch.context() as m:
            real = relax.doubled
            m.setattr(relax, "doubled", lambda frame: sizes.append(frame.count()) or real(frame))
            sizes = []
            assert {tuple(r) for r in relax.all_pairs(legs, doors, "square").collect()} == want
            assert all(size <= most for size in sizes)
