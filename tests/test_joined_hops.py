"""First hops of a matrix by columns within tasks are those of the joins, for parts of a matrix and legs of length 0 too."""

import random

from floorwalk.plans import matrix, relax


def test_columns_give_what_joins_give(spark, monkeypatch):
    rng = random.Random(8)
    rows = {(a, b): rng.choice([0, 0, 3, 5, 8]) for a, b in ((rng.randrange(30), rng.randrange(30)) for _ in range(110)) if a != b}
    legs = spark.createDataFrame([(a, b, d) for (a, b), d in rows.items()], "a_door long, b_door long, leg_mm long")
    whole = relax.all_pairs(legs, spark.range(32).withColumnRenamed("id", "door_id"), "local")
    for part in (whole, whole.where("(a_door * 7 + b_door) % 5 <> 0"), whole.where("b_door < 0")):
        part = spark.createDataFrame(part.collect(), whole.schema)
        with monkeypatch.context() as m:
            m.setattr(matrix, "is_local", lambda _: False)
            want = {tuple(r) for r in matrix.first_hops(part, legs).collect()}
        with monkeypatch.context() as m:
            m.setattr(relax, "BLOCK_CELLS", 400)
            found = matrix.first_hops(part, legs)
            assert {tuple(r) for r in found.collect()} == want
        assert "Join" not in found._jdf.queryExecution().toString()
