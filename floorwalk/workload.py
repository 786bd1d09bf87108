"""Experiment workloads: query generators and the grids of the benchmark tasks on the given tables."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from floorwalk.operators import knn, metrics, route
from floorwalk.operators import range as ranges
from floorwalk.operators.labels import METHODS, NAMES, cells_entered, matrix_labels, point_labels
from floorwalk.operators.topology import door_legs, exit_legs, graph_legs
from floorwalk.plans.border import build_border_tree
from floorwalk.plans.matrix import door_matrix, matrix_rows
from floorwalk.plans.rtree import build_rtree
from floorwalk.sources.scratch import materialize
from floorwalk.sources import venue as V

FLOORS, OBJECTS = (3, 5, 7, 9), (500, 1000, 1500, 2000, 2500)
RADII, KS, S2T = (20_000, 40_000, 60_000, 80_000, 100_000), (1, 5, 10, 50, 100), (30_000, 60_000, 90_000, 120_000, 150_000)
TOPOLOGY, DECOMPOSITION = ("sparse", "base", "dense"), ("merged", "nocut", "base", "fine")
SCHEMA = "task string, variant string, method string, query string, param string, value string, metric string, amount double, unit string"


def s2t_pairs(venue: V.Venue, targets: tuple[int, ...] = S2T, n: int = 10) -> DataFrame:
    """(s2t_mm, qid, dist_mm): for each wanted distance the n natural pairs that come nearest to it, ties by qid."""
    found = route.distance_query("dm", venue, V.query_pairs(venue)).where("dist_mm is not null")
    wanted = F.explode(F.array(*[F.lit(t).cast("long") for t in targets]))
    order = Window.partitionBy("s2t_mm").orderBy(F.abs(F.col("dist_mm") - F.col("s2t_mm")), "qid")
    return found.withColumn("s2t_mm", wanted).withColumn("r", F.row_number().over(order)).where(F.col("r") <= n).drop("r")


def generated_pairs(venue: V.Venue, s2t_mm: int, n: int = 10) -> DataFrame:
    """Pairs by the door-then-point rule: the door whose distance from the point comes nearest to the wanted one, then from
    this door outwards the first cells that hold objects, and of these objects the one whose distance from the point comes
    nearest to the wanted one, ties by id. Only the matrix rows that points and doors ask for are made."""
    points = V.query_points(venue, n)
    placed = ranges.placed_points(venue, points)
    asked = exit_legs(venue, placed).select(F.col("door").alias("door_id"))
    reach = materialize(matrix_labels(venue, placed, matrix=matrix_rows(venue, asked)))
    near = materialize(reach.withColumn("r", F.row_number().over(Window.partitionBy("qid").orderBy(F.abs(F.col("dist") - s2t_mm), "door"))).where("r = 1").select("qid", "door"))
    ahead = matrix_rows(venue, near.select(F.col("door").alias("door_id"))).select(F.col("a_door").alias("start"), F.col("b_door").alias("door"), F.col("dist_mm").alias("dist"))
    things = V.objects(venue)
    cells = cells_entered(venue, near.withColumnRenamed("door", "start").join(ahead, "start")).join(things.select("part_id").distinct(), "part_id", "left_semi")
    spots = materialize(cells.join(cells.groupBy("qid").agg(F.min("dist").alias("dist")), ["qid", "dist"]).select("qid", "part_id").distinct().join(things, "part_id"))
    scored = ranges.score_objects(venue, reach, placed, things.join(spots.select("object_id").distinct(), "object_id", "left_semi").select(*things.columns), None)
    order = Window.partitionBy("qid").orderBy(F.abs(F.col("dist_mm") - s2t_mm), "object_id")
    chosen = spots.join(scored, ["qid", "object_id"]).withColumn("r", F.row_number().over(order)).where("r = 1")
    source = points.select("qid", F.col("floor").alias("s_floor"), F.col("x_mm").alias("s_x"), F.col("y_mm").alias("s_y"))
    return source.join(chosen.select("qid", F.col("floor").alias("t_floor"), F.col("x_mm").alias("t_x"), F.col("y_mm").alias("t_y")), "qid")


def _row(task, variant, method, query, param, value, metric, amount, unit):
    return (task, variant, NAMES.get(method, method), query, param, str(value), metric, float(amount), unit)


def _run(method: str, query: str, venue: V.Venue, r: int, k: int, objects: DataFrame, pairs: DataFrame | None = None) -> float:
    points = V.query_points(venue)
    if query == "RQ":
        return metrics.timed(lambda: ranges.range_query(method, venue, points, objects, r))
    if query == "KNN":
        return metrics.timed(lambda: knn.knn_query(method, venue, points, objects, k))
    return metrics.timed(lambda: route.route_query(method, venue, pairs if pairs is not None else V.query_pairs(venue)))


BUILDS = {"ag": graph_legs, "dm": door_matrix, "lr": lambda v: build_rtree(v).levels[0], "bt": lambda v: build_border_tree(v).inner, "btd": lambda v: build_border_tree(v).deep_out}


def run_task(spark, sf_dir: str, task: str, methods: tuple[str, ...] = METHODS, other_dir: str | None = None) -> DataFrame:
    """One benchmark task (A, B1 ... B7) as a tidy table: construction seconds and sizes (A), seconds of a batch of
    queries, bytes at query time and doors visited. other_dir: tables of a second venue for B2."""
    out = []
    base = lambda floors=5, variant="base", d=sf_dir: V.build_venue(spark, d, floors, variant)

    def sizes(venue, param, value):
        for row in metrics.model_size(venue, methods).groupBy("method").agg(F.sum("n_bytes").alias("b")).collect():  # one row per method
            out.append((task, venue.variant, row["method"], "-", param, str(value), "model_size", float(row["b"]), "bytes"))

    def memory(venue, param, value, method, r):
        row = metrics.query_memory(method, venue, V.query_points(venue), r).first()
        out.append(_row(task, venue.variant, method, "RQ", param, value, "memory", row["resident_bytes"] + row["read_bytes"] + row["label_bytes"], "bytes"))

    def nvd(venue, param, value, method, pairs=None):
        pairs = V.query_pairs(venue) if pairs is None else pairs
        source, target = route.sides(venue, pairs)
        best = route.distance_query(method, venue, pairs).where("dist_mm is not null")
        out.append(_row(task, venue.variant, method, "SPDQ", param, value, "nvd", route.visited_doors(method, venue, source, target, best).agg(F.avg("nvd")).first()[0] or 0, "doors"))

    def queries(venue, param, value, kinds=("RQ", "KNN", "SPDQ"), r=60_000, k=10, objects=None, pairs=None):
        for method in methods:
            for kind in kinds:
                out.append(_row(task, venue.variant, method, kind, param, value, "time", _run(method, kind, venue, r, k, V.objects(venue) if objects is None else objects, pairs), "s"))
            if "RQ" in kinds and venue.override is None:
                memory(venue, param, value, method, r)
            if "SPDQ" in kinds:
                nvd(venue, param, value, method, pairs)

    if task == "A":
        for n in FLOORS:
            venue = base(n)
            fresh = V.Venue(spark, sf_dir, n, "base", venue.partitions, venue.doors, venue.moves)
            for method in methods:
                out.append(_row(task, "base", method, "-", "floors", n, "build_time", metrics.timed(lambda m=method, v=fresh: BUILDS[m](v)), "s"))
            sizes(venue, "floors", n)
    elif task == "B1":
        for n in FLOORS:
            queries(base(n), "floors", n)
    elif task == "B2":
        for d in filter(None, (sf_dir, other_dir)):
            have = V.objects(base(d=d)).count()
            for n in OBJECTS:
                if n <= have:
                    queries(base(d=d), "objects", n, ("RQ", "KNN"), objects=V.objects(base(d=d), n))
    elif task == "B3":
        for r in RADII:
            queries(base(), "r_mm", r, ("RQ",), r=r)
    elif task == "B4":
        for k in KS:
            queries(base(), "k", k, ("KNN",), k=k)
    elif task == "B5":
        chosen = s2t_pairs(base())
        for s2t in S2T:
            pairs = V.query_pairs(base()).join(chosen.where(F.col("s2t_mm") == s2t).select("qid"), "qid", "left_semi")
            queries(base(), "s2t_mm", s2t, ("SPDQ",), pairs=pairs)
    elif task in ("B6", "B7"):
        for variant in TOPOLOGY if task == "B6" else DECOMPOSITION:
            venue = base(5, variant)
            sizes(venue, "variant", variant)
            queries(venue, "variant", variant, ("SPDQ",) if variant == "merged" else ("RQ", "KNN", "SPDQ"))
    else:
        raise ValueError(f"no such task: {task}")
    return spark.createDataFrame(out, SCHEMA)


# Counters of the tasks: what does not depend on the machine, for comparison with SQL.


def _union(frames: list[DataFrame]) -> DataFrame:
    whole = frames[0]
    for frame in frames[1:]:
        whole = whole.union(frame)
    return whole


def radius_counters(venue: V.Venue) -> DataFrame:
    """B3: (method, r_mm, labels, answers): doors labelled and objects found within each radius."""
    points, rows = V.query_points(venue), []
    placed = ranges.placed_points(venue, points)
    for method in METHODS:
        for r in RADII:
            found = point_labels(method, venue, placed, r)
            answers = ranges.score_objects(venue, found, placed, V.objects(venue), r).agg(F.count("*").alias("answers"))
            rows.append(found.agg(F.count("*").alias("labels")).crossJoin(answers).select(F.lit(NAMES[method]).alias("method"), F.lit(r).cast("long").alias("r_mm"), "labels", "answers"))  # two one-row tables
    return _union(rows)


def neighbour_counters(venue: V.Venue) -> DataFrame:
    """B4: (method, k, answers, sum_mm) for each k."""
    rows = []
    for method in METHODS:
        most = materialize(knn.knn_query(method, venue, V.query_points(venue), V.objects(venue), max(KS)))
        for k in KS:
            rows.append(most.where(F.col("rank") <= k).agg(F.count("*").alias("answers"), F.sum("dist_mm").alias("sum_mm")).select(F.lit(NAMES[method]).alias("method"), F.lit(k).alias("k"), "answers", "sum_mm"))
    return _union(rows)


def object_counters(venue: V.Venue) -> DataFrame:
    """B2: (method, objects, answers) of range queries over the first objects."""
    rows = []
    for method in METHODS:
        found = materialize(ranges.range_query(method, venue, V.query_points(venue), V.objects(venue), 60_000))
        rows += [found.where(F.col("object_id") < n).agg(F.count("*").alias("answers")).select(F.lit(NAMES[method]).alias("method"), F.lit(n).alias("objects"), "answers") for n in OBJECTS]
    return _union(rows)


def distance_counters(venue: V.Venue, methods: tuple[str, ...] = ("ag", "dm", "lr")) -> DataFrame:
    """B5: (method, s2t_mm, pairs, sum_mm, nvd) over the pairs chosen for each distance."""
    chosen, pairs, rows = materialize(s2t_pairs(venue)), V.query_pairs(venue), []
    for method in methods:
        best = materialize(route.distance_query(method, venue, pairs).where("dist_mm is not null"))
        seen = route.visited_doors(method, venue, *route.sides(venue, pairs), best)
        per = chosen.select("s2t_mm", "qid").join(best, "qid").join(seen, "qid").groupBy("s2t_mm")
        rows.append(per.agg(F.count("*").alias("pairs"), F.sum("dist_mm").alias("sum_mm"), F.sum("nvd").alias("nvd")).select(F.lit(NAMES[method]).alias("method"), "s2t_mm", "pairs", "sum_mm", "nvd"))
    return _union(rows)


def variant_counters(spark, sf_dir: str, variants: tuple[str, ...], method: str = "dm") -> DataFrame:
    """B6 and B7: (variant, doors, legs, reached, sum_mm): size of the graph and distances of the natural pairs."""
    rows = []
    for variant in variants:
        venue = V.build_venue(spark, sf_dir, 5, variant)
        found = route.distance_query(method if venue.override is None else "ag", venue, V.query_pairs(venue)).agg(F.count("dist_mm").alias("reached"), F.sum("dist_mm").alias("sum_mm"))
        size = venue.doors.agg(F.count("*").alias("doors")).crossJoin(door_legs(venue).agg(F.count("*").alias("legs")))
        rows.append(size.crossJoin(found).select(F.lit(variant).alias("variant"), "doors", "legs", "reached", "sum_mm"))  # one-row tables
    return _union(rows)


def floor_counters(spark, sf_dir: str) -> DataFrame:
    """A and B1: (floors, doors, matrix_rows, sum_mm, max_mm) of the towers."""
    rows = []
    for n in FLOORS:
        venue = V.build_venue(spark, sf_dir, n)
        whole = door_matrix(venue).agg(F.count("*").alias("matrix_rows"), F.sum("dist_mm").alias("sum_mm"), F.max("dist_mm").alias("max_mm"))
        rows.append(venue.doors.agg(F.count("*").alias("doors")).crossJoin(whole).select(F.lit(n).alias("floors"), "doors", "matrix_rows", "sum_mm", "max_mm"))  # one-row tables
    return _union(rows)


def stats_of_variants(spark, sf_dir: str, variants: tuple[str, ...] = ("sparse", "base", "dense", "fine", "nocut")) -> DataFrame:
    """The dataset table: venue statistics of every variant."""
    return _union([metrics.venue_stats(V.build_venue(spark, sf_dir, 5, v)).withColumn("variant", F.lit(v)) for v in variants])


def growth(spark, sf_dir: str, low: str = "sparse", high: str = "dense") -> DataFrame:
    """(method, ratio): how many more doors a range query labels in one variant than in another.

    Of a door matrix that is not stored yet, only the rows that the points ask for are made.
    """
    rows = []

    def found(method: str, venue: V.Venue, placed: DataFrame) -> DataFrame:
        if method != "dm":
            return point_labels(method, venue, placed, 60_000)
        asked = exit_legs(venue, placed).select(F.col("door").alias("door_id"))
        return matrix_labels(venue, placed, 60_000, matrix=matrix_rows(venue, asked))

    for variant in (low, high):
        venue = V.build_venue(spark, sf_dir, 5, variant)
        placed = ranges.placed_points(venue, V.query_points(venue))
        rows += [found(m, venue, placed).agg(F.count("*").cast("double").alias("amount")).select(F.lit(NAMES[m]).alias("method"), F.lit(variant).alias("variant"), "amount") for m in METHODS]
    return metrics.ratio_report(_union(rows), "variant", low, high)


def border_report(spark, sf_dir: str, gammas: tuple[int, ...] = (4, 5, 6, 7)) -> DataFrame:
    """Leaves, height and cells of border trees over thresholds of crucial partitions."""
    rows = []
    for gamma in gammas:
        tree = build_border_tree(V.build_venue(spark, sf_dir), gamma)
        rows.append((gamma, tree.members.select("leaf").distinct().count(), tree.height, *tree.cell_counts()))
    return spark.createDataFrame(rows, "gamma int, leaves long, height int, leaf_cells long, inner_cells long")
