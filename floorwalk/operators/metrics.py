"""Cost and accuracy measures: model size, construction time, visited doors, pruning, predicted work, exactness."""

from __future__ import annotations

import math
import time

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from floorwalk.operators.labels import NAMES
from floorwalk.operators.topology import crucial_parts, door_legs, door_reach, dv_counts
from floorwalk.plans.border import GAMMA, build_border_tree
from floorwalk.plans.matrix import door_matrix
from floorwalk.plans.rtree import build_rtree, rt_links, skeleton
from floorwalk.sources.venue import Venue

ID, NUMBER, HOPS, LABEL = 8, 8, 16, 24


def venue_stats(venue: Venue, gamma: int = GAMMA) -> DataFrame:
    """floors, partitions, doors, hallways, crucial, q1, q2, q3, max_dv (quartiles of doors per partition, discrete)."""
    dv = dv_counts(venue)
    quart = dv.agg(*[F.percentile_disc("dv", q).cast("long").alias(n) for q, n in ((0.25, "q1"), (0.5, "q2"), (0.75, "q3"))], F.max("dv").alias("max_dv")) if hasattr(F, "percentile_disc") else None
    if quart is None:
        dv.createOrReplaceTempView("floorwalk_dv")
        quart = venue.spark.sql("select cast(percentile_disc(0.25) within group (order by dv) as bigint) q1, cast(percentile_disc(0.5) within group (order by dv) as bigint) q2, cast(percentile_disc(0.75) within group (order by dv) as bigint) q3, max(dv) max_dv from floorwalk_dv")
    parts = venue.partitions.where("part_id <> 0").agg(F.count_distinct("floor").alias("floors"), F.count("*").alias("partitions"), F.sum((F.col("kind") == "hall").cast("long")).alias("hallways"))
    doors = venue.doors.agg(F.count("*").alias("doors"))
    crucial = crucial_parts(venue, gamma).agg(F.count("*").alias("crucial"))
    return parts.crossJoin(doors).crossJoin(crucial).crossJoin(quart).select("floors", "partitions", "doors", "hallways", "crucial", "q1", "q2", "q3", "max_dv")  # five one-row tables


def dv_histogram(venue: Venue) -> DataFrame:
    return dv_counts(venue).groupBy("kind", "dv").agg(F.count("*").alias("n"))


def components(method: str, venue: Venue) -> dict[str, tuple[DataFrame, int]]:
    """Tables of a model and the bytes of one row of each; objects are not part of a model."""
    base = {"door_reach": (door_reach(venue), 2 * ID + NUMBER), "door_legs": (door_legs(venue), 3 * ID + NUMBER), "moves": (venue.moves, 3 * ID)}
    if method == "ag":
        return base
    if method == "dm":
        return base | {"matrix": (door_matrix(venue), 2 * ID + NUMBER), "ranks": (door_matrix(venue), 4), "hops": (door_matrix(venue), HOPS)}
    if method == "lr":
        tree = build_rtree(venue)
        levels = {f"rt_level{i}": (t, ID * 2 + 4 * NUMBER) for i, t in enumerate(tree.levels)}
        return base | levels | {"links": (rt_links(venue).select(F.explode("links")), 2 * ID), "skeleton": (skeleton(venue), 2 * ID + NUMBER)}
    tree = build_border_tree(venue)
    cells = {"members": (tree.members, 2 * ID), "nodes": (tree.nodes, 2 * ID), "access": (tree.access, 2 * ID)}
    cells |= {name: (getattr(tree, name), 3 * ID + NUMBER + HOPS) for name in ("leaf_out", "leaf_in", "leaf_pairs", "inner")}
    if method == "btd":
        cells |= {"deep_out": (tree.deep_out, 4 * ID + NUMBER + HOPS), "deep_in": (tree.deep_in, 4 * ID + NUMBER + HOPS)}
    return base | cells


def model_size(venue: Venue, methods: tuple[str, ...] = ("ag", "dm", "lr", "bt", "btd")) -> DataFrame:
    """(method, component, n_rows, n_bytes): logical size, rows times fixed widths."""
    out = None
    for method in methods:
        for name, (frame, width) in components(method, venue).items():
            row = frame.agg(F.count("*").alias("n_rows")).select(F.lit(NAMES[method]).alias("method"), F.lit(name).alias("component"), "n_rows", (F.col("n_rows") * width).alias("n_bytes"))
            out = row if out is None else out.union(row)
    return out


def timed(action) -> float:
    """Seconds of building or of running: results go to a sink that keeps nothing."""
    start = time.time()
    frame = action()
    if isinstance(frame, DataFrame):
        frame.write.format("noop").mode("overwrite").save()
    return time.time() - start


FEATURES = (
    ("access_graph", "no", "graph and maps", "scan", "best-first", "SPQ, SDQ"),
    ("door_matrix", "yes", "matrix", "scan", "loop", "RQ, KNN"),
    ("layered_rtree", "no", "tree and links", "R-tree", "best-first", "RQ, KNN"),
    ("border_tree", "yes", "tree and matrices", "scan", "common ancestor", "RQ, KNN, SPQ, SDQ"),
    ("border_tree_deep", "yes", "tree and matrices", "scan", "common ancestor", "RQ, KNN, SPQ, SDQ"),
)


def method_features(spark) -> DataFrame:
    return spark.createDataFrame(FEATURES, "method string, precomputation string, structure string, initialisation string, expansion string, native string")


def cost_model(v: float, d_total: float, o_total: float, d: float, w: float, f: float, rho: float, leaves: float) -> list[tuple[str, str, float]]:
    """(method, measure, units): predicted space and time from venue and tree statistics."""
    o, log_d, log_f = o_total / max(v, 1), math.log2(max(d_total, 2)), math.log(max(leaves, 2)) / math.log(max(f, 2))
    inner = rho * rho * f * f * leaves
    rows = {
        "access_graph": (v + d_total + 2 * v * d + v * d * d, o * v * log_d, v * log_d, v * log_d + w),
        "door_matrix": (3 * d_total * d_total, o * d * log_d, d * d, d * d + w),
        "layered_rtree": (v + v * d + o_total, o * v * log_d, v * log_d, v * log_d + w),
        "border_tree": (inner + rho * d_total, (rho * log_f) ** 2 * (v * o / leaves + rho), rho * rho * log_f, (rho * rho + w) * log_f),
        "border_tree_deep": (inner + rho * d_total * log_f, rho * rho * log_f * (v * o / leaves + rho), rho * rho, rho * rho + w),
    }
    return [(m, name, float(x)) for m, values in rows.items() for name, x in zip(("space", "rq_knn", "sdq", "spq"), values, strict=True)]


def tree_stats(venue: Venue) -> dict[str, float]:
    """Inputs of the cost model that come from the venue and its border tree."""
    tree = build_border_tree(venue)
    leaves = tree.members.select("leaf").distinct().count()
    rho = tree.access.groupBy("node_id").count().agg(F.avg("count")).first()[0] or 0.0
    fan = tree.nodes.where("parent_id is not null").groupBy("parent_id").count().agg(F.avg("count")).first()[0] or 1.0
    d = dv_counts(venue).agg(F.avg("dv")).first()[0]
    return {"v": venue.partitions.count() - 1, "d_total": venue.doors.count(), "d": d, "f": fan, "rho": rho, "leaves": leaves}


def query_memory(method: str, venue: Venue, points: DataFrame, radius_mm: int) -> DataFrame:
    """(method, resident_bytes, read_bytes, label_bytes) of a batch of range queries: the model that is held, the rows of it
    that the search reads, and the labels that it keeps. Logical sizes, so reruns agree."""
    from floorwalk.operators.labels import climb, point_labels
    from floorwalk.operators.range import placed_points
    from floorwalk.operators.topology import exit_legs, graph_legs

    placed = placed_points(venue, points)
    found = point_labels(method, venue, placed, radius_mm)
    kept = found.agg((F.count("*") * LABEL).alias("label_bytes"))
    if method == "dm":
        rows = exit_legs(venue, placed).join(door_matrix(venue).select("a_door", "dist_mm"), (F.col("door") == F.col("a_door")) & (F.col("dist") + F.col("dist_mm") <= radius_mm))
    elif method in ("ag", "lr"):
        rows = found.join(graph_legs(venue), F.col("door") == F.col("a_door"))
    else:
        rows = climb(venue, build_border_tree(venue), placed, False, method == "btd").select("qid").unionByName(found.select("qid"))
    read = rows.agg((F.count("*") * (2 * ID + NUMBER)).alias("read_bytes"))
    held = model_size(venue, (method,)).agg(F.sum("n_bytes").alias("resident_bytes"))
    return held.crossJoin(read).crossJoin(kept).select(F.lit(NAMES[method]).alias("method"), "resident_bytes", "read_bytes", "label_bytes")  # three one-row tables


def predicted_and_counted(venue: Venue, points: DataFrame, pairs: DataFrame, objects: DataFrame, radius_mm: int, w: float) -> DataFrame:
    """(method, measure, predicted, counted): the cost formulas beside what a model holds (rows), what range queries read
    (labels) and what routes visit (doors), a query's mean."""
    from floorwalk.operators import route
    from floorwalk.operators.labels import METHODS, point_labels
    from floorwalk.operators.range import placed_points

    rows = cost_model(o_total=objects.count(), w=w, **tree_stats(venue))
    predicted = venue.spark.createDataFrame(rows, "method string, measure string, predicted double")
    placed, out = placed_points(venue, points), None
    best = route.distance_query("dm", venue, pairs).where("dist_mm is not null")
    sides = route.sides(venue, pairs)
    for method in METHODS:
        name = F.lit(NAMES[method]).alias("method")
        parts = (
            model_size(venue, (method,)).agg(F.sum("n_rows").cast("double").alias("counted")).select(name, F.lit("space").alias("measure"), "counted"),
            point_labels(method, venue, placed, radius_mm).groupBy("qid").count().agg(F.avg("count").alias("counted")).select(name, F.lit("rq_knn").alias("measure"), "counted"),
            route.visited_doors(method, venue, *sides, best).agg(F.avg("nvd").alias("counted")).select(name, F.lit("sdq").alias("measure"), "counted"),
        )
        for part in parts:
            out = part if out is None else out.union(part)
    return predicted.join(out, ["method", "measure"])


def measured_winner(counted: DataFrame) -> DataFrame:
    """(measure, method): the method with the least count per measure, ties by name."""
    return counted.groupBy("measure").agg(F.min(F.struct("counted", "method")).alias("least")).select("measure", F.col("least.method").alias("method"))


def disagreement(left: DataFrame, right: DataFrame) -> int:
    """Rows in one result and not in the other: 0 for exact methods."""
    columns = left.columns
    return left.exceptAll(right.select(*columns)).count() + right.select(*columns).exceptAll(left).count()


def prune_stats(touched: DataFrame, n_doors: int) -> DataFrame:
    """(qid, touched, share_pruned_bp): doors labelled by a search, and the untouched share in basis points."""
    counts = touched.groupBy("qid").agg(F.count("*").alias("touched"))
    return counts.withColumn("share_pruned_bp", F.floor((F.lit(n_doors) - F.col("touched")) * 10_000 / n_doors).cast("long"))


def ratio_report(results: DataFrame, key: str, low: str, high: str) -> DataFrame:
    """results (method, <key>, amount) -> (method, ratio): growth from one setting to another."""
    a = results.where(F.col(key) == low).select("method", F.col("amount").alias("a"))
    b = results.where(F.col(key) == high).select("method", F.col("amount").alias("b"))
    return a.join(b, "method").select("method", (F.col("b") / F.col("a")).alias("ratio"))


SMALL_DOORS, CRUCIAL_SHARE = 500, 0.05


def recommend(venue: Venue) -> DataFrame:
    """(task, method): the model to choose for this venue, from its statistics."""
    stats = venue_stats(venue).select("doors", (F.col("crucial") / F.col("partitions")).alias("crucial_share"))
    small, crucial = F.col("doors") <= SMALL_DOORS, F.col("crucial_share") > CRUCIAL_SHARE
    matrix, deep, graph = F.lit("door_matrix"), F.lit("border_tree_deep"), F.lit("access_graph")
    choice = {"range": F.when(small, matrix).when(crucial, deep).otherwise(graph), "knn": F.when(small, matrix).when(crucial, deep).otherwise(graph), "route": F.when(small, matrix).otherwise(deep), "changing_doors": graph}
    pairs = F.array(*[F.struct(F.lit(t).alias("task"), c.alias("method")) for t, c in choice.items()])
    return stats.select(F.explode(pairs).alias("r")).select("r.task", "r.method")
