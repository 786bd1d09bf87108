"""k nearest neighbours: an upper bound on the k-th distance, found by each method in its own way, then a range query."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from floorwalk.functions.geometry import rect_far_mm, rect_gap_mm
from floorwalk.operators.labels import point_labels, tree_labels
from floorwalk.operators.range import placed_points, range_query, score_objects
from floorwalk.operators.topology import door_reach, exit_legs
from floorwalk.plans.border import build_border_tree
from floorwalk.plans.matrix import door_matrix
from floorwalk.sources.scratch import materialize
from floorwalk.sources.venue import Venue

START_MM = 40_000


def upper_bounds(venue: Venue, found: DataFrame, placed: DataFrame, objects: DataFrame, k: int) -> DataFrame:
    """(qid, bound): radius within which cells are sure to hold k objects; no row where they do not.

    Each cell counts once, with the least of label plus farthest reach; the host cell offers its farthest corner.
    """
    reach = door_reach(venue)
    bucket = objects.groupBy("part_id").agg(F.count("*").alias("n"))
    via = found.join(reach, found["door"] == reach["door_id"]).select("qid", "part_id", (F.col("dist") + F.col("reach_mm")).alias("u"))
    box = venue.partitions.where("xmin is not null").select("part_id", "xmin", "ymin", "xmax", "ymax")
    host = placed.join(box, "part_id").select("qid", "part_id", rect_far_mm("x_mm", "y_mm", "xmin", "ymin", "xmax", "ymax").alias("u"))
    cells = via.union(host).groupBy("qid", "part_id").agg(F.min("u").alias("u")).join(bucket, "part_id")
    running = Window.partitionBy("qid").orderBy("u", "part_id").rowsBetween(Window.unboundedPreceding, Window.currentRow)
    return cells.withColumn("seen", F.sum("n").over(running)).where(F.col("seen") >= k).groupBy("qid").agg(F.min("u").alias("bound"))


def rank_objects(scored: DataFrame, k: int) -> DataFrame:
    order = Window.partitionBy("qid").orderBy("dist_mm", "object_id")
    return scored.withColumn("rank", F.row_number().over(order)).where(F.col("rank") <= k).select("qid", "rank", "object_id", "dist_mm")


UNBOUNDED = 1 << 60


def _settle(venue: Venue, placed: DataFrame, objects: DataFrame, k: int, read) -> DataFrame:
    """(qid, bound): read(open points, round) gives labels and the radius (qid, radius) up to which they are complete,
    more of them each round; a query is settled once its upper bound lies within that radius, or nothing more comes."""
    open_points, done, before, step = placed, None, None, 0
    while True:
        found, radius = read(open_points, step)
        found = materialize(found)
        sure = upper_bounds(venue, found, open_points, objects, k).join(radius, "qid")
        settled = materialize(sure.where(F.col("bound") <= F.col("radius")).select("qid", "bound"))
        done = settled if done is None else done.union(settled)
        open_points = materialize(open_points.join(settled, "qid", "left_anti"))
        state = (found.count(), open_points.count())
        if not state[1]:
            return done
        if state == before:  # no label is new, though the reach has grown: fewer than k objects can be reached
            return done.union(open_points.select("qid", F.lit(UNBOUNDED).cast("long").alias("bound")))
        before, step = state, step + 1


def graph_bounds(venue: Venue, placed: DataFrame, objects: DataFrame, k: int) -> DataFrame:
    """access_graph: expansion by a radius that doubles until the cells reached hold k objects."""
    def read(points: DataFrame, step: int):
        radius = START_MM << step
        return point_labels("ag", venue, points, radius), points.select("qid", F.lit(radius).cast("long").alias("radius"))

    return _settle(venue, placed, objects, k, read)


def matrix_bounds(venue: Venue, placed: DataFrame, objects: DataFrame, k: int, first: int = 64) -> DataFrame:
    """door_matrix: the ranked rows of the host's exit doors are walked in heads of growing length; a head is complete up to
    the least distance at which one of the rows breaks off."""
    matrix, most = door_matrix(venue), door_matrix(venue).agg(F.max("rank")).first()[0] or 0

    def read(points: DataFrame, step: int):
        head = first * 4**step
        rows = exit_legs(venue, points).join(matrix.where(F.col("rank") <= head).select("a_door", "b_door", "dist_mm", "rank"), F.col("door") == F.col("a_door"))
        rows = rows.select("qid", "a_door", "rank", F.col("b_door").alias("door"), (F.col("dist") + F.col("dist_mm")).alias("dist"))
        ends = rows.groupBy("qid", "a_door").agg(F.max("dist").alias("last"), F.max("rank").alias("rank"))
        broken = F.when((F.col("rank") >= head) & (F.lit(head) < most), F.col("last") - 1).otherwise(UNBOUNDED)
        radius = ends.groupBy("qid").agg(F.min(broken).alias("radius"))
        return rows.groupBy("qid", "door").agg(F.min("dist").alias("dist")), points.select("qid").join(radius, "qid", "left").select("qid", F.coalesce("radius", F.lit(UNBOUNDED)).alias("radius"))

    return _settle(venue, placed, objects, k, read)


def layered_bounds(venue: Venue, placed: DataFrame, objects: DataFrame, k: int) -> DataFrame:
    """layered_rtree: cells in Euclid order give the radius to begin with, as no k objects can be nearer than the k-th by
    straight lines; from there it doubles, each query by its own."""
    bucket = objects.groupBy("part_id").agg(F.count("*").alias("n"))
    box = venue.partitions.where("xmin is not null").select("part_id", F.col("floor").alias("p_floor"), "xmin", "ymin", "xmax", "ymax").join(bucket, "part_id")
    near = placed.select("qid", "floor", "x_mm", "y_mm").join(box, F.col("floor") == F.col("p_floor")).select("qid", "part_id", "n", rect_gap_mm("x_mm", "y_mm", "xmin", "ymin", "xmax", "ymax").alias("gap"))
    running = Window.partitionBy("qid").orderBy("gap", "part_id").rowsBetween(Window.unboundedPreceding, Window.currentRow)
    first = near.withColumn("seen", F.sum("n").over(running)).where(F.col("seen") >= k).groupBy("qid").agg(F.min("gap").alias("first"))
    first = materialize(placed.select("qid").join(first, "qid", "left").select("qid", F.greatest(F.coalesce("first", F.lit(0)), F.lit(START_MM // 2)).cast("long").alias("first")))

    def read(points: DataFrame, step: int):
        radius = points.select("qid").join(first, "qid").select("qid", F.shiftleft("first", step).alias("radius"))
        return point_labels("lr", venue, points, radius.withColumnRenamed("radius", "bound")), radius

    return _settle(venue, placed, objects, k, read)


def node_reach(venue: Venue) -> DataFrame:
    """(node_id, door, reach_mm): from a node's access door to the farthest point of the node that it leads to."""

    def make():
        tree = build_border_tree(venue)
        reach = door_reach(venue).join(tree.members, "part_id")
        cells = tree.deep_in.join(reach, ["door_id", "leaf"]).groupBy("anc_node", "access_door", "part_id").agg(F.min(F.col("dist_mm") + F.col("reach_mm")).alias("far"))
        whole = tree.nodes.select("node_id", "ancestors").where("level = 0").select(F.col("node_id").alias("leaf"), F.explode("ancestors").alias("anc_node")).join(tree.members, "leaf").groupBy("anc_node").agg(F.count("*").alias("parts"))
        seen = cells.groupBy("anc_node", "access_door").agg(F.max("far").alias("reach_mm"), F.count("*").alias("n")).join(whole, "anc_node").where("n = parts")
        return materialize(seen.select(F.col("anc_node").alias("node_id"), F.col("access_door").alias("door"), "reach_mm"))

    return venue.remember("node_reach", make)


def tree_bounds(venue: Venue, placed: DataFrame, objects: DataFrame, k: int, deep: bool) -> DataFrame:
    """border_tree(_deep): nodes in the order of their farthest points, with the object counts of their subtrees, bound the
    k-th distance from above; nodes beyond it go, the others give way to their children, and the bound tightens."""
    tree = build_border_tree(venue)
    line = tree.nodes.where("level = 0").select(F.col("node_id").alias("leaf"), F.explode("ancestors").alias("node_id"))
    counts = materialize(objects.select("part_id").join(tree.members, "part_id").join(line, "leaf").groupBy("node_id").agg(F.count("*").alias("n")))
    reach = node_reach(venue)

    def narrow(cover: DataFrame) -> DataFrame:
        far = cover.join(reach, ["node_id", "door"]).groupBy("qid", "node_id").agg(F.min(F.col("dist") + F.col("reach_mm")).alias("far")).join(counts, "node_id")
        running = Window.partitionBy("qid").orderBy("far", "node_id").rowsBetween(Window.unboundedPreceding, Window.currentRow)
        sure = far.withColumn("seen", F.sum("n").over(running)).where(F.col("seen") >= k).groupBy("qid").agg(F.min("far").alias("bound"))
        return placed.select("qid").join(sure, "qid", "left").select("qid", F.coalesce("bound", F.lit(UNBOUNDED)).cast("long").alias("bound"))

    return tree_labels(venue, placed, None, False, deep, narrow)


def knn_bounds(method: str, venue: Venue, placed: DataFrame, objects: DataFrame, k: int) -> DataFrame:
    """(qid, bound) for every query, each method by its own search."""
    if method == "dm":
        return matrix_bounds(venue, placed, objects, k)
    if method == "lr":
        return layered_bounds(venue, placed, objects, k)
    if method == "ag":
        return graph_bounds(venue, placed, objects, k)
    return tree_bounds(venue, placed, objects, k, method == "btd")


def knn_query(method: str, venue: Venue, points: DataFrame, objects: DataFrame, k: int) -> DataFrame:
    """(qid, rank, object_id, dist_mm), ties by object id; fewer than k rows where fewer objects can be reached."""
    placed = placed_points(venue, points)
    bounds = materialize(knn_bounds(method, venue, placed, objects, k))
    return rank_objects(range_query(method, venue, points, objects, bounds), k)


def brute_knn(venue: Venue, points: DataFrame, objects: DataFrame, k: int) -> DataFrame:
    from floorwalk.operators.labels import matrix_labels

    placed = placed_points(venue, points)
    return rank_objects(score_objects(venue, matrix_labels(venue, placed), placed, objects, None), k)


def euclid_knn(points: DataFrame, objects: DataFrame, k: int) -> DataFrame:
    from floorwalk.operators.range import euclid_range

    return rank_objects(euclid_range(points, objects, 1 << 30), k)
