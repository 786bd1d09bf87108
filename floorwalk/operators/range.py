"""Range queries: all objects within an indoor distance of a point, under each of the five methods."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from floorwalk.functions.geometry import leg_mm
from floorwalk.operators.host import locate_grid, locate_scan
from floorwalk.operators.labels import cells_entered, point_labels
from floorwalk.operators.topology import door_reach
from floorwalk.plans.rtree import build_rtree, locate_rtree
from floorwalk.sources.venue import Venue


def placed_points(venue: Venue, points: DataFrame, initialisation: str = "grid") -> DataFrame:
    """Points with their host partition, found by grid cells, by a scan of all partitions, or down the R-tree."""
    spots = points.select("qid", "floor", "x_mm", "y_mm")
    if initialisation == "scan":
        return locate_scan(spots, venue.partitions)
    if initialisation == "rtree":
        return locate_rtree(spots, build_rtree(venue))
    return locate_grid(spots, venue.partitions)


def score_objects(venue: Venue, found: DataFrame, placed: DataFrame, objects: DataFrame, bound) -> DataFrame:
    """Least distance per (qid, object) through labelled doors or straight inside the host partition."""
    spot = venue.doors.select("door_id", F.col("x_mm").alias("dx"), F.col("y_mm").alias("dy"))
    things = objects.select("object_id", "part_id", F.col("x_mm").alias("ox"), F.col("y_mm").alias("oy"))
    via = cells_entered(venue, found).join(spot, F.col("door") == F.col("door_id")).join(things, "part_id")
    via = via.select("qid", "object_id", (F.col("dist") + leg_mm("dx", "dy", "ox", "oy")).alias("dist_mm"))
    here = placed.join(things, "part_id").select("qid", "object_id", leg_mm("x_mm", "y_mm", "ox", "oy").alias("dist_mm"))
    both = via.union(here)
    if isinstance(bound, int):
        both = both.where(F.col("dist_mm") <= bound)
    elif bound is not None:
        both = both.join(bound, "qid").where(F.col("dist_mm") <= F.col("bound")).select("qid", "object_id", "dist_mm")
    return both.groupBy("qid", "object_id").agg(F.min("dist_mm").alias("dist_mm"))


def range_query(method: str, venue: Venue, points: DataFrame, objects: DataFrame, radius_mm, initialisation: str = "grid") -> DataFrame:
    """(qid, object_id, dist_mm) with dist_mm within the radius: a number, or a table (qid, bound)."""
    placed = placed_points(venue, points, initialisation)
    found = point_labels(method, venue, placed, radius_mm)
    return score_objects(venue, found, placed, objects, radius_mm)


def classify_cells(venue: Venue, found: DataFrame, radius_mm: int) -> DataFrame:
    """(qid, part_id, is_full): reached cells; full if some door's farthest reach stays within the radius."""
    reach = door_reach(venue)
    rows = found.join(reach, found["door"] == reach["door_id"])
    return rows.groupBy("qid", "part_id").agg(F.max(F.col("dist") + F.col("reach_mm") <= radius_mm).alias("is_full"))


def range_ids(method: str, venue: Venue, points: DataFrame, objects: DataFrame, radius_mm: int) -> DataFrame:
    """(qid, object_id) only: buckets of full cells are accepted whole, objects of other cells are tested."""
    placed = placed_points(venue, points)
    found = point_labels(method, venue, placed, radius_mm)
    cells = classify_cells(venue, found, radius_mm)
    accepted = cells.where("is_full").join(objects.select("object_id", "part_id"), "part_id").select("qid", "object_id")
    partial = cells.where("not is_full").select("qid", "part_id")
    tested = score_objects(venue, found, placed, objects.join(partial.select("part_id").union(placed.select("part_id")).distinct(), "part_id", "left_semi"), radius_mm)
    return accepted.union(tested.select("qid", "object_id")).distinct()


def brute_range(venue: Venue, points: DataFrame, objects: DataFrame, radius_mm: int | None) -> DataFrame:
    """Every point against every object over the full matrix: the exact baseline of the tests."""
    from floorwalk.operators.labels import matrix_labels

    placed = placed_points(venue, points)
    return score_objects(venue, matrix_labels(venue, placed), placed, objects, radius_mm)


def euclid_range(points: DataFrame, objects: DataFrame, radius_mm: int) -> DataFrame:
    """Straight lines on one floor, walls ignored: the contrast that shows why topology matters."""
    things = objects.select("object_id", F.col("floor").alias("o_floor"), F.col("x_mm").alias("ox"), F.col("y_mm").alias("oy"))
    near = (F.col("floor") == F.col("o_floor")) & F.col("ox").between(F.col("x_mm") - radius_mm, F.col("x_mm") + radius_mm)
    rows = points.join(things, near).select("qid", "object_id", leg_mm("x_mm", "y_mm", "ox", "oy").alias("dist_mm"))
    return rows.where(F.col("dist_mm") <= radius_mm)
