"""Host partition of a point: by scan, by grid, by R-tree. A point on a shared edge belongs to one cell (half-open)."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from floorwalk.functions.geometry import contains

CELL_MM = 10_000


def _areas(partitions: DataFrame) -> DataFrame:
    return partitions.where("xmin is not null").select("part_id", F.col("floor").alias("p_floor"), "xmin", "ymin", "xmax", "ymax")


def locate_scan(points: DataFrame, partitions: DataFrame) -> DataFrame:
    """points (qid, floor, x_mm, y_mm) -> + part_id, by comparing with every partition; no host, no row."""
    hit = (F.col("floor") == F.col("p_floor")) & contains("x_mm", "y_mm")
    found = points.join(_areas(partitions), hit)
    return found.groupBy(*points.columns).agg(F.min("part_id").alias("part_id"))


def locate_grid(points: DataFrame, partitions: DataFrame, cell_mm: int = CELL_MM) -> DataFrame:
    """The same through an equi-join on grid cells: linear in points plus covered cells."""
    tile = lambda c: F.floor(c / cell_mm).cast("long")
    areas = _areas(partitions)
    areas = areas.withColumn("gx", F.explode(F.sequence(tile(F.col("xmin")), tile(F.col("xmax") - 1))))
    areas = areas.withColumn("gy", F.explode(F.sequence(tile(F.col("ymin")), tile(F.col("ymax") - 1))))
    tiled = points.withColumn("gx", tile(F.col("x_mm"))).withColumn("gy", tile(F.col("y_mm")))
    joined = tiled.join(areas, (tiled["floor"] == areas["p_floor"]) & (tiled["gx"] == areas["gx"]) & (tiled["gy"] == areas["gy"]) & contains(tiled["x_mm"], tiled["y_mm"]))
    return joined.select(*[tiled[c] for c in points.columns], "part_id")
