"""Bulk-loaded R-tree over partition rectangles, stored as tables and searched level by level with joins."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from floorwalk.functions.geometry import contains
from floorwalk.operators.topology import graph_legs
from floorwalk.plans.relax import labels
from floorwalk.sources.scratch import materialize
from floorwalk.sources.venue import Venue

FANOUT = 20
BOX = ("xmin", "ymin", "xmax", "ymax")


@dataclass
class RTree:
    """levels[0] holds the partitions themselves (node_id is part_id); the last level holds one node per floor."""

    levels: list[DataFrame]
    fanout: int


def pack(items: DataFrame, fanout: int) -> tuple[DataFrame, DataFrame]:
    """Sort-tile-recursive grouping per floor: slabs by x, runs by y. Returns items with parent_id, and the parents."""
    floor = Window.partitionBy("floor")
    cx, cy = (F.col("xmin") + F.col("xmax")), (F.col("ymin") + F.col("ymax"))
    sized = items.withColumn("n", F.count("*").over(floor))
    slabs = F.ceil(F.sqrt(F.ceil(F.col("n") / fanout)))
    sized = sized.withColumn("slab", F.floor((F.row_number().over(floor.orderBy(cx, "node_id")) - 1) / F.ceil(F.col("n") / slabs)))
    run = F.floor((F.row_number().over(Window.partitionBy("floor", "slab").orderBy(cy, "node_id")) - 1) / fanout)
    named = sized.withColumn("parent_id", (F.col("floor") * 100_000_000 + F.col("slab") * 10_000 + run).cast("long"))
    parents = named.groupBy("floor", F.col("parent_id").alias("node_id")).agg(F.min("xmin").alias("xmin"), F.min("ymin").alias("ymin"), F.max("xmax").alias("xmax"), F.max("ymax").alias("ymax"))
    return named.drop("n", "slab"), parents


def build_rtree(venue: Venue, fanout: int = FANOUT) -> RTree:
    def make():
        level = venue.partitions.where("xmin is not null").select("floor", F.col("part_id").alias("node_id"), *BOX)
        floors = level.select("floor").distinct().count()
        levels = []
        while True:
            children, parents = pack(level, fanout)
            levels.append(materialize(children))
            level = materialize(parents)
            if level.count() <= floors:
                levels.append(level)
                return RTree(levels, fanout)

    return venue.remember(("rtree", fanout), make)


def descend(tree: RTree, probes: DataFrame, predicate) -> DataFrame:
    """probes (qid, floor, ...) -> (probe columns, part_id) of the partitions whose boxes satisfy predicate, top down."""
    columns = probes.columns
    box = lambda frame: frame.select(F.col("floor").alias("b_floor"), "node_id", *BOX, *(["parent_id"] if "parent_id" in frame.columns else []))
    hits = probes.join(box(tree.levels[-1]), predicate()).select(*columns, "node_id")
    for level in reversed(tree.levels[:-1]):
        below = box(level).withColumnRenamed("node_id", "child_id")
        joined = hits.join(below, hits["node_id"] == below["parent_id"]).where(predicate())
        hits = joined.select(*columns, F.col("child_id").alias("node_id"))
    return hits.withColumnRenamed("node_id", "part_id")


def locate_rtree(points: DataFrame, tree: RTree) -> DataFrame:
    """Host partition by descent: inner boxes are closed so that no cell is missed, leaves decide half-open."""
    inside = lambda: (F.col("floor") == F.col("b_floor")) & F.col("x_mm").between(F.col("xmin"), F.col("xmax")) & F.col("y_mm").between(F.col("ymin"), F.col("ymax"))
    found = descend(tree, points, inside)
    areas = tree.levels[0].select(F.col("node_id").alias("part_id"), *BOX)
    return found.join(areas, "part_id").where(contains("x_mm", "y_mm")).select(*points.columns, "part_id")


def skeleton(venue: Venue) -> DataFrame:
    """(a_stair, b_stair, dist_mm) between staircase doors: the upper tier, and a lower bound between floors."""

    def make():
        stairs = venue.doors.where("kind in ('stair_low', 'stair_high')").select(F.col("door_id"))
        seeds = stairs.select(F.col("door_id").alias("qid"), F.col("door_id").alias("door"), F.lit(0).cast("long").alias("dist"))
        found = labels(seeds, graph_legs(venue))
        return materialize(found.join(stairs.select(F.col("door_id").alias("door")), "door", "left_semi").select(F.col("qid").alias("a_stair"), F.col("door").alias("b_stair"), F.col("dist").alias("dist_mm")))

    return venue.remember("skeleton", make)


def rt_links(venue: Venue) -> DataFrame:
    """(part_id, links): the topological layer, a partition's (door, neighbour) pairs."""
    pairs = venue.moves.select(F.col("from_part").alias("part_id"), F.struct("door_id", "to_part").alias("link"))
    return pairs.groupBy("part_id").agg(F.sort_array(F.collect_list("link")).alias("links"))


def candidate_cells(venue: Venue, tree: RTree, placed: DataFrame, bound) -> DataFrame:
    """placed (qid, floor, x_mm, y_mm[, bound]) -> (qid, part_id): cells whose lower bound is within the bound.

    Same floor: straight line to the box. Other floors: line to a stair door, the stair tier, line to the box.
    """
    from floorwalk.functions.geometry import rect_gap_mm

    limit = F.lit(bound).cast("long") if isinstance(bound, int) else F.col("bound")
    stairs = venue.doors.where("kind in ('stair_low', 'stair_high')").select("door_id", F.col("floor").alias("s_floor"), F.col("x_mm").alias("sx"), F.col("y_mm").alias("sy"))
    probes = placed.select("qid", "floor", "x_mm", "y_mm", limit.alias("room_mm"))
    gap = rect_gap_mm("sx", "sy", "x_mm", "y_mm", "x_mm", "y_mm")
    # Climbing a staircase changes floors between its two doors, so the arrival side is any stair door of another floor.
    up = probes.join(stairs, probes["floor"] == stairs["s_floor"]).withColumn("first", gap).where("first <= room_mm")
    tier = skeleton(venue).join(stairs.select(F.col("door_id").alias("b_stair"), F.col("s_floor").alias("to_floor"), F.col("sx").alias("tx"), F.col("sy").alias("ty")), "b_stair")
    other = up.join(tier, up["door_id"] == tier["a_stair"]).where("to_floor <> floor")
    arrivals = other.groupBy("qid", "to_floor", "tx", "ty").agg(F.max(F.col("room_mm") - F.col("first") - F.col("dist_mm")).alias("room_mm")).where("room_mm >= 0")
    every = probes.union(arrivals.select("qid", F.col("to_floor").alias("floor"), F.col("tx").alias("x_mm"), F.col("ty").alias("y_mm"), "room_mm"))
    near = lambda: (F.col("floor") == F.col("b_floor")) & (rect_gap_mm("x_mm", "y_mm", "xmin", "ymin", "xmax", "ymax") <= F.col("room_mm"))
    return descend(tree, every, near).select("qid", "part_id").distinct()
