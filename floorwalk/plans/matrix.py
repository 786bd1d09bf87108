"""door_matrix: all-pairs door distances with ranks and first hops (one long table)."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from floorwalk.operators.topology import graph_legs
from floorwalk.plans.relax import ROUND_LEGS, all_pairs, hops_of, is_local, local_hops, local_pairs, relax
from floorwalk.sources.scratch import materialize
from floorwalk.sources.venue import Venue

DOOR_BUDGET = 50_000


def matrix_dist(venue: Venue, engine: str = "auto") -> DataFrame:
    """(a_door, b_door, dist_mm). Refuses venues whose square of doors would not pay: use a border tree there."""

    def make():
        doors = venue.doors.select("door_id")
        if doors.count() > DOOR_BUDGET:
            raise ValueError("too many doors for a full matrix; choose border_tree or access_graph")
        legs = graph_legs(venue)
        found = all_pairs(legs, doors, engine)
        if not is_local(legs):  # the compiled kernel gives a door's rows together, by distance
            found = found.repartition("a_door").sortWithinPartitions("a_door", "dist_mm")
        return materialize(found)

    return venue.remember(("dist", engine), make)


def matrix_rows(venue: Venue, starts: DataFrame) -> DataFrame:
    """(a_door, b_door, dist_mm) of some start doors (door_id), of venues of any size: read from the stored matrix, or made
    alone if there is none."""
    legs = graph_legs(venue)
    if "matrix" not in venue.cache:
        if legs.count() <= ROUND_LEGS:
            return materialize(local_pairs(starts, legs, "rounds"))
        seeds = starts.distinct().select(F.col("door_id").alias("qid"), F.col("door_id").alias("door"), F.lit(0).cast("long").alias("dist"))
        return relax(seeds, legs).select(F.col("qid").alias("a_door"), F.col("door").alias("b_door"), F.col("dist").alias("dist_mm"))
    return door_matrix(venue).select("a_door", "b_door", "dist_mm").join(starts.select(F.col("door_id").alias("a_door")).distinct(), "a_door", "left_semi")


def with_ranks(matrix: DataFrame) -> DataFrame:
    """Adds rank: 1 is the door itself, ties by door id."""
    return matrix.withColumn("rank", F.row_number().over(Window.partitionBy("a_door").orderBy("dist_mm", "b_door")))


def first_hops(matrix: DataFrame, legs: DataFrame) -> DataFrame:
    """(a_door, b_door, first_hop, stride_hop): the least next door on a shortest path; NULL on the diagonal.

    Two doors may stand at one place (a staircase's upper and the next one's lower end), so a leg may be 0. Such a step is a
    first hop only if it arrives or if a step of positive length follows it; stride_hop is the least next door by a
    positive leg, the one to take after a step of length 0. Legs of a checked size meet the matrix a column at a time.
    """
    if is_local(legs):
        return hops_of(matrix, legs)
    rest = matrix.select(F.col("a_door").alias("x"), "b_door", F.col("dist_mm").alias("rest"))
    step = legs.select("a_door", F.col("b_door").alias("x"), "leg_mm")
    tight = matrix.join(step, "a_door").join(rest, ["x", "b_door"]).where(F.col("leg_mm") + F.col("rest") == F.col("dist_mm")).select("a_door", "b_door", "x", "leg_mm")
    stride = tight.where("leg_mm > 0").groupBy("a_door", "b_door").agg(F.min("x").alias("stride_hop"))
    onward = stride.select(F.col("a_door").alias("x"), "b_door")
    still = tight.where("leg_mm = 0")
    still = still.where("x = b_door").select("a_door", "b_door", "x").union(still.join(onward, ["x", "b_door"], "left_semi").select("a_door", "b_door", "x"))
    either = still.union(stride.select("a_door", "b_door", "stride_hop")).groupBy("a_door", "b_door").agg(F.min("x").alias("first_hop"))
    return matrix.select("a_door", "b_door").join(either, ["a_door", "b_door"], "left").join(stride, ["a_door", "b_door"], "left")


def joined_hops(venue: Venue) -> DataFrame:
    """first_hops() of the door matrix: as stored, or of rows that go straight on to their columns where legs are of a checked size."""
    legs, doors = graph_legs(venue), venue.doors.select("door_id")
    if ("dist", "auto") not in venue.cache and doors.count() <= DOOR_BUDGET and is_local(legs):
        return hops_of(local_pairs(doors, legs), legs)
    return first_hops(matrix_dist(venue), legs)


def last_hops(matrix: DataFrame, legs: DataFrame) -> DataFrame:
    """(a_door, b_door, last_hop): the least door before the end, by the same rule on reversed legs."""
    turned = first_hops(matrix.select(F.col("b_door").alias("a_door"), F.col("a_door").alias("b_door"), "dist_mm"), legs.select(F.col("b_door").alias("a_door"), F.col("a_door").alias("b_door"), "leg_mm"))
    return turned.select(F.col("b_door").alias("a_door"), F.col("a_door").alias("b_door"), F.col("first_hop").alias("last_hop"))


def door_hops(venue: Venue) -> DataFrame:
    """(a_door, b_door, dist_mm, first_hop, stride_hop): the door matrix without its ranks, which need all rows sorted."""
    if "matrix" in venue.cache:
        return venue.cache["matrix"].drop("rank")
    legs, doors = graph_legs(venue), venue.doors.select("door_id")
    if doors.count() > DOOR_BUDGET:
        raise ValueError("too many doors for a full matrix; choose border_tree or access_graph")
    if is_local(legs):
        return local_hops(doors, legs)
    matrix = matrix_dist(venue)
    return matrix.join(first_hops(matrix, legs), ["a_door", "b_door"])


def door_matrix(venue: Venue, starts: DataFrame | None = None) -> DataFrame:
    """(a_door, b_door, dist_mm, rank, first_hop, stride_hop), files by start door, rows by distance.

    Range scans and rank walks of any start door read the heads of the files only: pages behind a bound are skipped. starts
    (door_id), few: all rows of these doors, made alone if the matrix is not stored, in venues of any size.
    """
    if starts is not None:
        if "matrix" in venue.cache:
            return venue.cache["matrix"].join(starts.select(F.col("door_id").alias("a_door")).distinct(), "a_door", "left_semi")
        asked = venue.doors.select("door_id").crossJoin(starts.agg(F.collect_set("door_id").alias("starts")))  # a one-row table
        return with_ranks(local_hops(asked, graph_legs(venue)))

    def make():
        return materialize(with_ranks(door_hops(venue).repartition("a_door")).sortWithinPartitions("dist_mm", "a_door"))

    return venue.remember("matrix", make)
