"""Door and partition mappings, local distance maps, decomposition and its inverse."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from floorwalk.functions.geometry import leg_mm, rect_far_mm
from floorwalk.sources.scratch import materialize
from floorwalk.sources.venue import FLOOR_STEP, HALL, OUTDOOR, Venue


def door_enters(moves: DataFrame) -> DataFrame:
    """Partitions that one can enter through a door."""
    return moves.select("door_id", F.col("to_part").alias("part_id")).distinct()


def door_leaves(moves: DataFrame) -> DataFrame:
    """Partitions that one can leave through a door."""
    return moves.select("door_id", F.col("from_part").alias("part_id")).distinct()


def door_pairs(moves: DataFrame) -> DataFrame:
    """Every door's legal movements as a sorted array of (from, to)."""
    return moves.groupBy("door_id").agg(F.sort_array(F.collect_set(F.struct(F.col("from_part").alias("from"), F.col("to_part").alias("to")))).alias("moves"))


def part_entries(moves: DataFrame) -> DataFrame:
    return moves.select(F.col("to_part").alias("part_id"), "door_id").distinct()


def part_exits(moves: DataFrame) -> DataFrame:
    return moves.select(F.col("from_part").alias("part_id"), "door_id").distinct()


def part_doors(moves: DataFrame) -> DataFrame:
    """Doors of a partition whatever their direction."""
    return part_entries(moves).union(part_exits(moves)).distinct()


def two_way_doors(moves: DataFrame) -> DataFrame:
    back = moves.select("door_id", F.col("to_part").alias("from_part"), F.col("from_part").alias("to_part"))
    return moves.select("door_id", "from_part", "to_part").intersect(back).select("door_id").distinct()


def one_way_doors(moves: DataFrame) -> DataFrame:
    return moves.select("door_id").distinct().exceptAll(two_way_doors(moves))


def access_edges(moves: DataFrame) -> DataFrame:
    """The accessibility base graph: partitions as vertices, an edge per movement, labelled with its door."""
    return moves.select(F.col("from_part").alias("src_part"), F.col("to_part").alias("dst_part"), "door_id")


def _indoor(frame: DataFrame) -> DataFrame:
    return frame.where(F.col("part_id") != OUTDOOR)


def door_reach(venue: Venue) -> DataFrame:
    """(door_id, part_id, reach_mm): farthest point of each partition that the door enters; absent means infinity."""
    doors = venue.doors.select("door_id", "x_mm", "y_mm")
    parts = venue.partitions.select("part_id", "xmin", "ymin", "xmax", "ymax", "stair_mm")
    rows = _indoor(door_enters(venue.moves)).join(doors, "door_id").join(parts, "part_id")
    return rows.select("door_id", "part_id", F.coalesce("stair_mm", rect_far_mm("x_mm", "y_mm", "xmin", "ymin", "xmax", "ymax")).alias("reach_mm"))


def door_legs(venue: Venue) -> DataFrame:
    """(part_id, a_door, b_door, leg_mm): from a door that enters a partition to another that leaves it."""

    def make():
        spot = venue.doors.select("door_id", "x_mm", "y_mm")
        a = _indoor(part_entries(venue.moves)).join(spot, "door_id").select("part_id", F.col("door_id").alias("a_door"), F.col("x_mm").alias("ax"), F.col("y_mm").alias("ay"))
        b = _indoor(part_exits(venue.moves)).join(spot, "door_id").select("part_id", F.col("door_id").alias("b_door"), F.col("x_mm").alias("bx"), F.col("y_mm").alias("by"))
        both = a.join(b, "part_id").where("a_door <> b_door").join(venue.partitions.select("part_id", "stair_mm"), "part_id")
        leg = F.coalesce("stair_mm", leg_mm("ax", "ay", "bx", "by"))
        if venue.override is not None:
            both = both.join(venue.override, ["part_id", "a_door", "b_door"], "left")
            concave = F.col("part_id").isin([r[0] for r in venue.override.select("part_id").distinct().collect()])  # one per floor
            both = both.where(~concave | F.col("inside_mm").isNotNull())
            leg = F.coalesce("inside_mm", leg)
        return materialize(both.select("part_id", "a_door", "b_door", leg.alias("leg_mm")))

    return venue.remember("legs", make)


def graph_legs(venue: Venue) -> DataFrame:
    """(a_door, b_door, leg_mm): the least over shared partitions; what the distance kernels run on."""
    return venue.remember("graph", lambda: materialize(door_legs(venue).groupBy("a_door", "b_door").agg(F.min("leg_mm").alias("leg_mm"))))


def dv_counts(venue: Venue) -> DataFrame:
    """(part_id, kind, dv): number of doors of every indoor partition."""
    counts = part_doors(venue.moves).groupBy("part_id").agg(F.count("*").alias("dv"))
    return venue.partitions.where(F.col("part_id") != OUTDOOR).select("part_id", "kind").join(counts, "part_id", "left").withColumn("dv", F.coalesce("dv", F.lit(0)))


def crucial_parts(venue: Venue, gamma: int = 6) -> DataFrame:
    """Partitions with more than gamma doors."""
    return dv_counts(venue).where(F.col("dv") > gamma).select("part_id", "dv")


def is_irregular(partitions: DataFrame, aspect: float = 4.0) -> DataFrame:
    """Partitions that are long and narrow beyond the aspect, or pieces of a larger one."""
    width, height = F.col("xmax") - F.col("xmin"), F.col("ymax") - F.col("ymin")
    long_side = F.greatest(width, height) > aspect * F.least(width, height)
    return partitions.where("xmin is not null").where(long_side | F.col("parent_part").isNotNull()).select("part_id", "kind")


def decompose(partitions: DataFrame, doors: DataFrame, moves: DataFrame, cut_mm: int) -> tuple[DataFrame, DataFrame, DataFrame]:
    """Cuts hallways along x into cells of at most cut_mm, with an open segment as a two-way door between neighbours.

    Doors go to the cell whose span holds them (the last cell keeps its right edge). New cells are numbered behind
    their hallway, new doors like the cell at their left.
    """
    width = F.col("xmax") - F.col("xmin")
    wide = partitions.where((F.col("kind") == "hall") & (width > cut_mm))
    n = F.ceil(width / cut_mm).cast("long")
    cells = wide.withColumn("n", n).withColumn("s", F.explode(F.sequence(F.lit(0).cast("long"), F.col("n") - 1)))
    cells = cells.withColumn("old", F.col("part_id")).withColumn("left", F.col("xmin") + F.col("s") * cut_mm).withColumn("right", F.least(F.col("xmax"), F.col("xmin") + (F.col("s") + 1) * cut_mm))
    pieces = cells.withColumn("part_id", F.col("old") + F.col("s")).withColumn("xmin", F.col("left")).withColumn("xmax", F.col("right")).withColumn("parent_part", F.col("old"))
    new_parts = partitions.join(wide.select("part_id"), "part_id", "left_anti").select(*partitions.columns).unionByName(pieces.select(*partitions.columns))
    inner = cells.where(F.col("s") < F.col("n") - 1)
    seam = inner.select("venue_id", (F.col("old") + F.col("s")).alias("door_id"), F.lit("segment").alias("kind"), "floor", F.col("right").alias("x_mm"), F.floor((F.col("ymin") + F.col("ymax")) / 2).alias("y_mm"))
    new_doors = doors.unionByName(seam)
    where = doors.select("door_id", F.col("x_mm").alias("dx"))
    span = cells.select("old", (F.col("old") + F.col("s")).alias("piece"), "left", "right", (F.col("s") == F.col("n") - 1).alias("is_last"))
    held = lambda c: (F.col(c) == F.col("old")) & (F.col("dx") >= F.col("left")) & ((F.col("dx") < F.col("right")) | (F.col("is_last") & (F.col("dx") <= F.col("right"))))
    turned = moves.join(where, "door_id")
    for side in ("from_part", "to_part"):
        turned = turned.join(span, held(side), "left").withColumn(side, F.coalesce("piece", side)).drop("old", "piece", "left", "right", "is_last")
    here, there = F.col("old") + F.col("s"), F.col("old") + F.col("s") + 1
    ways = inner.withColumn("m", F.explode(F.array(F.struct(here.alias("f"), there.alias("t")), F.struct(there.alias("f"), here.alias("t")))))
    new_moves = turned.select(*moves.columns).unionByName(ways.select("venue_id", here.alias("door_id"), F.col("m.f").alias("from_part"), F.col("m.t").alias("to_part")))
    return new_parts, new_doors, new_moves


def merge_hallways(venue: Venue) -> Venue:
    """All hall and lobby cells of a floor as one concave cell; distances inside it are inherited from the cells.

    Doors between merged cells vanish. Between the remaining ones the interior distance is the shortest over the floor's
    former cells, kept in the override table (part_id, a_door, b_door, inside_mm).
    """
    from floorwalk.plans.relax import all_pairs

    inner = venue.partitions.where(F.col("kind").isin("hall", "lobby"))
    big = FLOOR_STEP * F.col("floor") + 9 * HALL
    owner = inner.select("part_id", big.alias("big"))
    legs = door_legs(venue).join(owner, "part_id").select("a_door", "b_door", "leg_mm")
    inside = all_pairs(legs, venue.doors.select("door_id"))
    names = owner.select(F.col("part_id").alias("from_part"), F.col("big").alias("from_big"))
    moves = venue.moves.join(names, "from_part", "left").join(names.toDF("to_part", "to_big"), "to_part", "left")
    moves = moves.select("venue_id", "door_id", F.coalesce("from_big", "from_part").alias("from_part"), F.coalesce("to_big", "to_part").alias("to_part"))
    moves = materialize(moves.where("from_part <> to_part").distinct())
    kept = moves.select("door_id").distinct()
    doors = venue.doors.join(kept, "door_id", "left_semi")
    enter = part_entries(moves).select("part_id", F.col("door_id").alias("a_door"))
    leave = part_exits(moves).select("part_id", F.col("door_id").alias("b_door"))
    bigs = owner.select(F.col("big").alias("part_id")).distinct()
    override = materialize(enter.join(leave, "part_id").join(bigs, "part_id").join(inside, ["a_door", "b_door"]).where("a_door <> b_door").select("part_id", "a_door", "b_door", F.col("dist_mm").alias("inside_mm")))
    whole = inner.groupBy("venue_id", "floor").agg(F.min("xmin").alias("xmin"), F.min("ymin").alias("ymin"), F.max("xmax").alias("xmax"), F.max("ymax").alias("ymax"))
    none = F.lit(None).cast("long")
    cells = whole.select("venue_id", big.alias("part_id"), F.lit("concave").alias("kind"), "floor", *[none.alias(c) for c in ("xmin", "ymin", "xmax", "ymax")], none.alias("stair_mm"), none.alias("parent_part"))
    parts = materialize(venue.partitions.where(~F.col("kind").isin("hall", "lobby")).unionByName(cells))
    merged = Venue(venue.spark, venue.sf_dir, venue.floors, "merged", parts, materialize(doors.select(*venue.doors.columns)), moves, override)
    merged.cache["original"] = venue
    return merged


def exit_legs(venue: Venue, placed: DataFrame) -> DataFrame:
    """placed (qid, part_id, x_mm, y_mm) -> (qid, door, dist): from a point to the doors that leave its partition."""
    return _point_legs(venue, placed, part_exits(venue.moves), True)


def entry_legs(venue: Venue, placed: DataFrame) -> DataFrame:
    """The same from the doors that enter the point's partition to the point."""
    return _point_legs(venue, placed, part_entries(venue.moves), False)


def _point_legs(venue: Venue, placed: DataFrame, sides: DataFrame, leaving: bool) -> DataFrame:
    if venue.override is not None:
        return _concave_legs(venue, placed, sides, leaving)
    spot = sides.join(venue.doors.select("door_id", F.col("x_mm").alias("dx"), F.col("y_mm").alias("dy")), "door_id")
    rows = placed.select("qid", "part_id", "x_mm", "y_mm").join(spot, "part_id")
    return rows.groupBy("qid", F.col("door_id").alias("door")).agg(F.min(leg_mm("x_mm", "y_mm", "dx", "dy")).alias("dist"))


def _concave_legs(venue: Venue, placed: DataFrame, sides: DataFrame, leaving: bool) -> DataFrame:
    """Legs of points in merged cells: shortest inside the floor's former cells, from or to the doors that remain."""
    from floorwalk.plans.relax import labels, reverse

    original = venue.cache["original"]
    hall = original.partitions.where("kind in ('hall', 'lobby')").select("part_id")
    spot = original.doors.select("door_id", F.col("x_mm").alias("dx"), F.col("y_mm").alias("dy"))
    own = (part_exits if leaving else part_entries)(original.moves).join(spot, "door_id")
    first = placed.select("qid", "part_id", "x_mm", "y_mm").join(own, "part_id")
    first = first.groupBy("qid", F.col("door_id").alias("door"), "part_id").agg(F.min(leg_mm("x_mm", "y_mm", "dx", "dy")).alias("dist"))
    rooms = first.join(hall, "part_id", "left_anti").select("qid", "door", "dist")
    inside = door_legs(original).join(hall, "part_id", "left_semi").groupBy("a_door", "b_door").agg(F.min("leg_mm").alias("leg_mm"))
    seeds = first.join(hall, "part_id", "left_semi").select("qid", "door", "dist")
    walked = labels(seeds, inside if leaving else reverse(inside))
    kept = sides.join(venue.override.select("part_id").distinct(), "part_id", "left_semi").select(F.col("door_id").alias("door")).distinct()
    return rooms.union(walked.join(kept, "door", "left_semi").select("qid", "door", "dist")).groupBy("qid", "door").agg(F.min("dist").alias("dist"))
