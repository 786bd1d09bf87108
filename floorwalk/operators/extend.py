"""Extensions: door schedules, moving objects, uncertain positions, keywords."""

from __future__ import annotations

from collections.abc import Sequence

import numpy as np
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from floorwalk.functions.geometry import leg_mm, rect_far_mm, rect_gap_mm
from floorwalk.operators.labels import cells_entered, point_labels
from floorwalk.operators.range import placed_points, range_query
from floorwalk.operators.knn import rank_objects
from floorwalk.operators.topology import entry_legs, exit_legs, graph_legs
from floorwalk.plans import relax
from floorwalk.plans.border import build_border_tree
from floorwalk.plans.rtree import build_rtree, descend
from floorwalk.sources.scratch import materialize
from floorwalk.sources.venue import ROOM, Venue, table

PRECOMPUTED = ("dm", "bt", "btd")


def door_hours(venue: Venue) -> DataFrame:
    """(door_id, open_s, close_s) in seconds of day; doors without a row are always open."""
    main = venue.doors.where("kind = 'room_main'").select("door_id", (F.col("door_id") % 100_000_000 - ROOM).alias("s"))
    opens, closes = (3600 * (6 + F.col("s") % 5)), (3600 * (18 + F.col("s") % 6))
    first = main.select("door_id", opens.alias("open_s"), F.when(F.col("s") % 10 == 9, 43_200).otherwise(closes).alias("close_s"))
    return first.union(main.where("s % 10 = 9").select("door_id", F.lit(46_800).cast("long").alias("open_s"), closes.alias("close_s")))


def doors_open_at(venue: Venue, second: int) -> DataFrame:
    """(door_id) of doors that are open at a second of the day."""
    hours = door_hours(venue)
    open_now = hours.where(F.lit(second).between(F.col("open_s"), F.col("close_s") - 1)).select("door_id")
    free = venue.doors.select("door_id").join(hours.select("door_id"), "door_id", "left_anti")
    return free.union(open_now).distinct()


def open_venue(venue: Venue, second: int) -> Venue:
    """The venue at a fixed time: closed doors cannot be passed. Only models without precomputed distances apply."""
    def make():
        moves = materialize(venue.moves.join(doors_open_at(venue, second), "door_id", "left_semi"))
        out = Venue(venue.spark, venue.sf_dir, venue.floors, f"{venue.variant}@{second}", venue.partitions, venue.doors, moves, venue.override)
        out.cache["changing"] = True
        return out

    return venue.remember(("open", second), make)


def require_native(method: str) -> None:
    if method in PRECOMPUTED:
        raise ValueError("door schedules change distances: use access_graph or layered_rtree")


def route_open_at(method: str, venue: Venue, pairs: DataFrame, second: int) -> DataFrame:
    """(qid, dist_mm) with door states frozen at the departure time."""
    from floorwalk.operators.route import distance_query

    require_native(method)
    return distance_query(method, open_venue(venue, second), pairs)


def route_timed(venue: Venue, pairs: DataFrame, depart_s: int, speed_mm_s: int = 1200, max_rounds: int = 10_000) -> DataFrame:
    """(qid, dist_mm): each door is checked at the time of arrival at it (departure plus distance over speed)."""
    from floorwalk.operators.route import direct_legs, sides

    hours = door_hours(venue).groupBy("door_id").agg(F.collect_list(F.struct("open_s", "close_s")).alias("hours")).withColumnRenamed("door_id", "door")
    source, target = sides(venue, pairs)

    def passable(frame: DataFrame) -> DataFrame:
        at = (F.lit(depart_s) + F.floor(F.col("dist") / speed_mm_s)) % 86_400
        checked = frame.join(hours, "door", "left").where(F.col("hours").isNull() | F.exists("hours", lambda h: at.between(h["open_s"], h["close_s"] - 1)))
        return checked.select("qid", "door", "dist")

    starts, ends = passable(exit_legs(venue, source)), entry_legs(venue, target).select("qid", "door", F.col("dist").alias("rest"))
    if graph_legs(venue).count() <= relax.ROUND_LEGS:
        via = _timed_ways(venue, starts, ends, depart_s, speed_mm_s)
    else:
        via = _timed_jobs(venue, starts, ends, passable, max_rounds)
    found = via.union(direct_legs(source, target)).groupBy("qid").agg(F.min("dist").alias("dist_mm"))
    return pairs.select("qid").join(found, "qid", "left")


def _timed_ways(venue: Venue, starts: DataFrame, ends: DataFrame, depart_s: int, speed_mm_s: int) -> DataFrame:
    """(qid, dist): a query's rounds within one task, over legs of a checked size."""
    graph = relax.leg_arrays(venue.doors.select("door_id"), graph_legs(venue))
    hours = door_hours(venue).toPandas().sort_values(["door_id", "open_s"])
    turn, at = hours.groupby("door_id").cumcount().to_numpy(), np.searchsorted(graph.nodes, hours["door_id"].to_numpy())
    # Row k holds the k-th opening of each door; doors without a row are open all day.
    opens, closes = np.full((max(turn.max(initial=0) + 1, 1), len(graph.nodes)), 86_400), np.zeros((max(turn.max(initial=0) + 1, 1), len(graph.nodes)), dtype=np.int64)
    opens[0], closes[0] = 0, 86_400
    opens[turn, at], closes[turn, at] = hours["open_s"].to_numpy(), hours["close_s"].to_numpy()

    def passable(door: np.ndarray, dist: np.ndarray) -> np.ndarray:
        second = (depart_s + dist // speed_mm_s) % 86_400
        return ((opens[:, door] <= second) & (second < closes[:, door])).any(axis=0)

    return relax.round_ways(starts, ends, graph, passable)


def _timed_jobs(venue: Venue, starts: DataFrame, ends: DataFrame, passable, max_rounds: int) -> DataFrame:
    """(qid, dist): a job per round, for legs of any size."""
    best = frontier = materialize(starts)
    for _ in range(max_rounds):
        step = frontier.join(graph_legs(venue), frontier["door"] == F.col("a_door")).select("qid", F.col("b_door").alias("door"), (F.col("dist") + F.col("leg_mm")).alias("dist"))
        grown = passable(step).groupBy("qid", "door").agg(F.min("dist").alias("dist"))
        known = best.select("qid", "door", F.col("dist").alias("known"))
        frontier = materialize(grown.join(known, ["qid", "door"], "left").where("known is null or dist < known").select("qid", "door", "dist"))
        if frontier.isEmpty():
            break
        best = materialize(best.union(frontier).groupBy("qid", "door").agg(F.min("dist").alias("dist")))
    return best.join(ends, ["qid", "door"]).select("qid", (F.col("dist") + F.col("rest")).alias("dist"))


def numbered_rooms(rooms: DataFrame) -> tuple[DataFrame, int]:
    """Rooms numbered from 0 by supplier, and how many: ranks inside blocks of keys, plus the rooms of earlier blocks."""
    key, block = F.col("part_id") % 100_000_000, F.floor(F.col("part_id") % 100_000_000 / 4096)
    blocks = rooms.groupBy(block.alias("block")).agg(F.count("*").alias("size"))
    before = blocks.alias("x").join(blocks.alias("y"), F.col("y.block") < F.col("x.block"), "left").groupBy(F.col("x.block").alias("block")).agg(F.coalesce(F.sum("y.size"), F.lit(0)).alias("before"))
    placed = rooms.withColumn("block", block).withColumn("own", F.row_number().over(Window.partitionBy("block").orderBy(key)))
    return placed.join(before, "block").withColumn("n", (F.col("before") + F.col("own") - 1).cast("long")).drop("block", "before", "own"), rooms.count()


def positions(venue: Venue) -> DataFrame:
    """(user_id, ts, event_id, floor, x_mm, y_mm, part_id) from events: a room per event."""
    rooms = venue.partitions.where("kind = 'room' and floor < 5").select("part_id", "floor", "xmin", "ymin")
    rooms, total = numbered_rooms(rooms)
    events = table(venue.spark, venue.sf_dir, "events").select("user_id", F.col("ts").cast("timestamp_ntz").alias("ts"), F.col("event_id").cast("long").alias("event_id"))
    spot = events.withColumn("n", (31 * F.col("event_id") + F.col("user_id")) % total)
    x, y = F.col("xmin") + 1 + (F.col("event_id") * 7919) % 9998, F.col("ymin") + 1 + (F.col("event_id") * 104_729) % 7998
    return spot.join(rooms, "n").select("user_id", "ts", "event_id", "floor", x.alias("x_mm"), y.alias("y_mm"), "part_id")


def positions_as_of(moving: DataFrame, at: str) -> DataFrame:
    """(user_id, ts, part_id): each user's last position at or before a time, ties to the larger event id."""
    past = moving.where(F.col("ts") <= F.lit(at).cast("timestamp_ntz"))
    last = past.groupBy("user_id").agg(F.max_by(F.struct("ts", "part_id"), F.struct("ts", "event_id")).alias("l"))
    return last.select("user_id", "l.ts", "l.part_id")


def uncertain_objects(objects: DataFrame) -> DataFrame:
    """(object_id, floor, x_lo, x_hi, y_lo, y_hi): an object is somewhere in a square round its recorded place."""
    half = 500 + 500 * (F.col("object_id") % 6)
    return objects.select("object_id", "floor", (F.col("x_mm") - half).alias("x_lo"), (F.col("x_mm") + half).alias("x_hi"), (F.col("y_mm") - half).alias("y_lo"), (F.col("y_mm") + half).alias("y_hi"))


def uncertain_range(venue: Venue, points: DataFrame, regions: DataFrame, radius_mm: int) -> DataFrame:
    """(qid, object_id, certain): regions are clipped to the partitions they overlap; certain if every clip lies within
    the radius through some door (or the host), possible if any point of a clip may."""
    tree = build_rtree(venue)
    probes = regions.select(F.col("object_id").alias("qid"), "floor", "x_lo", "x_hi", "y_lo", "y_hi")
    overlap = lambda: (F.col("floor") == F.col("b_floor")) & (F.col("x_lo") < F.col("xmax")) & (F.col("x_hi") > F.col("xmin")) & (F.col("y_lo") < F.col("ymax")) & (F.col("y_hi") > F.col("ymin"))
    hit = descend(tree, probes, overlap).withColumnRenamed("qid", "object_id")
    box = venue.partitions.select("part_id", "xmin", "ymin", "xmax", "ymax")
    clip = hit.join(box, "part_id").select("object_id", "part_id", F.greatest("x_lo", "xmin").alias("cx0"), F.greatest("y_lo", "ymin").alias("cy0"), F.least("x_hi", "xmax").alias("cx1"), F.least("y_hi", "ymax").alias("cy1"))
    placed = placed_points(venue, points)
    found = cells_entered(venue, point_labels("lr", venue, placed, radius_mm))
    spot = venue.doors.select("door_id", F.col("x_mm").alias("dx"), F.col("y_mm").alias("dy"))
    gap, far = rect_gap_mm("dx", "dy", "cx0", "cy0", "cx1", "cy1"), rect_far_mm("dx", "dy", "cx0", "cy0", "cx1", "cy1")
    via = found.join(spot, F.col("door") == F.col("door_id")).join(clip, "part_id").select("qid", "object_id", "part_id", (F.col("dist") + gap).alias("near"), (F.col("dist") + far).alias("far"))
    here = placed.join(clip, "part_id").select("qid", "object_id", "part_id", rect_gap_mm("x_mm", "y_mm", "cx0", "cy0", "cx1", "cy1").alias("near"), rect_far_mm("x_mm", "y_mm", "cx0", "cy0", "cx1", "cy1").alias("far"))
    per_clip = via.union(here).groupBy("qid", "object_id", "part_id").agg(F.min("near").alias("near"), F.min("far").alias("far"))
    clips = clip.groupBy("object_id").agg(F.count("*").alias("clips"))
    whole = per_clip.groupBy("qid", "object_id").agg(F.min("near").alias("near"), F.max("far").alias("far"), F.count("*").alias("seen")).join(clips, "object_id")
    sure = (F.col("far") <= radius_mm) & (F.col("seen") == F.col("clips"))
    return whole.where(F.col("near") <= radius_mm).select("qid", "object_id", sure.cast("int").alias("certain"))


def object_words(venue: Venue, wanted: Sequence[str] | None = None) -> DataFrame:
    """(object_id, word): a customer's segment and the name and brand words of the parts they bought.

    wanted: these words only, so that lines of other parts go before orders are read.
    """
    spark, d = venue.spark, venue.sf_dir
    segment = table(spark, d, "customer").select(F.col("c_custkey").cast("long").alias("object_id"), F.lower("c_mktsegment").alias("word"))
    orders = table(spark, d, "orders").select(F.col("o_custkey").cast("long").alias("object_id"), "o_orderkey")
    lines = table(spark, d, "lineitem").select(F.col("l_orderkey").alias("o_orderkey"), F.col("l_partkey").alias("p_partkey"))
    parts = table(spark, d, "part").select("p_partkey", F.explode(F.array_union(F.split(F.lower("p_name"), " "), F.array(F.lower("p_brand")))).alias("word"))
    if wanted is None:
        words = orders.join(lines, "o_orderkey").select("object_id", "p_partkey").distinct().join(parts, "p_partkey")
    else:
        chosen = F.col("word").isin(list(wanted))
        segment, words = segment.where(chosen), lines.join(parts.where(chosen), "p_partkey").join(orders, "o_orderkey")
    return segment.union(words.select("object_id", "word")).where("word <> ''").distinct()


def with_words(objects: DataFrame, words: DataFrame, wanted: list[str], all_words: bool = True) -> DataFrame:
    """Objects that carry all (or any) of the wanted words."""
    hits = words.where(F.col("word").isin(wanted)).groupBy("object_id").agg(F.count_distinct("word").alias("n"))
    return objects.join(hits.where(F.col("n") >= (len(set(wanted)) if all_words else 1)), "object_id", "left_semi")


def keyword_range(method: str, venue: Venue, points: DataFrame, objects: DataFrame, words: DataFrame, wanted: list[str], radius_mm: int, all_words: bool = True) -> DataFrame:
    return range_query(method, venue, points, with_words(objects, words, wanted, all_words), radius_mm)


def node_words(venue: Venue, objects: DataFrame, words: DataFrame) -> DataFrame:
    """(node_id, word): words below each node of the border tree."""
    tree = build_border_tree(venue)
    lines = tree.nodes.where("level = 0").select(F.col("node_id").alias("leaf"), F.explode("ancestors").alias("node_id"))
    held = words.join(objects.select("object_id", "part_id"), "object_id").join(tree.members, "part_id").select("leaf", "word").distinct()
    return held.join(lines, "leaf").select("node_id", "word").distinct()


def word_nodes(venue: Venue, objects: DataFrame, words: DataFrame, wanted: list[str], all_words: bool) -> DataFrame:
    """(node_id): nodes of the border tree below which the wanted words occur."""
    hits = node_words(venue, objects, words.where(F.col("word").isin(wanted))).groupBy("node_id").agg(F.count_distinct("word").alias("n"))
    return hits.where(F.col("n") >= (len(set(wanted)) if all_words else 1)).select("node_id")


def keyword_knn(method: str, venue: Venue, points: DataFrame, objects: DataFrame, words: DataFrame, wanted: list[str], k: int, all_words: bool = True) -> DataFrame:
    """Boolean k nearest neighbours: (qid, rank, object_id, dist_mm) among objects with the wanted words.

    The border trees descend only into nodes whose word sets hold the wanted ones; the other methods filter the objects.
    """
    from floorwalk.operators.knn import knn_query, tree_bounds
    from floorwalk.operators.labels import tree_labels
    from floorwalk.operators.range import score_objects

    words = materialize(words.where(F.col("word").isin(wanted)))
    chosen = materialize(with_words(objects, words, wanted, all_words))
    if method not in ("bt", "btd"):
        return knn_query(method, venue, points, chosen, k)
    deep, placed = method == "btd", placed_points(venue, points)
    nodes = materialize(word_nodes(venue, objects, words, wanted, all_words))
    bounds = materialize(tree_bounds(venue, placed, chosen, k, deep))
    found = tree_labels(venue, placed, bounds, False, deep, nodes=nodes)
    return rank_objects(score_objects(venue, found, placed, chosen, bounds), k)


def keyword_route(venue: Venue, pairs: DataFrame, objects: DataFrame, words: DataFrame, wanted: list[str], k: int = 1, max_rounds: int = 10_000) -> DataFrame:
    """(qid, rank, total_mm, door_path): the k shortest routes whose visited partitions cover all wanted words.

    A word is covered by passing through a partition that holds an object with it. A query is searched within one task where the
    legs are of a checked size, else by a job per round. States are (door, covered words), each
    with its least (distance, doors); routes are complete states, ranked by total and doors.
    """
    from floorwalk.operators.route import sides
    from floorwalk.operators.topology import door_legs

    bits = F.lit(0).cast("long")
    flagged = words.where(F.col("word").isin(wanted)).join(objects.select("object_id", "part_id"), "object_id").select("part_id", "word").distinct()
    for i, word in enumerate(wanted):
        bits = bits.bitwiseOR(F.max(F.when(F.col("word") == word, 1 << i).otherwise(0)).cast("long"))
    mask = materialize(flagged.groupBy("part_id").agg(bits.alias("mask")))
    full = (1 << len(wanted)) - 1
    source, target = sides(venue, pairs)
    cover = lambda frame: frame.join(mask, "part_id", "left").withColumn("mask", F.coalesce("mask", F.lit(0).cast("long")))
    start = exit_legs(venue, source).join(cover(source.select("qid", "part_id")).select("qid", "mask"), "qid")
    legs = materialize(cover(door_legs(venue)).groupBy("a_door", "b_door", F.col("mask").alias("seen")).agg(F.min("leg_mm").alias("leg_mm")))
    ends = entry_legs(venue, target).select("qid", "door", F.col("dist").alias("rest")).join(cover(target.select("qid", "part_id")).select("qid", "mask"), "qid")
    if legs.count() <= relax.ROUND_LEGS:
        via = relax.cover_ways(start, ends, legs, full, k)
    else:
        via = _cover_jobs(start, ends, legs, full, max_rounds)
    here = cover(source.join(target.select("qid", "part_id", F.col("x_mm").alias("tx"), F.col("y_mm").alias("ty")), ["qid", "part_id"])).where(F.col("mask") == full)
    here = here.select("qid", leg_mm("x_mm", "y_mm", "tx", "ty").alias("total_mm"), F.array().cast("array<bigint>").alias("path"))
    order = Window.partitionBy("qid").orderBy("total_mm", "path")
    return via.union(here).distinct().withColumn("rank", F.row_number().over(order)).where(F.col("rank") <= k).select("qid", "rank", "total_mm", F.col("path").alias("door_path"))


def _cover_jobs(start: DataFrame, ends: DataFrame, legs: DataFrame, full: int, max_rounds: int) -> DataFrame:
    """(qid, total_mm, path) of all complete states: a job per round, for legs of any size."""
    state, label = ["qid", "door", "mask"], F.struct("dist", "path")
    least = lambda frame: frame.groupBy(*state).agg(F.min(label).alias("low")).select(*state, "low.dist", "low.path")
    best = frontier = materialize(start.select(*state, "dist", F.array("door").alias("path")))
    for _ in range(max_rounds):
        step = frontier.join(legs, frontier["door"] == legs["a_door"]).select("qid", F.col("b_door").alias("door"), F.col("mask").bitwiseOR(F.col("seen")).alias("mask"), (F.col("dist") + F.col("leg_mm")).alias("dist"), F.array_append("path", F.col("b_door")).alias("path"))
        known = best.select(*state, label.alias("known"))
        frontier = materialize(least(step).join(known, state, "left").where(F.col("known").isNull() | (label < F.col("known"))).select(*state, "dist", "path"))
        if frontier.isEmpty():
            break
        best = materialize(least(best.union(frontier)))
    last = ends.select("qid", "door", "rest", F.col("mask").alias("last"))
    return best.join(last, ["qid", "door"]).where(F.col("mask").bitwiseOR(F.col("last")) == full).select("qid", (F.col("dist") + F.col("rest")).alias("total_mm"), "path")
