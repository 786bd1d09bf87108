"""Operators around the methods: checks, roll-ups, per-room top-k, trajectories, profiles of the given tables."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from floorwalk.functions.geometry import leg_mm
from floorwalk.operators.topology import dv_counts, graph_legs
from floorwalk.sources.venue import ENTRANCE, EXIT_ONLY, Venue, table


def bucket_counts(venue: Venue, objects: DataFrame) -> DataFrame:
    """(part_id, n) with 0 for empty partitions."""
    counts = objects.groupBy("part_id").agg(F.count("*").alias("n"))
    return venue.partitions.where("part_id <> 0").select("part_id").join(counts, "part_id", "left").withColumn("n", F.coalesce("n", F.lit(0)))


def rooms_with_objects(venue: Venue, objects: DataFrame) -> DataFrame:
    return venue.partitions.where("kind = 'room'").select("part_id").join(objects, "part_id", "left_semi")


def rooms_without_objects(venue: Venue, objects: DataFrame) -> DataFrame:
    return venue.partitions.where("kind = 'room'").select("part_id").join(objects, "part_id", "left_anti")


def unreachable_doors(venue: Venue, matrix: DataFrame) -> DataFrame:
    """Doors from which no other door can be reached."""
    return venue.doors.select("door_id").join(matrix.where("a_door <> b_door").select(F.col("a_door").alias("door_id")), "door_id", "left_anti")


def space_rollup(venue: Venue, objects: DataFrame) -> DataFrame:
    """(floor, kind, n): object counts per floor and kind, per floor, and over all (nulls mark the sums)."""
    placed = objects.select("object_id", "part_id").join(venue.partitions.select("part_id", "floor", "kind"), "part_id")
    return placed.rollup("floor", "kind").agg(F.count("*").alias("n"))


def kind_pivot(venue: Venue) -> DataFrame:
    """(dv, hall, lobby, room, stair): partitions per number of doors."""
    return dv_counts(venue).groupBy("dv").pivot("kind", ["hall", "lobby", "room", "stair"]).agg(F.count(F.lit(1))).na.fill(0)


def top_objects_per_room(venue: Venue, objects: DataFrame, k: int = 3) -> DataFrame:
    """(part_id, rank, object_id, leg_mm): objects nearest to their room's main door."""
    main = venue.doors.where("kind = 'room_main'").select(F.col("door_id").alias("part_id"), F.col("x_mm").alias("dx"), F.col("y_mm").alias("dy"))
    near = objects.join(main, "part_id").withColumn("leg_mm", leg_mm("x_mm", "y_mm", "dx", "dy"))
    order = Window.partitionBy("part_id").orderBy("leg_mm", "object_id")
    return near.withColumn("rank", F.row_number().over(order)).where(F.col("rank") <= k).select("part_id", "rank", "object_id", "leg_mm")


def cumulative_objects(matrix: DataFrame, venue: Venue, objects: DataFrame, a_door: int) -> DataFrame:
    """(b_door, rank, seen): running object count of the rooms that ranked doors enter, from one door's row."""
    from floorwalk.operators.topology import door_enters

    bucket = objects.groupBy("part_id").agg(F.count("*").alias("n"))
    rooms = door_enters(venue.moves).join(bucket, "part_id").groupBy(F.col("door_id").alias("b_door")).agg(F.sum("n").alias("n"))
    rows = matrix.where(F.col("a_door") == a_door).join(rooms, "b_door", "left")
    return rows.select("b_door", "rank", F.sum(F.coalesce("n", F.lit(0))).over(Window.partitionBy("a_door").orderBy("rank")).alias("seen"))


def trajectory_steps(moving: DataFrame) -> DataFrame:
    """(user_id, event_id, step_mm): straight step from a user's event to the one before, on one floor."""
    order = Window.partitionBy("user_id").orderBy("ts", "event_id")
    prior = moving.withColumns({f"p_{c}": F.lag(c).over(order) for c in ("floor", "x_mm", "y_mm")})
    return prior.where("p_floor = floor").select("user_id", "event_id", leg_mm("x_mm", "y_mm", "p_x_mm", "p_y_mm").alias("step_mm"))


def requested_k(venue: Venue) -> DataFrame:
    """(event_id, k): the number of neighbours that an event's JSON properties ask for."""
    events = table(venue.spark, venue.sf_dir, "events")
    return events.select(F.col("event_id").cast("long").alias("event_id"), F.from_json("props", "k int")["k"].alias("k")).where("k is not null")


def approx_users_per_room(moving: DataFrame, rsd: float = 0.02) -> DataFrame:
    """(part_id, users, near): the sketch's estimate beside the exact count: near if within five standard errors."""
    both = moving.groupBy("part_id").agg(F.approx_count_distinct("user_id", rsd).alias("estimate"), F.count_distinct("user_id").alias("users"))
    return both.select("part_id", "users", (F.abs(F.col("estimate") - F.col("users")) <= 5 * rsd * F.col("users") + 1).cast("int").alias("near"))


def users_per_room(moving: DataFrame) -> DataFrame:
    return moving.groupBy("part_id").agg(F.count_distinct("user_id").alias("users"))


def validate_venue(venue: Venue) -> DataFrame:
    """(check, id): offending rows of the venue checks; none if the venue is sound.

    V1 partition ids, V2 door ids unique; V3 a door joins one or two partitions; V4 a door stands on the edge of its
    partitions; V5 legs are not
    shorter than the straight line; V6 two doors of one partition at one place that are not both stair doors.
    """
    twice = lambda frame, c, name: frame.groupBy(c).count().where("count > 1").select(F.lit(name).alias("check"), F.col(c).alias("id"))
    out = twice(venue.partitions, "part_id", "V1").union(twice(venue.doors, "door_id", "V2"))
    sides = venue.moves.select("door_id", F.col("from_part").alias("part_id")).union(venue.moves.select("door_id", "to_part")).distinct()
    wrong = venue.doors.select("door_id").join(sides.groupBy("door_id").count(), "door_id", "left").where("count is null or count > 2")
    out = out.union(wrong.select(F.lit("V3"), "door_id"))
    box = venue.partitions.where("xmin is not null").drop("floor", "kind", "venue_id")
    edge = sides.join(box, "part_id").join(venue.doors, "door_id")
    on_edge = F.col("x_mm").between(F.col("xmin"), F.col("xmax")) & F.col("y_mm").between(F.col("ymin"), F.col("ymax")) & ((F.col("x_mm") == F.col("xmin")) | (F.col("x_mm") == F.col("xmax")) | (F.col("y_mm") == F.col("ymin")) | (F.col("y_mm") == F.col("ymax")))
    out = out.union(edge.where(~on_edge & F.col("kind").isin("room_main", "through", "segment")).select(F.lit("V4"), "door_id"))
    spot = lambda side: venue.doors.select(F.col("door_id").alias(f"{side}_door"), F.col("floor").alias(f"{side}f"), F.col("x_mm").alias(f"{side}x"), F.col("y_mm").alias(f"{side}y"))
    short = graph_legs(venue).join(spot("a"), "a_door").join(spot("b"), "b_door").where("af = bf").where(F.col("leg_mm") < leg_mm("ax", "ay", "bx", "by"))
    out = out.union(short.select(F.lit("V5"), "a_door"))
    kinds = venue.doors.select(F.col("door_id").alias("a_door"), "kind")
    still = graph_legs(venue).where("leg_mm = 0").join(kinds, "a_door").where("kind not in ('stair_low', 'stair_high')")
    return out.union(still.select(F.lit("V6"), "a_door")).distinct()


def validate_points(points: DataFrame, placed: DataFrame) -> DataFrame:
    """Points outside every partition."""
    return points.join(placed.select("qid"), "qid", "left_anti").select("qid")


def broken_venue(venue: Venue) -> Venue:
    """The venue with planted faults: a partition twice, main doors of the lowest floor off their walls, the entrance with a
    third partition, the exit without any."""
    first = venue.partitions.where("part_id <> 0").agg(F.min("part_id")).first()[0]
    parts = venue.partitions.union(venue.partitions.where(F.col("part_id") == first))
    doors = venue.doors.withColumn("y_mm", F.when((F.col("kind") == "room_main") & (F.col("floor") == 0), F.col("y_mm") + 1).otherwise(F.col("y_mm")))
    moves = venue.moves.where(F.col("door_id") != EXIT_ONLY)
    extra = moves.where(F.col("door_id") == ENTRANCE).limit(1).withColumn("to_part", F.lit(first).cast("long"))
    return Venue(venue.spark, venue.sf_dir, venue.floors, "broken", parts, doors.select(*venue.doors.columns), moves.unionByName(extra))


def connectivity(matrix: DataFrame) -> DataFrame:
    """(reachable, one_way): ordered door pairs with a way, and those of them without a way back."""
    pairs = matrix.where("a_door <> b_door").select("a_door", "b_door")
    back = pairs.select(F.col("b_door").alias("a_door"), F.col("a_door").alias("b_door"), F.lit(1).alias("back"))
    return pairs.join(back, ["a_door", "b_door"], "left").agg(F.count("*").alias("reachable"), F.sum(F.col("back").isNull().cast("long")).alias("one_way"))


def kind_maps(venue: Venue) -> DataFrame:
    """(floor, kinds, rooms, frequent): a floor's partition counts as a map by kind, looked into and filtered."""
    counts = venue.partitions.where("part_id <> 0").groupBy("floor", "kind").agg(F.count("*").alias("n"))
    maps = counts.groupBy("floor").agg(F.map_from_entries(F.sort_array(F.collect_list(F.struct("kind", "n")))).alias("m"))
    return maps.select("floor", F.size("m").alias("kinds"), F.coalesce(F.element_at("m", F.lit("room")), F.lit(0)).alias("rooms"), F.size(F.map_filter("m", lambda k, n: n >= 5)).alias("frequent"))


def dv_ranks(venue: Venue) -> DataFrame:
    """(part_id, place, dense, quarter, share): partitions of a kind ranked by their doors."""
    order = Window.partitionBy("kind").orderBy("dv")
    whole = Window.partitionBy("kind").orderBy("dv", "part_id")
    return dv_counts(venue).select("part_id", F.rank().over(order).alias("place"), F.dense_rank().over(order).alias("dense"), F.ntile(4).over(whole).alias("quarter"), F.floor(F.percent_rank().over(order) * 1000).cast("long").alias("share"))


def events_last_hour(moving: DataFrame) -> DataFrame:
    """(event_id, n): a user's events in the hour up to each event, by a frame over time in whole seconds, the nearest (halves to even)."""
    second = F.rint(F.col("ts").cast("timestamp").cast("double")).cast("long")
    frame = Window.partitionBy("user_id").orderBy(second).rangeBetween(-3600, 0)
    return moving.select("event_id", F.count("*").over(frame).alias("n"))


def word_profile(venue: Venue) -> DataFrame:
    """(first_word, parts, longest, brand_no, nearest): words of part names, brand numbers, spelling distance to `green`."""
    parts = table(venue.spark, venue.sf_dir, "part").select(F.split(F.lower("p_name"), " ").alias("words"), F.regexp_extract("p_brand", "([0-9]+)", 1).cast("int").alias("brand"))
    named = parts.select(F.element_at("words", 1).alias("first_word"), F.length(F.array_join("words", "")).alias("size"), "brand")
    return named.groupBy("first_word").agg(F.count("*").alias("parts"), F.max("size").alias("longest"), F.max("brand").alias("brand_no"), F.min(F.levenshtein("first_word", F.lit("green"))).alias("nearest"))


def event_calendar(venue: Venue) -> DataFrame:
    """(weekday, hour, n): events by weekday (Sunday is 1) and hour."""
    events = table(venue.spark, venue.sf_dir, "events").select(F.col("ts").cast("timestamp").alias("ts"))
    return events.groupBy(F.dayofweek("ts").alias("weekday"), F.hour("ts").alias("hour")).agg(F.count("*").alias("n"))
