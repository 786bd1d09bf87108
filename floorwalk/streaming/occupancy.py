"""Structured Streaming over position events: occupancy windows, visits, range monitoring, meetings."""

from __future__ import annotations

import uuid
from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from floorwalk.operators.extend import numbered_rooms
from floorwalk.operators.labels import cells_entered, point_labels
from floorwalk.operators.range import placed_points
from floorwalk.sources.scratch import shared_folder
from floorwalk.sources.venue import Venue

LATE = "10 days"


def event_stream(spark: SparkSession, sf_dir: str, per_trigger: int = 1) -> DataFrame:
    """Replays the events table as a stream of (user_id, ts, event_id, event_type, props)."""
    path = f"{sf_dir}/events.parquet"
    schema = spark.read.parquet(path).schema
    stream = spark.readStream.schema(schema).option("maxFilesPerTrigger", per_trigger).option("pathGlobFilter", "*.parquet")
    # A file source reads folders: the folder of the table, restricted to its own file, or the table's folder.
    folder, name = path.rsplit("/", 1)
    raw = stream.option("pathGlobFilter", name).load(folder) if not _is_folder(spark, path) else stream.load(path)
    return raw.withColumn("ts", F.col("ts").cast("timestamp")).withColumn("event_id", F.col("event_id").cast("long"))


def _is_folder(spark: SparkSession, path: str) -> bool:
    target = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(path)
    return target.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).getFileStatus(target).isDirectory()


def place_events(venue: Venue, events: DataFrame) -> DataFrame:
    """Adds part_id, floor, x_mm, y_mm to a batch or stream of events by the position rule (stream-static join)."""
    rooms = venue.partitions.where("kind = 'room' and floor < 5").select("part_id", "floor", "xmin", "ymin")
    rooms, total = numbered_rooms(rooms)
    spot = events.withColumn("n", (31 * F.col("event_id") + F.col("user_id")) % total)
    joined = spot.join(rooms, "n")
    return joined.withColumn("x_mm", F.col("xmin") + 1 + (F.col("event_id") * 7919) % 9998).withColumn("y_mm", F.col("ymin") + 1 + (F.col("event_id") * 104_729) % 7998).drop("n", "xmin", "ymin")


def deduplicated(stream: DataFrame, late: str = LATE) -> DataFrame:
    """Each event once, whatever the replay: state is dropped behind the watermark."""
    return stream.withWatermark("ts", late).dropDuplicatesWithinWatermark(["event_id"])


def tumbling(positions: DataFrame) -> DataFrame:
    """(start_ts, part_id, n) per hour."""
    out = positions.groupBy(F.window("ts", "1 hour"), "part_id").agg(F.count("*").alias("n"))
    return out.select(F.col("window.start").alias("start_ts"), "part_id", "n")


def sliding(positions: DataFrame) -> DataFrame:
    """(start_ts, part_id, n) per two hours, every half hour."""
    out = positions.groupBy(F.window("ts", "2 hours", "30 minutes"), "part_id").agg(F.count("*").alias("n"))
    return out.select(F.col("window.start").alias("start_ts"), "part_id", "n")


def visits(positions: DataFrame, gap: str = "30 minutes") -> DataFrame:
    """(user_id, start_ts, end_ts, n): sessions of a user's events."""
    out = positions.groupBy(F.session_window("ts", gap), "user_id").agg(F.count("*").alias("n"))
    return out.select("user_id", F.col("session_window.start").alias("start_ts"), F.col("session_window.end").alias("end_ts"), "n")


def run_once(stream: DataFrame, mode: str = "append") -> DataFrame:
    """Drives a stream over all there is into the shared folder and returns what it wrote as a frame.

    Rows stay with the executors: each micro-batch is a folder of its own, so a batch that is run again replaces its own rows.
    In complete mode the last batch is the whole result.
    """
    spark, schema, path = stream.sparkSession, stream.schema, f"{shared_folder(stream.sparkSession)}/floorwalk-stream-{uuid.uuid4().hex}"
    written: dict[int, str] = {}

    def write(batch: DataFrame, number: int) -> None:
        batch.write.mode("overwrite").parquet(f"{path}/b{number}")
        written[number] = f"{path}/b{number}"

    query = stream.writeStream.foreachBatch(write).outputMode(mode).trigger(availableNow=True).option("checkpointLocation", f"{path}/checkpoint").start()
    query.awaitTermination()
    if not written:
        return spark.createDataFrame([], schema)
    kept = [written[max(written)]] if mode == "complete" else [written[n] for n in sorted(written)]
    return spark.read.schema(schema).parquet(*kept)


def within_range(venue: Venue, point: DataFrame, radius_mm: int, method: str = "dm") -> DataFrame:
    """(part_id, door_x, door_y, dist): what a position needs to be tested against a fixed point's range."""
    placed = placed_points(venue, point)
    found = cells_entered(venue, point_labels(method, venue, placed, radius_mm))
    spot = venue.doors.select("door_id", F.col("x_mm").alias("door_x"), F.col("y_mm").alias("door_y"))
    via = found.join(spot, F.col("door") == F.col("door_id")).select("part_id", "door_x", "door_y", "dist")
    return via.union(placed.select("part_id", "x_mm", "y_mm", F.lit(0).cast("long")))


def monitored(positions: DataFrame, area: DataFrame, radius_mm: int) -> DataFrame:
    """(event_id, user_id, ts, inside): whether a position lies within the monitored range, one row per event."""
    ways = area.groupBy("part_id").agg(F.collect_list(F.struct("door_x", "door_y", "dist")).alias("ways"))
    joined = positions.join(ways, "part_id", "left")
    leg = lambda w: w["dist"] + F.ceil(F.sqrt(((F.col("x_mm") - w["door_x"]) * (F.col("x_mm") - w["door_x"]) + (F.col("y_mm") - w["door_y"]) * (F.col("y_mm") - w["door_y"])).cast("double")))
    inside = F.coalesce(F.exists("ways", lambda w: leg(w) <= radius_mm), F.lit(False))
    return joined.select("event_id", "user_id", "ts", inside.alias("inside"))


def alerts(states: DataFrame, late: str = "0 seconds") -> DataFrame:
    """(user_id, ts, event): `enter` and `leave` when a user's state changes, in the order of event time.

    Rows wait in the user's state until the watermark has passed them, so the order in which they arrive is of no matter;
    rows behind what has been told of the user are dropped, rows before the watermark stay until it moves on.
    """
    schema = T.StructType([T.StructField("user_id", T.LongType()), T.StructField("ts", T.TimestampType()), T.StructField("event", T.StringType())])
    waiting = T.ArrayType(T.LongType())
    held = T.StructType([T.StructField("inside", T.BooleanType()), T.StructField("passed", T.LongType()), T.StructField("us", waiting), T.StructField("ids", waiting), T.StructField("flags", waiting)])

    def watch(key, frames: Iterator[pd.DataFrame], state) -> Iterator[pd.DataFrame]:
        was, passed, *old = state.get if state.exists else (False, -1, [], [], [])
        new = [] if state.hasTimedOut else list(frames)
        at = [np.asarray(x, dtype=np.int64) for x in old]
        for rows in new:
            stamps = rows["ts"].to_numpy().astype("datetime64[us]").astype(np.int64)
            fresh = stamps // 1000 >= passed  # what is behind has been told already
            columns = (stamps, rows["event_id"].to_numpy(), rows["inside"].to_numpy().astype(np.int64))
            at = [np.concatenate([x, y[fresh]]) for x, y in zip(at, columns, strict=True)]
        mark = state.getCurrentWatermarkMs()
        order = np.lexsort((at[1], at[0]))
        us, ids, flags = (x[order] for x in at)
        ready = int(np.searchsorted(us // 1000, mark, side="left")) if mark > 0 else 0
        seen = np.concatenate([[int(was)], flags[:ready]])
        change = np.flatnonzero(np.diff(seen))
        state.update((bool(seen[-1]), int(mark), us[ready:].tolist(), ids[ready:].tolist(), flags[ready:].tolist()))
        if ready < len(us):
            state.setTimeoutTimestamp(int(max(mark, us[ready] // 1000)) + 1)
        stamps = pd.to_datetime(us[change], unit="us")
        yield pd.DataFrame({"user_id": np.full(len(change), key[0]), "ts": stamps, "event": np.where(flags[change] == 1, "enter", "leave")})

    return states.withWatermark("ts", late).groupBy("user_id").applyInPandasWithState(watch, schema, held, "append", "EventTimeTimeout")


def upserts(stream: DataFrame, keys: list[str], merge, mode: str = "append") -> DataFrame:
    """Drives a stream into a table that each micro-batch is merged into, merge(old and new rows) -> rows; returns the table.

    Every version is a folder of its own in the shared folder, written before the next one is named, so a batch that is
    run again after a failure starts from the version before it.
    """
    spark, path = stream.sparkSession, f"{shared_folder(stream.sparkSession)}/floorwalk-upserts-{uuid.uuid4().hex}"
    schema = stream.schema

    def write(batch: DataFrame, number: int) -> None:
        rows = batch.select(*schema.names)
        if number > 0:
            rows = batch.sparkSession.read.schema(schema).parquet(f"{path}/v{number - 1}").unionByName(rows)
        merge(rows, keys).select(*schema.names).write.mode("overwrite").parquet(f"{path}/v{number}")

    query = stream.writeStream.foreachBatch(write).outputMode(mode).trigger(availableNow=True).option("checkpointLocation", f"{path}/checkpoint").start()
    query.awaitTermination()
    last = query.lastProgress["batchId"] if query.lastProgress else -1
    while last >= 0:
        try:
            return spark.read.schema(schema).parquet(f"{path}/v{last}")
        except Exception:  # noqa: BLE001  a last batch without data writes no version
            last -= 1
    return spark.createDataFrame([], schema)


def latest(rows: DataFrame, keys: list[str]) -> DataFrame:
    """The row with the greatest (ts, event_id) of each key."""
    others = [c for c in rows.columns if c not in keys]
    newest = rows.groupBy(*keys).agg(F.max_by(F.struct(*others), F.struct("ts", "event_id")).alias("l"))
    return newest.select(*keys, *[F.col(f"l.{c}").alias(c) for c in others])


def greatest_count(rows: DataFrame, keys: list[str]) -> DataFrame:
    """Counts only grow, so the greatest is the last update."""
    return rows.groupBy(*keys).agg(F.max("n").alias("n"))


def meetings(left: DataFrame, right: DataFrame, within: str = "10 minutes", late: str = LATE) -> DataFrame:
    """(part_id, a_user, b_user, a_ts, b_ts): pairs of users in one partition within a time, stream with stream."""
    a = left.select("part_id", F.col("user_id").alias("a_user"), F.col("ts").alias("a_ts")).withWatermark("a_ts", late)
    b = right.select(F.col("part_id").alias("b_part"), F.col("user_id").alias("b_user"), F.col("ts").alias("b_ts")).withWatermark("b_ts", late)
    close = F.expr(f"part_id = b_part and b_ts between a_ts - interval {within} and a_ts + interval {within} and a_user < b_user")
    return a.join(b, close).select("part_id", "a_user", "b_user", "a_ts", "b_ts")
