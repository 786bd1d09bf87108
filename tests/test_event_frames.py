"""Frames over event time against DuckDB on times with fractions of a second."""

import duckdb
from pyspark.sql import functions as F

from floorwalk.operators import surrounding


def test_last_hour_counts_nearest_seconds(spark):
    times = ["00:00:00.5", "00:00:00.6", "00:00:01.5", "01:00:00.4", "01:00:00.500001", "01:00:01.2", "01:00:01.5", "01:00:02.5", "02:00:02.499999"]
    rows = [(7, i, f"2024-01-15 {t}") for i, t in enumerate(times)]
    moving = spark.createDataFrame(rows, "user_id long, event_id long, ts string").withColumn("ts", F.col("ts").cast("timestamp_ntz"))
    found = sorted(map(tuple, surrounding.events_last_hour(moving).collect()))
    pos = ", ".join(f"({u}, {e}, timestamp '{t}')" for u, e, t in rows)
    want = duckdb.sql(f"select event_id, count(*) over (partition by user_id order by epoch(ts)::bigint range between 3600 preceding and current row) as n from (values {pos}) p(user_id, event_id, ts)").fetchall()
    assert found == sorted(want)
