"""Streams end in written tables, not in the driver's memory."""

from pyspark.sql import functions as F

from floorwalk.streaming import occupancy


def test_streams_leave_no_rows_in_the_driver(spark, small):
    events = occupancy.event_stream(spark, small)
    before = {t.name for t in spark.catalog.listTables()}
    rows = occupancy.run_once(events.select("event_id"))
    whole = occupancy.run_once(events.groupBy("user_id").agg(F.count("*").alias("n")), "complete")
    assert {t.name for t in spark.catalog.listTables()} == before
    assert rows.inputFiles() and whole.inputFiles()
    table = spark.read.parquet(f"{small}/events.parquet")
    assert sorted(r[0] for r in rows.collect()) == sorted(r[0] for r in table.select("event_id").collect())
    assert sorted(map(tuple, whole.collect())) == sorted(map(tuple, table.groupBy("user_id").count().collect()))
