"""Exchange and persistence: floor plans from CSV or JSON, model tables as Parquet or buckets, a generator source."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition

from floorwalk.sources.venue import Venue

SCHEMAS = {
    "partitions": "venue_id int, part_id long, kind string, floor long, xmin long, ymin long, xmax long, ymax long, stair_mm long, parent_part long",
    "doors": "venue_id int, door_id long, kind string, floor long, x_mm long, y_mm long",
    "moves": "venue_id int, door_id long, from_part long, to_part long",
}


def save_floorplan(venue: Venue, folder: str, form: str = "csv") -> None:
    for name in SCHEMAS:
        writer = getattr(venue, name).write.mode("overwrite")
        writer.csv(f"{folder}/{name}", header=True) if form == "csv" else writer.json(f"{folder}/{name}")


def load_floorplan(spark: SparkSession, folder: str, form: str = "csv") -> Venue:
    """A venue from exchange files of the three tables, with their fixed schemas."""
    read = lambda name: spark.read.csv(f"{folder}/{name}", schema=SCHEMAS[name], header=True) if form == "csv" else spark.read.json(f"{folder}/{name}", schema=SCHEMAS[name])
    parts, doors, moves = (read(n) for n in SCHEMAS)
    return Venue(spark, folder, 0, "imported", parts, doors, moves)


def save_model(frames: dict[str, DataFrame], folder: str) -> None:
    """Model tables as Parquet, partitioned by venue where they carry one."""
    for name, frame in frames.items():
        writer = frame.write.mode("overwrite")
        (writer.partitionBy("venue_id") if "venue_id" in frame.columns else writer).parquet(f"{folder}/{name}")


def load_model(spark: SparkSession, folder: str, names: list[str]) -> dict[str, DataFrame]:
    return {n: spark.read.parquet(f"{folder}/{n}") for n in names}


def save_bucketed(matrix: DataFrame, name: str, buckets: int = 16) -> None:
    """A matrix as a table bucketed by its start door and sorted by distance: range scans skip row groups, joins skip shuffles."""
    matrix.write.mode("overwrite").bucketBy(buckets, "a_door").sortBy("a_door", "dist_mm").saveAsTable(name)


class _Slice(InputPartition):
    def __init__(self, venue: int) -> None:
        self.venue = venue


class _TowerReader(DataSourceReader):
    def __init__(self, options: dict) -> None:
        self.venues, self.floors, self.rooms = (int(options.get(k, d)) for k, d in (("venues", 1), ("floors", 3), ("rooms", 10)))

    def partitions(self) -> list[_Slice]:
        return [_Slice(v) for v in range(self.venues)]

    def read(self, part: _Slice):
        for floor in range(self.floors):
            yield part.venue, floor * 1000, "hall", floor, 0, 0, self.rooms * 5000, 4000
            for room in range(self.rooms):
                yield part.venue, floor * 1000 + 1 + room, "room", floor, room * 5000, 4000, (room + 1) * 5000, 12_000


class TowerSource(DataSource):
    """Synthetic towers for scale tests: options venues, floors, rooms (per floor). One task per venue."""

    @classmethod
    def name(cls) -> str:
        return "floorwalk_tower"

    def schema(self) -> str:
        return "venue_id int, part_id int, kind string, floor int, xmin int, ymin int, xmax int, ymax int"

    def reader(self, schema) -> _TowerReader:
        return _TowerReader(self.options)


def register(spark: SparkSession) -> None:
    spark.dataSource.register(TowerSource)
