"""The venue that the given star-schema tables carry: regions are floors, nations hallways, suppliers rooms.

Everything is a pure function of the tables (rules in FIXTURES.md); coordinates are integer millimetres.
"""

from __future__ import annotations

from dataclasses import dataclass, field

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from floorwalk.sources.scratch import materialize

FLOOR_STEP, ROOM, HALL, LOBBY, STAIR_LOW, STAIR_HIGH = 100_000_000, 10_000_000, 1_000_000, 2_000_000, 3_000_000, 4_000_000
SECOND, THROUGH, ENTRANCE, EXIT_ONLY, STAIR_MM, OUTDOOR = 20_000_000, 30_000_000, 5_000_000, 5_000_001, 20_000, 0
CUTS = {"base": 4, "sparse": 4, "dense": 4, "fine": 2, "nocut": 99}


@dataclass
class Venue:
    """One building: partitions, doors and legal movements, and optional inherited interior distances of concave cells."""

    spark: SparkSession
    sf_dir: str
    floors: int
    variant: str
    partitions: DataFrame
    doors: DataFrame
    moves: DataFrame
    override: DataFrame | None = None
    cache: dict = field(default_factory=dict)

    def remember(self, key, make):
        """Derived tables are made once per venue and written out."""
        if key not in self.cache:
            self.cache[key] = make()
        return self.cache[key]


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def halls(spark: SparkSession, sf_dir: str, floors: int) -> DataFrame:
    """(floor, base, nation, g, rooms, cols, length, y): one hallway per nation and floor."""
    nation = table(spark, sf_dir, "nation").select(F.col("n_nationkey").cast("long").alias("nation"), F.col("n_regionkey").cast("long").alias("template"))
    nation = nation.withColumn("g", (F.row_number().over(Window.partitionBy("template").orderBy("nation")) - 1).cast("long"))
    rooms = table(spark, sf_dir, "supplier").groupBy(F.col("s_nationkey").cast("long").alias("nation")).agg(F.count("*").alias("rooms"))
    levels = spark.range(floors).select(F.col("id").alias("floor"), (F.col("id") % 5).alias("template"), (F.col("id") * FLOOR_STEP).alias("base"))
    out = levels.join(nation, "template").join(rooms, "nation", "left").withColumn("rooms", F.coalesce("rooms", F.lit(0).cast("long")))
    cols = F.greatest(F.lit(1).cast("long"), F.floor((F.col("rooms") + 1) / 2))
    return out.withColumn("cols", cols).withColumn("length", cols * 10_000).withColumn("y", F.col("g") * 20_000).drop("template")


def rooms_of(spark: SparkSession, sf_dir: str, hall: DataFrame) -> DataFrame:
    """(room ordinal i, column c, side, supplier s) of every floor."""
    supplier = table(spark, sf_dir, "supplier").select(F.col("s_suppkey").cast("long").alias("s"), F.col("s_nationkey").cast("long").alias("nation"))
    placed = supplier.withColumn("i", (F.row_number().over(Window.partitionBy("nation").orderBy("s")) - 1).cast("long"))
    placed = placed.withColumn("c", F.floor(F.col("i") / 2)).withColumn("side", F.col("i") % 2)
    return placed.join(hall, "nation")


def _stairs(hall: DataFrame, cut: int) -> DataFrame:
    """(floor, base, k, host, x, y): where stair k meets each floor."""
    lobby = hall.where(F.col("g").isin(0, 4)).select("floor", "base", F.when(F.col("g") == 0, 0).otherwise(1).cast("long").alias("k"), (F.col("base") + LOBBY + F.col("g")).alias("host"), F.lit(-6000).cast("long").alias("x"), F.when(F.col("g") == 0, 10_000).otherwise(90_000).cast("long").alias("y"))
    last = F.ceil(F.col("cols") / cut) - 1
    ends = hall.where(F.col("g").isin(1, 3)).select("floor", "base", F.when(F.col("g") == 1, 2).otherwise(3).cast("long").alias("k"), (F.col("base") + HALL + F.col("nation") * 1000 + last).alias("host"), F.col("length").alias("x"), F.when(F.col("g") == 1, 30_000).otherwise(70_000).cast("long").alias("y"))
    return lobby.union(ends)


PARTITION_COLUMNS = ("part_id", "kind", "floor", "xmin", "ymin", "xmax", "ymax", "stair_mm", "parent_part")


def _partitions(hall: DataFrame, room: DataFrame, floors: int, cut: int) -> DataFrame:
    nothing = F.lit(None).cast("long")
    cells = hall.withColumn("s", F.explode(F.sequence(F.lit(0).cast("long"), F.ceil(F.col("cols") / cut) - 1)))
    parent = F.col("base") + HALL + F.col("nation") * 1000
    frames = [
        cells.select((parent + F.col("s")).alias("part_id"), F.lit("hall").alias("kind"), "floor", (F.col("s") * 10_000 * cut).alias("xmin"), (F.col("y") + 8000).alias("ymin"), F.least(F.col("length"), (F.col("s") + 1) * 10_000 * cut).alias("xmax"), (F.col("y") + 12_000).alias("ymax"), nothing.alias("stair_mm"), parent.alias("parent_part")),
        hall.select((F.col("base") + LOBBY + F.col("g")).alias("part_id"), F.lit("lobby").alias("kind"), "floor", F.lit(-6000).cast("long").alias("xmin"), F.col("y").alias("ymin"), F.lit(0).cast("long").alias("xmax"), (F.col("y") + 20_000).alias("ymax"), nothing.alias("stair_mm"), nothing.alias("parent_part")),
        room.select((F.col("base") + ROOM + F.col("s")).alias("part_id"), F.lit("room").alias("kind"), "floor", (F.col("c") * 10_000).alias("xmin"), (F.col("y") + F.when(F.col("side") == 0, 12_000).otherwise(0)).alias("ymin"), ((F.col("c") + 1) * 10_000).alias("xmax"), (F.col("y") + F.when(F.col("side") == 0, 20_000).otherwise(8000)).alias("ymax"), nothing.alias("stair_mm"), nothing.alias("parent_part")),
        hall.where(F.col("floor") < floors - 1).select("floor", "base").distinct().withColumn("k", F.explode(F.sequence(F.lit(0), F.lit(3)))).select((F.col("base") + STAIR_LOW + F.col("k")).alias("part_id"), F.lit("stair").alias("kind"), "floor", *[nothing.alias(c) for c in ("xmin", "ymin", "xmax", "ymax")], F.lit(STAIR_MM).cast("long").alias("stair_mm"), nothing.alias("parent_part")),
    ]
    outdoor = hall.sparkSession.range(1).select(F.lit(OUTDOOR).cast("long").alias("part_id"), F.lit("outdoor").alias("kind"), F.lit(None).cast("long").alias("floor"), *[nothing.alias(c) for c in ("xmin", "ymin", "xmax", "ymax", "stair_mm", "parent_part")])
    out = outdoor
    for frame in frames:
        out = out.unionByName(frame)
    return out.select(F.lit(0).alias("venue_id"), *PARTITION_COLUMNS)


def _doors(spark: SparkSession, hall: DataFrame, room: DataFrame, floors: int, cut: int, variant: str) -> DataFrame:
    """Doors with their movements as an array: (door_id, kind, floor, x_mm, y_mm, moves array<struct<from, to>>)."""
    move = lambda a, b: F.struct(a.alias("from_part"), b.alias("to_part"))
    none = F.lit(None).cast("struct<from_part:bigint,to_part:bigint>")

    def door(frame, ident, kind, x, y, first, second):
        both = F.filter(F.array(first, second), lambda m: m.isNotNull())
        return frame.select(ident.cast("long").alias("door_id"), F.lit(kind).alias("kind"), "floor", x.cast("long").alias("x_mm"), y.cast("long").alias("y_mm"), both.alias("moves"))

    base, y = F.col("base"), F.col("y")
    cell0 = base + HALL + F.col("nation") * 1000
    lobby = base + LOBBY + F.col("g")
    cells = hall.withColumn("last", F.ceil(F.col("cols") / cut) - 1).where(F.col("last") > 0).withColumn("s", F.explode(F.sequence(F.lit(0).cast("long"), F.col("last") - 1)))
    here, there = cell0 + F.col("s"), cell0 + F.col("s") + 1
    out = [
        door(cells, here, "segment", (F.col("s") + 1) * 10_000 * cut, y + 10_000, move(here, there), move(there, here)),
        door(hall, base + LOBBY + F.col("g"), "lobby_hall", F.lit(0), y + 10_000, move(lobby, cell0), move(cell0, lobby)),
        door(hall.where("g < 4"), base + LOBBY + 1000 + F.col("g"), "lobby_lobby", F.lit(-3000), y + 20_000, move(lobby, lobby + 1), move(lobby + 1, lobby)),
    ]
    own, cell = base + ROOM + F.col("s"), cell0 + F.floor(F.col("c") / cut)
    wall = y + F.when(F.col("side") == 0, 12_000).otherwise(8000)
    out.append(door(room, own, "room_main", F.col("c") * 10_000 + 5000, wall, move(cell, own), move(own, cell)))
    if variant != "sparse":
        some = room if variant == "dense" else room.where("s % 3 = 0")
        out.append(door(some, base + SECOND + F.col("s"), "room_second", F.col("c") * 10_000 + 8000, wall, move(own, cell), F.when(F.col("s") % 2 != 0, move(cell, own)).otherwise(none)))
        upper = room.where("side = 0").select("floor", "base", "g", "c", "s")
        lower = room.where("side = 1").select("floor", (F.col("g") - 1).alias("g"), "c", F.col("s").alias("t"))
        pairs = upper.join(lower, ["floor", "g", "c"])
        a, b = base + ROOM + F.col("s"), base + ROOM + F.col("t")
        out.append(door(pairs, base + THROUGH + F.col("s"), "through", F.col("c") * 10_000 + 5000, (F.col("g") + 1) * 20_000, move(a, b), F.when(F.col("s") % 5 != 0, move(b, a)).otherwise(none)))
    stairs = _stairs(hall, cut)
    low = stairs.where(F.col("floor") < floors - 1)
    flight = base + STAIR_LOW + F.col("k")
    out.append(door(low, flight, "stair_low", F.col("x"), y, move(F.col("host"), flight), F.when(F.col("k") != 3, move(flight, F.col("host"))).otherwise(none)))
    below = flight - FLOOR_STEP
    out.append(door(stairs.where("floor > 0"), base - FLOOR_STEP + STAIR_HIGH + F.col("k"), "stair_high", F.col("x"), y, move(below, F.col("host")), F.when(F.col("k") != 3, move(F.col("host"), below)).otherwise(none)))
    ground = spark.range(1).select(F.lit(0).cast("long").alias("floor"))
    outdoor = F.lit(OUTDOOR).cast("long")
    place = lambda g: F.lit(LOBBY + g).cast("long")
    out.append(door(ground, F.lit(ENTRANCE), "entrance", F.lit(-6000), F.lit(50_000), move(outdoor, place(2)), move(place(2), outdoor)))
    out.append(door(ground, F.lit(EXIT_ONLY), "exit_only", F.lit(-3000), F.lit(100_000), move(place(4), outdoor), none))
    whole = out[0]
    for frame in out[1:]:
        whole = whole.unionByName(frame)
    return whole


_venues: dict[tuple, Venue] = {}


def build_venue(spark: SparkSession, sf_dir: str, floors: int = 5, variant: str = "base") -> Venue:
    """The venue of a scale-factor folder; the same session gets the same object again."""
    key = (spark.sparkContext.applicationId, sf_dir, floors, variant)
    if key not in _venues:
        if variant == "merged":
            from floorwalk.operators.topology import merge_hallways

            _venues[key] = merge_hallways(build_venue(spark, sf_dir, floors, "base"))
        else:
            cut = CUTS[variant]
            hall = halls(spark, sf_dir, floors)
            room = rooms_of(spark, sf_dir, hall)
            doors = materialize(_doors(spark, hall, room, floors, cut, variant))
            moves = doors.select(F.lit(0).alias("venue_id"), "door_id", F.explode("moves").alias("m")).select("venue_id", "door_id", "m.from_part", "m.to_part")
            _venues[key] = Venue(
                spark, sf_dir, floors, variant, materialize(_partitions(hall, room, floors, cut)),
                doors.select(F.lit(0).alias("venue_id"), "door_id", "kind", "floor", "x_mm", "y_mm"), materialize(moves),
            )
    return _venues[key]


def place(keys: DataFrame, hall: DataFrame, room: DataFrame, floors: int) -> DataFrame:
    """keys (key, nation, ...) -> + floor, x_mm, y_mm: a point in a room of the nation's hallway, or in the hallway."""
    copies = hall.select("nation", "floor", "g", "rooms", "length", "y", "base")
    if floors == 5:
        spots = keys.join(copies, "nation")
    else:
        nation_g = copies.groupBy("nation").agg(F.first("g").alias("g0"), F.sort_array(F.collect_set("floor")).alias("levels"))
        everywhere = keys.join(nation_g, "nation", "left")
        spots = _spread(everywhere, hall, floors)
    o = F.col("key") % (F.col("rooms") + 1)
    spots = spots.withColumn("o", o).withColumn("c", F.floor(o / 2)).withColumn("in_room", o < F.col("rooms"))
    low = F.col("y") + F.when(o % 2 == 0, 12_000).otherwise(0)
    x = F.when(F.col("in_room"), F.col("c") * 10_000 + 1 + (F.col("key") * 7919) % 9998).otherwise(1 + (F.col("key") * 7919) % (F.col("length") - 2))
    y = F.when(F.col("in_room"), low + 1 + (F.col("key") * 104_729) % 7998).otherwise(F.col("y") + 8001 + (F.col("key") * 104_729) % 3998)
    return spots.withColumn("x_mm", x.cast("long")).withColumn("y_mm", y.cast("long"))


def _spread(keys: DataFrame, hall: DataFrame, floors: int) -> DataFrame:
    """Floors for venues of other heights: the copies of the nation's region, or the nation of the same g elsewhere."""
    spark = keys.sparkSession
    sf_dir = next(k[1] for k in _venues if k[0] == spark.sparkContext.applicationId)
    nation = table(spark, sf_dir, "nation").select(F.col("n_nationkey").cast("long").alias("nation"), F.col("n_regionkey").cast("long").alias("region"))
    nation = nation.withColumn("own_g", (F.row_number().over(Window.partitionBy("region").orderBy("nation")) - 1).cast("long"))
    placed = keys.drop("g0", "levels").join(nation, "nation")
    copies = F.floor((F.lit(floors - 1) - F.col("region")) / 5) + 1
    copies = F.when(F.col("region") < floors, copies).otherwise(0)
    floor = F.when(copies > 0, F.col("region") + 5 * (F.col("key") % F.greatest(copies, F.lit(1)))).otherwise(F.col("key") % floors).cast("long")
    there = hall.select("floor", F.col("g").alias("own_g"), "rooms", "length", "y", "base", F.col("nation").alias("hall_nation"))
    return placed.withColumn("floor", floor).join(there, ["floor", "own_g"]).withColumnRenamed("own_g", "g")


def objects(venue: Venue, limit: int | None = None) -> DataFrame:
    """(object_id, floor, x_mm, y_mm, part_id): customers as static objects, each in the cell that holds it."""
    from floorwalk.operators.host import locate_grid

    def make():
        spark = venue.spark
        keys = table(spark, venue.sf_dir, "customer").select(F.col("c_custkey").cast("long").alias("key"), F.col("c_nationkey").cast("long").alias("nation"))
        hall = halls(spark, venue.sf_dir, venue.floors)
        spots = place(keys, hall, None, venue.floors).select(F.col("key").alias("qid"), "floor", "x_mm", "y_mm")
        return materialize(locate_grid(spots, venue.partitions).select(F.col("qid").alias("object_id"), "floor", "x_mm", "y_mm", "part_id"))

    out = venue.remember("objects", make)
    return out if limit is None else out.where(F.col("object_id") < limit)


def order_points(venue: Venue) -> DataFrame:
    """(qid, floor, x_mm, y_mm): every order's point."""
    spark = venue.spark
    nation = table(spark, venue.sf_dir, "customer").select(F.col("c_custkey").alias("o_custkey"), F.col("c_nationkey").cast("long").alias("nation"))
    keys = table(spark, venue.sf_dir, "orders").select(F.col("o_orderkey").cast("long").alias("key"), "o_custkey").join(nation, "o_custkey")
    hall = halls(spark, venue.sf_dir, venue.floors)
    return place(keys, hall, None, venue.floors).select(F.col("key").alias("qid"), "floor", "x_mm", "y_mm")


def query_points(venue: Venue, n: int = 10) -> DataFrame:
    """The first n orders' points."""
    return venue.remember(("points", n), lambda: materialize(order_points(venue).where(F.col("qid") < n)))


def query_pairs(venue: Venue, n_orders: int = 10) -> DataFrame:
    """(qid, s_floor, s_x, s_y, t_floor, t_x, t_y): order's point to the centre of each of its suppliers' rooms."""

    def make():
        lines = table(venue.spark, venue.sf_dir, "lineitem").where(F.col("l_orderkey") < n_orders).select(F.col("l_orderkey").cast("long").alias("o"), F.col("l_suppkey").cast("long").alias("s")).distinct()
        source = order_points(venue).select(F.col("qid").alias("o"), F.col("floor").alias("s_floor"), F.col("x_mm").alias("s_x"), F.col("y_mm").alias("s_y"))
        base = venue.partitions.where("kind = 'room'").select((F.col("part_id") % FLOOR_STEP - ROOM).alias("s"), F.col("floor").alias("t_floor"), (F.col("xmin") + 5000).alias("t_x"), (F.col("ymin") + 4000).alias("t_y"))
        first = base.groupBy("s").agg(F.min(F.struct("t_floor", "t_x", "t_y")).alias("t")).select("s", "t.t_floor", "t.t_x", "t.t_y")
        return materialize(lines.join(source, "o").join(first, "s").select((F.col("o") * 1_000_000 + F.col("s")).alias("qid"), "s_floor", "s_x", "s_y", "t_floor", "t_x", "t_y"))

    return venue.remember(("pairs", n_orders), make)
