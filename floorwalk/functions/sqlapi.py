"""SQL surface: views of a venue and its models, a leg function, and a table function that unrolls paths."""

from __future__ import annotations

from collections.abc import Iterator

from pyspark.sql import SparkSession
from pyspark.sql import functions as F
from pyspark.sql.functions import udtf
from pyspark.sql.types import IntegerType, LongType, StructField, StructType

from floorwalk.operators.range import placed_points
from floorwalk.operators.route import route_query
from floorwalk.operators.topology import door_legs, door_reach, exit_legs, graph_legs
from floorwalk.plans.matrix import door_matrix
from floorwalk.sources.venue import Venue, objects, query_pairs, query_points


@udtf(returnType=StructType([StructField("step", IntegerType()), StructField("door", LongType())]))
class UnrollPath:
    def eval(self, path: str) -> Iterator[tuple[int, int]]:
        for i, door in enumerate(filter(None, (path or "").split(">"))):
            yield i, int(door)


def register(spark: SparkSession, venue: Venue, prefix: str = "indoor") -> None:
    """Views <prefix>_partitions, _doors, _moves, _legs, _graph, _reach, _matrix, _objects, _points, _hosts (points with
    their partitions), _point_legs, _paths (routes of the natural pairs) and SQL functions.

    indoor_leg(ax, ay, bx, by) is the leg in millimetres. Table functions: indoor_range(radius) and indoor_knn(k) of all
    points, indoor_route(qid) the doors of a pair's route, indoor_unroll(path) those of an 'a>b>c' path.
    """
    placed = placed_points(venue, query_points(venue))
    paths = route_query("dm", venue, query_pairs(venue), False).select("qid", "dist_mm", F.array_join(F.transform("door_path", lambda d: d.cast("string")), ">").alias("path"))
    views = {"partitions": venue.partitions, "doors": venue.doors, "moves": venue.moves, "legs": door_legs(venue), "graph": graph_legs(venue), "reach": door_reach(venue), "matrix": door_matrix(venue), "objects": objects(venue), "points": query_points(venue), "hosts": placed, "point_legs": exit_legs(venue, placed), "paths": paths}
    for name, frame in views.items():
        frame.createOrReplaceTempView(f"{prefix}_{name}")
    spark.udtf.register(f"{prefix}_unroll", UnrollPath)
    spark.sql(f"create or replace temporary function {prefix}_leg(ax bigint, ay bigint, bx bigint, by bigint) returns bigint return cast(ceil(sqrt(cast((ax-bx)*(ax-bx)+(ay-by)*(ay-by) as double))) as bigint)")
    p = prefix
    spark.sql(f"""create or replace temporary function {p}_range(radius bigint) returns table (qid bigint, object_id bigint, dist_mm bigint) return
        select qid, object_id, min(d) from (
            select l.qid, o.object_id, l.dist + m.dist_mm + {p}_leg(d.x_mm, d.y_mm, o.x_mm, o.y_mm) as d from {p}_point_legs l
            join {p}_matrix m on m.a_door = l.door and m.dist_mm <= radius - l.dist join {p}_moves v on v.door_id = m.b_door
            join {p}_doors d on d.door_id = m.b_door join {p}_objects o on o.part_id = v.to_part
            union all select h.qid, o.object_id, {p}_leg(h.x_mm, h.y_mm, o.x_mm, o.y_mm) from {p}_hosts h join {p}_objects o on o.part_id = h.part_id)
        where d <= radius group by qid, object_id""")
    spark.sql(f"""create or replace temporary function {p}_knn(k int) returns table (qid bigint, rank int, object_id bigint, dist_mm bigint) return
        select qid, rank, object_id, dist_mm from (select *, row_number() over (partition by qid order by dist_mm, object_id) as rank from {p}_range({1 << 60})) where rank <= k""")
    spark.sql(f"""create or replace temporary function {p}_route(pair bigint) returns table (step int, door bigint) return
        select u.step, u.door from {p}_paths r, lateral {p}_unroll(r.path) u where r.qid = pair""")
