"""Registered queries of the indoor engine: key -> callable(spark, sf_dir), and their oracle SQL."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from floorwalk import oracles as O
from floorwalk import workload
from floorwalk.functions import sqlapi
from floorwalk.functions.udfs import least_sum, leg_mm_py
from floorwalk.operators import extend, host, knn, metrics, route, surrounding, topology
from floorwalk.operators import range as ranges
from floorwalk.operators.labels import METHODS, NAMES, graph_labels, matrix_labels
from floorwalk.operators.topology import entry_legs, exit_legs
from floorwalk.plans import border, matrix, relax, rtree
from floorwalk.sources import venue as V
from floorwalk.sources.scratch import materialize
from floorwalk.streaming import occupancy

R_MM, K, GAMMA, AT_S, AT_TS = 60_000, 10, 6, 7 * 3600 + 1800, "2024-01-15 12:00:00"
WORDS = ("building", "brand#1")
VARIANTS = ("sparse", "dense", "fine", "nocut", "merged")

Query = Callable[[SparkSession, str], DataFrame]
_queries: dict[str, Query] = {}
_oracles: dict[str, str] = {}


def query(key: str, sql: str | None = None):
    def add(make):
        _queries[key] = lambda spark, sf_dir: make(V.build_venue(spark, sf_dir))
        if sql is not None:
            _oracles[key] = sql
        return make

    return add


def _text(path: str) -> F.Column:
    return F.array_join(F.transform(path, lambda d: d.cast("string")), ">")


# ---- topology -----------------------------------------------------------------------------------------------------

query("door_enters", O.sql("select distinct door as door_id, t as part_id from move"))(lambda v: topology.door_enters(v.moves))
query("door_leaves", O.sql("select distinct door as door_id, f as part_id from move"))(lambda v: topology.door_leaves(v.moves))
query("part_entries", O.sql("select distinct t as part_id, door as door_id from move"))(lambda v: topology.part_entries(v.moves))
query("part_exits", O.sql("select distinct f as part_id, door as door_id from move"))(lambda v: topology.part_exits(v.moves))
query("door_pairs", O.sql("select door as door_id, count(*) as n_moves, string_agg(f || '-' || t, ',' order by f, t) as moves from move group by door"))(
    lambda v: topology.door_pairs(v.moves).select("door_id", F.size("moves").cast("long").alias("n_moves"), F.array_join(F.transform("moves", lambda m: F.concat(m["from"].cast("string"), F.lit("-"), m["to"].cast("string"))), ",").alias("moves"))
)
query("part_doors", O.sql("""select part_id, count(*) filter (way = 't') as n_entries, count(*) filter (way = 'f') as n_exits, count(distinct door) as n_doors
    from (select distinct t as part_id, door, 't' as way from move union all select distinct f, door, 'f' from move) group by 1"""))(
    lambda v: topology.part_doors(v.moves).groupBy("part_id").agg(F.count("*").alias("n_doors")).join(topology.part_entries(v.moves).groupBy("part_id").agg(F.count("*").alias("n_entries")), "part_id", "left").join(topology.part_exits(v.moves).groupBy("part_id").agg(F.count("*").alias("n_exits")), "part_id", "left").select("part_id", F.coalesce("n_entries", F.lit(0)).alias("n_entries"), F.coalesce("n_exits", F.lit(0)).alias("n_exits"), "n_doors")
)
query("two_way_doors", O.sql("select distinct m.door as door_id from move m join move o on o.door = m.door and o.f = m.t and o.t = m.f"))(lambda v: topology.two_way_doors(v.moves))
query("one_way_doors", O.sql("select door as door_id from move group by door having count(*) = 1"))(lambda v: topology.one_way_doors(v.moves))
query("access_edges", O.sql("select f as src_part, t as dst_part, door as door_id from move"))(lambda v: topology.access_edges(v.moves))
query("door_reach", O.sql(f"""select m.door as door_id, m.t as part_id, coalesce(stair_mm, greatest({', '.join(O.leg('d.', f'c{i}.') for i in range(4))})) as reach_mm
    from (select distinct door, t from move) m join door d on d.door = m.door join part p on p.part_id = m.t,
    lateral (select xmin as x, ymin as y) c0, lateral (select xmin as x, ymax as y) c1, lateral (select xmax as x, ymin as y) c2, lateral (select xmax as x, ymax as y) c3"""))(topology.door_reach)
query("door_legs", O.sql("select part_id, a as a_door, b as b_door, leg as leg_mm from legs"))(topology.door_legs)
query("dv_counts", O.sql("select p.part_id, p.kind, count(distinct door) as dv from part p left join (select door, f as part_id from move union all select door, t from move) m using (part_id) group by 1, 2"))(topology.dv_counts)
_DV = "dv as (select p.part_id, p.kind, count(distinct door) as dv from part p left join (select door, f as part_id from move union all select door, t from move) m using (part_id) group by 1, 2)"
query("crucial_parts", O.sql(f"select part_id, dv from dv where dv > {GAMMA}", _DV))(lambda v: topology.crucial_parts(v, GAMMA))
query("venue_stats", O.sql(f"""select (select count(distinct floor) from part) as floors, (select count(*) from part) as partitions, (select count(distinct door) from door) as doors,
    (select count(*) from part where kind = 'hall')::bigint as hallways, (select count(*) from dv where dv > {GAMMA}) as crucial,
    quantile_disc(dv, 0.25)::bigint as q1, quantile_disc(dv, 0.5)::bigint as q2, quantile_disc(dv, 0.75)::bigint as q3, max(dv) as max_dv from dv""", _DV))(lambda v: metrics.venue_stats(v, GAMMA))
query("dv_histogram", O.sql("select kind, dv, count(*) as n from dv group by 1, 2", _DV))(metrics.dv_histogram)
query("kind_pivot", O.sql("select dv, count(*) filter (kind = 'hall') as hall, count(*) filter (kind = 'lobby') as lobby, count(*) filter (kind = 'room') as room, count(*) filter (kind = 'stair') as stair from dv group by dv", _DV))(surrounding.kind_pivot)
query("irregular_parts", O.sql("select part_id, kind from part where xmin is not null and (kind = 'hall' or greatest(xmax - xmin, ymax - ymin) > 4.0 * least(xmax - xmin, ymax - ymin))"))(lambda v: topology.is_irregular(v.partitions))
query("validate_broken", O.sql("""select 'V1' as "check", min(part_id)::bigint as id from part union all select 'V3', unnest([5000000, 5000001]) union all select 'V4', door from door where kind = 'room_main' and floor = 0"""))(lambda v: surrounding.validate_venue(surrounding.broken_venue(v)))
query("connectivity", O.sql("select count(*) as reachable, count(*) filter (not exists (select 1 from dist r where r.a = d.b and r.b = d.a)) as one_way from dist d where a <> b", pairs=True))(lambda v: surrounding.connectivity(matrix.matrix_dist(v)))
query("kind_maps", O.sql("select floor, count(*)::int as kinds, coalesce(max(n) filter (kind = 'room'), 0) as rooms, (count(*) filter (n >= 5))::int as frequent from (select floor, kind, count(*) as n from part group by 1, 2) group by floor"))(surrounding.kind_maps)
query("dv_ranks", O.sql("select part_id, (rank() over (partition by kind order by dv))::int as place, (dense_rank() over (partition by kind order by dv))::int as dense, (ntile(4) over (partition by kind order by dv, part_id))::int as quarter, floor(percent_rank() over (partition by kind order by dv) * 1000)::bigint as share from dv", _DV))(surrounding.dv_ranks)
query("word_profile", "select string_split(lower(p_name), ' ')[1] as first_word, count(*) as parts, max(length(replace(lower(p_name), ' ', '')))::int as longest, max(regexp_extract(p_brand, '([0-9]+)', 1)::int) as brand_no, min(levenshtein(string_split(lower(p_name), ' ')[1], 'green'))::int as nearest from part group by 1")(surrounding.word_profile)
query("event_calendar", "select (dayofweek(ts) + 1)::int as weekday, hour(ts)::int as hour, count(*) as n from events group by 1, 2")(surrounding.event_calendar)
query("validate_venue", O.sql("select 'V1' as \"check\", 0::bigint as id where false"))(surrounding.validate_venue)


def _recut(v: V.Venue) -> DataFrame:
    """Undivided hallways cut anew into cells of four columns must give the base venue's distances back."""
    whole = V.build_venue(v.spark, v.sf_dir, v.floors, "nocut")
    parts, doors, moves = topology.decompose(whole.partitions, whole.doors, whole.moves, 40_000)
    cut = V.Venue(v.spark, v.sf_dir, v.floors, "recut", parts, doors, moves)
    return topology.door_legs(cut).select("part_id", "a_door", "b_door", "leg_mm")


query("decompose_legs", O.sql("select part_id, a as a_door, b as b_door, leg as leg_mm from legs"))(_recut)

# ---- host lookup --------------------------------------------------------------------------------------------------

_POINTS = O.points()
_HOST = O.sql("select qid, part_id from pt", _POINTS)
query("host_scan", _HOST)(lambda v: host.locate_scan(V.query_points(v), v.partitions).select("qid", "part_id"))
query("host_grid", _HOST)(lambda v: host.locate_grid(V.query_points(v), v.partitions).select("qid", "part_id"))
query("host_rtree", _HOST)(lambda v: rtree.locate_rtree(V.query_points(v), rtree.build_rtree(v)).select("qid", "part_id"))
query("host_all_orders", O.sql("select qid, part_id from pt", O.points(None)))(lambda v: host.locate_grid(V.order_points(v), v.partitions).select("qid", "part_id"))

# ---- models -------------------------------------------------------------------------------------------------------

query("matrix_dist", O.sql("select a as a_door, b as b_door, d as dist_mm from dist", pairs=True))(matrix.matrix_dist)
query("matrix_rank", O.sql("select a as a_door, row_number() over (partition by a order by d, b) as rank, b as b_door from dist", pairs=True))(lambda v: matrix.door_matrix(v).select("a_door", "rank", "b_door"))
_TIGHT = """tight as (select g.a, r.b as b, g.b as x, g.leg from dist d join graph g on g.a = d.a join dist r on r.a = g.b and r.b = d.b where g.leg + r.d = d.d),
hop as (select a, b, min(x) as x from tight t where leg > 0 or x = b or exists (select 1 from tight o where o.a = t.x and o.b = t.b and o.leg > 0) group by a, b)"""
query("first_hops", O.sql("select d.a as a_door, d.b as b_door, hop.x as first_hop from dist d left join hop on hop.a = d.a and hop.b = d.b", _TIGHT, pairs=True))(lambda v: matrix.door_hops(v).select("a_door", "b_door", "first_hop"))
_BACK = """tight as (select g.b as a, r.a as b, g.a as x, g.leg from dist d join graph g on g.b = d.b join dist r on r.b = g.a and r.a = d.a where g.leg + r.d = d.d),
hop as (select a, b, min(x) as x from tight t where leg > 0 or x = b or exists (select 1 from tight o where o.a = t.x and o.b = t.b and o.leg > 0) group by a, b)"""
query("last_hops", O.sql("select d.a as a_door, d.b as b_door, hop.x as last_hop from dist d left join hop on hop.a = d.b and hop.b = d.a", _BACK, pairs=True))(lambda v: matrix.last_hops(matrix.matrix_dist(v), topology.graph_legs(v)))
query("kernel_relax_all", O.sql("select a as a_door, b as b_door, d as dist_mm from dist", pairs=True))(lambda v: relax.all_pairs(topology.graph_legs(v), v.doors.select("door_id"), engine="relax"))
query("kernel_hops", O.sql("select d.a as a_door, d.b as b_door, d.d as dist_mm, hop.x as first_hop from dist d left join hop on hop.a = d.a and hop.b = d.b", _TIGHT, pairs=True))(lambda v: relax.local_hops(v.doors.select("door_id"), topology.graph_legs(v)).select("a_door", "b_door", "dist_mm", "first_hop"))
query("first_hops_joined", O.sql("select d.a as a_door, d.b as b_door, hop.x as first_hop from dist d left join hop on hop.a = d.a and hop.b = d.b", _TIGHT, pairs=True))(lambda v: matrix.joined_hops(v).select("a_door", "b_door", "first_hop"))
query("kernel_square", O.sql("select a as a_door, b as b_door, d as dist_mm from dist", pairs=True))(lambda v: relax.all_pairs(topology.graph_legs(v), v.doors.select("door_id"), engine="square"))
query("skeleton", O.sql("select a as a_stair, b as b_stair, d as dist_mm from dist where a in (select door from door where kind in ('stair_low', 'stair_high')) and b in (select door from door where kind in ('stair_low', 'stair_high'))", pairs=True))(rtree.skeleton)
query("rt_links", O.sql("select f as part_id, count(*) as n_links, string_agg(door || ':' || t, ',' order by door, t) as links from move group by f"))(
    lambda v: rtree.rt_links(v).select("part_id", F.size("links").cast("long").alias("n_links"), F.array_join(F.transform("links", lambda x: F.concat(x["door_id"].cast("string"), F.lit(":"), x["to_part"].cast("string"))), ",").alias("links"))
)
query("unreachable_doors", O.sql("select door as door_id from door where door not in (select a from dist where a <> b)", pairs=True))(lambda v: surrounding.unreachable_doors(v, matrix.matrix_dist(v)))


def _leaf_check(v: V.Venue) -> DataFrame:
    tree = border.build_border_tree(v)
    crucial = topology.crucial_parts(v, GAMMA).select("part_id", F.lit(1).alias("crucial"))
    parts = tree.members.join(crucial, "part_id", "left").groupBy("leaf").agg(F.count("*").alias("n_parts"), F.count("crucial").alias("n_crucial"))
    rim = tree.access.groupBy(F.col("node_id").alias("leaf")).agg(F.count("*").alias("n_access"))
    return parts.join(rim, "leaf", "left").select(F.col("leaf").alias("leaf_id"), "n_parts", "n_crucial", F.coalesce("n_access", F.lit(0)).alias("n_access"))


query("bt_leaf_check")(_leaf_check)
query("bt_nodes")(lambda v: border.build_border_tree(v).nodes.select("node_id", "level", "parent_id"))
query("bt_leaf_cells", None)(lambda v: border.build_border_tree(v).leaf_out)
query("bt_inner_cells", None)(lambda v: border.build_border_tree(v).inner)
query("btd_cells", None)(lambda v: border.build_border_tree(v).deep_out)
# Cells hold global distances: rows that differ from the full matrix, of which there must be none.
query("bt_cells_exact", O.sql("select 0::bigint as wrong"))(
    lambda v: border.build_border_tree(v).leaf_pairs.select("a_door", "b_door", F.col("dist_mm").alias("d"))
    .union(border.build_border_tree(v).inner.select("a_door", "b_door", "dist_mm"))
    .union(border.build_border_tree(v).deep_out.select("door_id", "access_door", "dist_mm"))
    .union(border.build_border_tree(v).deep_in.select("access_door", "door_id", "dist_mm"))
    .join(matrix.matrix_dist(v), ["a_door", "b_door"], "left").agg(F.coalesce(F.sum((~F.col("d").eqNullSafe(F.col("dist_mm"))).cast("long")), F.lit(0)).alias("wrong"))
)

# Stored hops of all cells against the first doors of shortest paths: rows that differ, of which there must be none.
query("bt_hops", O.sql("select a as a_door, b as b_door, x as first_hop from hop where a in (select door from door) and b in (select door from door)", _TIGHT, pairs=True))(lambda v: _cell_hops(v))


def _cell_hops(v: V.Venue) -> DataFrame:
    """Hops as the cells store them, and from the kernel for pairs that no cell holds."""
    tree = border.build_border_tree(v)
    cells = tree.deep_out.select(F.col("door_id").alias("a_door"), F.col("access_door").alias("b_door"), "first_hop")
    cells = cells.union(tree.deep_in.select(F.col("access_door").alias("a_door"), F.col("door_id").alias("b_door"), "first_hop"))
    cells = cells.union(tree.leaf_pairs.select("a_door", "b_door", "first_hop")).union(tree.inner.select("a_door", "b_door", "first_hop")).where("first_hop is not null").distinct()
    rest = matrix.door_hops(v).where("first_hop is not null").select("a_door", "b_door", "first_hop").join(cells, ["a_door", "b_door"], "left_anti")
    return cells.union(rest)


# ---- queries by method --------------------------------------------------------------------------------------------

_OD = O.object_distances()
_RQ = O.sql(f"select qid, object_id, dist_mm from od where dist_mm <= {R_MM}", _POINTS, O.OBJECTS, _OD, pairs=True)
_KNN = O.sql(f"select qid, row_number() over (partition by qid order by dist_mm, object_id) as rank, object_id, dist_mm from od qualify rank <= {K}", _POINTS, O.OBJECTS, _OD, pairs=True)
_SDQ = O.sql("select pr.qid, dist_mm from pr left join sdq using (qid)", _POINTS, O.PAIR_SIDES, O.pair_distances(), pairs=True)
_SPDQ = O.sql("select pr.qid, c.d as dist_mm, len(c.p)::bigint as n_doors, array_to_string(c.p, '>') as door_path from pr left join best using (qid)", _POINTS, O.PAIR_SIDES, O.pair_paths())
_AG_NVD = f"""ex as (select distinct src.qid, d.door, {O.leg('src.', 'd.')} as leg from src join move m on m.f = src.part_id join door d on d.door = m.door),
ahead as (select qid, b as door, min(leg + d) as d from ex join dist on a = ex.door group by 1, 2)"""
_NVD = {
    "ag": O.sql("select pr.qid, count(*) as nvd from pr join sdq using (qid) join ahead on ahead.qid = pr.qid and d <= dist_mm group by 1", _POINTS, O.PAIR_SIDES, O.pair_distances(), _AG_NVD, pairs=True),
    "dm": O.sql("select src.qid, (select count(*) from exits e where e.part_id = src.part_id) + (select count(*) from entries n where n.part_id = dst.part_id) as nvd from src join dst using (qid)", _POINTS, O.PAIR_SIDES),
}
_NVD["lr"] = _NVD["ag"]


def _visited(method: str):
    def make(v: V.Venue) -> DataFrame:
        source, target = route.sides(v, V.query_pairs(v))
        best = route.distance_query("dm", v, V.query_pairs(v)).where("dist_mm is not null")
        return route.visited_doors(method, v, source, target, best).select("qid", "nvd")

    return make


for _m in METHODS:
    query(f"rq_{_m}", _RQ)(lambda v, m=_m: ranges.range_query(m, v, V.query_points(v), V.objects(v), R_MM))
    query(f"knn_{_m}", _KNN)(lambda v, m=_m: knn.knn_query(m, v, V.query_points(v), V.objects(v), K))
    query(f"sdq_{_m}", _SDQ)(lambda v, m=_m: route.distance_query(m, v, V.query_pairs(v)))
    query(f"spdq_{_m}", _SPDQ)(lambda v, m=_m: route.route_query(m, v, V.query_pairs(v), False).select("qid", "dist_mm", F.size("door_path").cast("long").alias("n_doors"), _text("door_path").alias("door_path")))
    query(f"nvd_{_m}", _NVD.get(_m))(_visited(_m))
query("rq_brute", _RQ)(lambda v: ranges.brute_range(v, V.query_points(v), V.objects(v), R_MM))
query("knn_brute", _KNN)(lambda v: knn.brute_knn(v, V.query_points(v), V.objects(v), K))
query("rq_ids", O.sql(f"select qid, object_id from od where dist_mm <= {R_MM}", _POINTS, O.OBJECTS, _OD, pairs=True))(lambda v: ranges.range_ids("ag", v, V.query_points(v), V.objects(v), R_MM))
_EUCLID = f"select qid, object_id, {O.leg('pt.', 'obj.')} as dist_mm from pt join obj using (floor)"
query("euclid_range", O.sql(f"select * from ({_EUCLID}) where dist_mm <= {R_MM}", _POINTS, O.OBJECTS))(lambda v: ranges.euclid_range(V.query_points(v), V.objects(v), R_MM))
query("euclid_knn", O.sql(f"select qid, row_number() over (partition by qid order by dist_mm, object_id) as rank, object_id, dist_mm from ({_EUCLID}) qualify rank <= {K}", _POINTS, O.OBJECTS))(lambda v: knn.euclid_knn(V.query_points(v), V.objects(v), K))
query("rq_disagreement", "select 0::bigint as rows_different")(
    lambda v: v.spark.range(1).select(F.lit(sum(metrics.disagreement(ranges.range_query(m, v, V.query_points(v), V.objects(v), R_MM), ranges.brute_range(v, V.query_points(v), V.objects(v), R_MM)) for m in METHODS)).cast("long").alias("rows_different"))
)

# ---- measures -----------------------------------------------------------------------------------------------------

query("model_size", O.sql("""select 'access_graph' as method, 'moves' as component, count(*) as n_rows from move union all select 'access_graph', 'door_legs', count(*) from legs
    union all select 'access_graph', 'door_reach', count(*) from (select distinct door, t from move where t <> 0)
    union all select 'door_matrix', 'matrix', count(*) from dist""", pairs=True))(
    lambda v: metrics.model_size(v, ("ag", "dm")).where("method = 'access_graph' or component = 'matrix'").select("method", "component", "n_rows")
)
query("model_size_all")(lambda v: metrics.model_size(v))
query("method_features", """select * from (values ('access_graph', 'no', 'graph and maps', 'scan', 'best-first', 'SPQ, SDQ'), ('door_matrix', 'yes', 'matrix', 'scan', 'loop', 'RQ, KNN'),
    ('layered_rtree', 'no', 'tree and links', 'R-tree', 'best-first', 'RQ, KNN'), ('border_tree', 'yes', 'tree and matrices', 'scan', 'common ancestor', 'RQ, KNN, SPQ, SDQ'),
    ('border_tree_deep', 'yes', 'tree and matrices', 'scan', 'common ancestor', 'RQ, KNN, SPQ, SDQ')) t(method, precomputation, structure, initialisation, expansion, native)""")(lambda v: metrics.method_features(v.spark))
query("recommend", O.sql(f"""select unnest(['range', 'knn', 'route', 'changing_doors']) as task, unnest([case when small then 'door_matrix' when crucial then 'border_tree_deep' else 'access_graph' end,
    case when small then 'door_matrix' when crucial then 'border_tree_deep' else 'access_graph' end, case when small then 'door_matrix' else 'border_tree_deep' end, 'access_graph']) as method
    from (select (select count(*) from door) <= {metrics.SMALL_DOORS} as small, count(*) filter (dv > {GAMMA}) / count(*) > {metrics.CRUCIAL_SHARE} as crucial from dv)""", _DV))(metrics.recommend)


def _prune(v: V.Venue) -> DataFrame:
    placed = ranges.placed_points(v, V.query_points(v))
    return metrics.prune_stats(graph_labels(v, placed, R_MM), v.doors.count())


query("prune_stats", O.sql(f"""select qid, count(*) as touched, cast(floor(((select count(*) from door) - count(*)) * 10000 / (select count(*) from door)) as bigint) as share_pruned_bp
    from (select qid, door, min(d) as d from (select distinct pt.qid, b as door, {O.leg('pt.', 'd.')} + dist.d as d from pt join move m on m.f = pt.part_id join door d on d.door = m.door join dist on a = d.door) group by 1, 2) where d <= {R_MM} group by qid""", _POINTS, pairs=True))(_prune)


def _predicted(v: V.Venue) -> DataFrame:
    stats = metrics.tree_stats(v)
    rows = metrics.cost_model(o_total=V.objects(v).count(), w=9.0, **stats)
    return v.spark.createDataFrame(rows, "method string, measure string, units double")


query("cost_model")(_predicted)

# ---- variants -----------------------------------------------------------------------------------------------------

for _variant in VARIANTS:
    _sql_variant = "base" if _variant == "merged" else _variant
    query(f"variant_{_variant}_sdq", O.sql("select pr.qid, dist_mm from pr left join sdq using (qid)", _POINTS, O.PAIR_SIDES, O.pair_distances(), variant=_sql_variant, pairs=True))(
        lambda v, name=_variant: route.distance_query("ag", V.build_venue(v.spark, v.sf_dir, 5, name), V.query_pairs(v))
    )
for _n in (3, 7, 9):
    query(f"tower{_n}_matrix", O.sql("select a as a_door, b as b_door, d as dist_mm from dist", floors=_n, pairs=True))(lambda v, n=_n: matrix.matrix_dist(V.build_venue(v.spark, v.sf_dir, n)))
query("merged_matrix", O.sql("select a as a_door, b as b_door, d as dist_mm from dist where a not in (select door from door where kind in ('segment', 'lobby_hall', 'lobby_lobby')) and b not in (select door from door where kind in ('segment', 'lobby_hall', 'lobby_lobby'))", pairs=True))(lambda v: matrix.matrix_dist(V.build_venue(v.spark, v.sf_dir, 5, "merged")))

# ---- extensions ---------------------------------------------------------------------------------------------------

_OPEN = f"open_door as (select door from door where door not in (select door from hours) union select door from hours where {AT_S} >= open_s and {AT_S} < close_s)"
query("doors_open_at", O.sql("select door as door_id from open_door", O.OPEN_HOURS, _OPEN))(lambda v: extend.doors_open_at(v, AT_S))


def _open_sql() -> str:
    text = O.venue().replace("move as (select door::bigint", "move0 as (select door::bigint", 1)
    text = text.replace("legs as (select m.t", f"{O.OPEN_HOURS.strip()},\n{_OPEN},\nmove as (select * from move0 where door in (select door from open_door)),\nlegs as (select m.t", 1)
    return "with recursive " + ",".join([text, O.PAIRS, _POINTS, O.PAIR_SIDES, O.pair_distances()]) + "\nselect pr.qid, dist_mm from pr left join sdq using (qid)"


query("route_open_at", _open_sql())(lambda v: extend.route_open_at("ag", v, V.query_pairs(v), AT_S))
_TIMED = f"""tlab(qid, door, d) using key (qid, door) as (
    select src.qid, e.door, {O.leg('src.', 'da.')} from src join exits e on e.part_id = src.part_id join door da on da.door = e.door where free(e.door, {O.leg('src.', 'da.')})
    union
    select r.qid, g.b, min(r.d + g.leg) from tlab r join graph g on g.a = r.door left join recurring.tlab k on k.qid = r.qid and k.door = g.b
    where free(g.b, r.d + g.leg) and (k.d is null or r.d + g.leg < k.d) group by r.qid, g.b),
timed as (select qid, min(d) as dist_mm from (
    select tlab.qid, tlab.d + {O.leg('d.', 'dst.')} as d from tlab join entries n on n.door = tlab.door join dst on dst.qid = tlab.qid and dst.part_id = n.part_id join door d on d.door = tlab.door
    union all select src.qid, {O.leg('src.', 'dst.')} from src join dst using (qid, part_id)) group by qid)"""


def _timed_sql() -> str:
    """Door hours hold at the second of arrival: 1.2 m/s from the departure on."""
    text = _TIMED
    for door, d in (("e.door", O.leg("src.", "da.")), ("g.b", "r.d + g.leg")):
        second = f"(({AT_S} + ({d}) // 1200) % 86400)"
        text = text.replace(f"free({door}, {d})", f"({door} not in (select door from hours) or exists (select 1 from hours h where h.door = {door} and {second} >= h.open_s and {second} < h.close_s))")
    return O.sql("select pr.qid, dist_mm from pr left join timed using (qid)", _POINTS, O.PAIR_SIDES, O.OPEN_HOURS, text)


query("route_timed", _timed_sql())(lambda v: extend.route_timed(v, V.query_pairs(v), AT_S))
_POS = """rk as (select base + 10000000 + s as part_id, floor, c * 10000 as xmin, hy + case side when 0 then 12000 else 0 end as ymin, row_number() over (order by s) - 1 as n from room),
pos as (select user_id, ts, event_id::bigint as event_id, rk.floor, xmin + 1 + (7919 * event_id) % 9998 as x, ymin + 1 + (104729 * event_id) % 7998 as y, part_id from events join rk on rk.n = (31 * event_id + user_id) % (select count(*) from rk))"""
query("positions_as_of", O.sql(f"select user_id, ts, part_id from pos where ts <= timestamp '{AT_TS}' qualify row_number() over (partition by user_id order by ts desc, event_id desc) = 1", _POS))(lambda v: extend.positions_as_of(extend.positions(v), AT_TS))
query("trajectory_steps", O.sql(f"select user_id, event_id, {O.leg('s.', 's.p')} as step_mm from (select *, lag(floor) over w as pfloor, lag(x) over w as px, lag(y) over w as py from pos window w as (partition by user_id order by ts, event_id)) s where pfloor = floor", _POS))(lambda v: surrounding.trajectory_steps(extend.positions(v)))
query("users_per_room", O.sql("select part_id, count(distinct user_id) as users from pos group by 1", _POS))(lambda v: surrounding.users_per_room(extend.positions(v)))
query("approx_users_per_room", O.sql("select part_id, count(distinct user_id) as users, 1::int as near from pos group by 1", _POS))(lambda v: surrounding.approx_users_per_room(extend.positions(v)))
_TS = "timestamp"
query("occupancy_tumbling", O.sql("select date_trunc('hour', ts) as start_ts, part_id, count(*) as n from pos group by 1, 2", _POS))(lambda v: occupancy.tumbling(extend.positions(v).withColumn("ts", F.col("ts").cast(_TS))).withColumn("start_ts", F.col("start_ts").cast("timestamp_ntz")))
query("occupancy_sliding", O.sql("select start_ts, part_id, count(*) as n from (select part_id, time_bucket(interval 30 minutes, ts) - to_minutes(30 * k) as start_ts from pos, range(4) r(k)) group by 1, 2", _POS))(lambda v: occupancy.sliding(extend.positions(v).withColumn("ts", F.col("ts").cast(_TS))).withColumn("start_ts", F.col("start_ts").cast("timestamp_ntz")))
query("occupancy_session", O.sql("""select user_id, min(ts) as start_ts, max(ts) + interval 30 minutes as end_ts, count(*) as n from (
    select *, sum(fresh) over (partition by user_id order by ts, event_id) as s from (select *, case when ts - lag(ts) over (partition by user_id order by ts, event_id) < interval 30 minutes then 0 else 1 end as fresh from pos)) group by user_id, s""", _POS))(
    lambda v: occupancy.visits(extend.positions(v).withColumn("ts", F.col("ts").cast(_TS))).select("user_id", F.col("start_ts").cast("timestamp_ntz").alias("start_ts"), F.col("end_ts").cast("timestamp_ntz").alias("end_ts"), "n")
)


def _stream_positions(v: V.Venue) -> DataFrame:
    return occupancy.place_events(v, occupancy.event_stream(v.spark, v.sf_dir))


def _ntz(frame: DataFrame) -> DataFrame:
    return frame.withColumn("start_ts", F.col("start_ts").cast("timestamp_ntz"))


query("stream_occupancy", O.sql("select date_trunc('hour', ts) as start_ts, part_id, count(*) as n from pos group by 1, 2", _POS))(lambda v: _ntz(occupancy.run_once(occupancy.tumbling(_stream_positions(v).withWatermark("ts", occupancy.LATE)), "complete")))
query("stream_dedup", "select event_id::bigint as event_id from events")(lambda v: occupancy.run_once(occupancy.deduplicated(_stream_positions(v)).select("event_id")))


def _monitor(v: V.Venue) -> DataFrame:
    area = occupancy.within_range(v, V.query_points(v).where("qid = 0"), R_MM)
    return occupancy.run_once(occupancy.monitored(_stream_positions(v), area, R_MM).select("event_id", F.col("inside").cast("int").alias("inside")))


query("stream_range_monitor", O.sql(f"""select event_id, max(case when d <= {R_MM} then 1 else 0 end) as inside from (
    select pos.event_id, r.d + {O.leg('d.', 'pos.')} as d from pos join move m on m.t = pos.part_id join reach r on r.door = m.door and r.qid = 0 join door d on d.door = m.door
    union all select pos.event_id, {O.leg('pt.', 'pos.')} from pos join pt on pt.part_id = pos.part_id and pt.qid = 0
    union all select event_id, 1000000000 from pos) group by 1""", _POINTS, O.OBJECTS, _OD, _POS, pairs=True))(_monitor)


def _alerts(v: V.Venue) -> DataFrame:
    area = occupancy.within_range(v, V.query_points(v).where("qid = 0"), R_MM)
    return occupancy.run_once(occupancy.alerts(occupancy.monitored(_stream_positions(v), area, R_MM)))


_MON = f"""mon as (select event_id, max(case when d <= {R_MM} then 1 else 0 end) as inside from (
    select pos.event_id, r.d + {O.leg('d.', 'pos.')} as d from pos join move m on m.t = pos.part_id join reach r on r.door = m.door and r.qid = 0 join door d on d.door = m.door
    union all select pos.event_id, {O.leg('pt.', 'pos.')} from pos join pt on pt.part_id = pos.part_id and pt.qid = 0
    union all select event_id, 1000000000 from pos) group by 1)"""
# Rows at the last time of all stay behind the watermark.
query("stream_alerts", O.sql("""select user_id::bigint as user_id, ts, case when inside = 1 then 'enter' else 'leave' end as event from (
    select user_id, ts, inside, lag(inside, 1, 0) over (partition by user_id order by ts, event_id) as was from pos join mon using (event_id))
    where inside <> was and ts < (select max(ts) from pos)""", _POINTS, O.OBJECTS, _OD, _POS, _MON, pairs=True))(lambda v: _alerts(v).withColumn("ts", F.col("ts").cast("timestamp_ntz")))
query("stream_bucket_upserts", O.sql("select user_id, ts, part_id from pos qualify row_number() over (partition by user_id order by ts desc, event_id desc) = 1", _POS))(
    lambda v: occupancy.upserts(_stream_positions(v).select("user_id", "ts", "event_id", "part_id"), ["user_id"], occupancy.latest).select("user_id", F.col("ts").cast("timestamp_ntz").alias("ts"), "part_id")
)
query("stream_update_mode", O.sql("select date_trunc('hour', ts) as start_ts, part_id, count(*) as n from pos group by 1, 2", _POS))(
    lambda v: _ntz(occupancy.upserts(occupancy.tumbling(_stream_positions(v).withWatermark("ts", occupancy.LATE)), ["start_ts", "part_id"], occupancy.greatest_count, "update"))
)
query("events_last_hour", O.sql("select event_id, count(*) over (partition by user_id order by epoch(ts)::bigint range between 3600 preceding and current row) as n from pos", _POS))(lambda v: surrounding.events_last_hour(extend.positions(v)))
query("stream_meetings", O.sql("select a.part_id, a.user_id as a_user, b.user_id as b_user, a.event_id * 0 + count(*) as n from pos a join pos b on a.part_id = b.part_id and a.user_id < b.user_id and b.ts between a.ts - interval 10 minutes and a.ts + interval 10 minutes group by all", _POS).replace("a.event_id * 0 + count(*)", "count(*)"))(
    lambda v: occupancy.run_once(occupancy.meetings(_stream_positions(v), _stream_positions(v))).groupBy("part_id", "a_user", "b_user").agg(F.count("*").alias("n"))
)
_UNC = """unc as (select object_id, floor, x - h as x_lo, x + h as x_hi, y - h as y_lo, y + h as y_hi from (select *, 500 + 500 * (object_id % 6) as h from obj)),
clip as (select object_id, part_id, greatest(x_lo, xmin) as cx0, greatest(y_lo, ymin) as cy0, least(x_hi, xmax) as cx1, least(y_hi, ymax) as cy1 from unc join part using (floor) where x_lo < xmax and x_hi > xmin and y_lo < ymax and y_hi > ymin),
start as (select qid, part_id, x, y, 0 as d from pt union all select r.qid, m.t, d.x, d.y, r.d from reach r join move m on m.door = r.door and m.t <> 0 join door d on d.door = r.door),
seen as (select qid, object_id, clip.part_id, min(d + cast(floor(sqrt(cast(gx * gx + gy * gy as double))) as bigint)) as near,
    min(d + cast(ceil(sqrt(cast(fx * fx + fy * fy as double))) as bigint)) as far
    from start join clip using (part_id), lateral (select greatest(cx0 - x, x - cx1, 0) as gx, greatest(cy0 - y, y - cy1, 0) as gy, greatest(abs(cx0 - x), abs(cx1 - x)) as fx, greatest(abs(cy0 - y), abs(cy1 - y)) as fy) group by all)"""
query("uncertain_range", O.sql(f"""select qid, object_id, cast(max(far) <= {R_MM} and count(*) = (select count(*) from clip c where c.object_id = seen.object_id) as int) as certain
    from seen group by 1, 2 having min(near) <= {R_MM}""", _POINTS, O.OBJECTS, _OD, _UNC, pairs=True))(lambda v: extend.uncertain_range(v, V.query_points(v), extend.uncertain_objects(V.objects(v)), R_MM))
_WORDS = """words as (select c_custkey::bigint as object_id, lower(c_mktsegment) as word from customer
    union select o_custkey::bigint, unnest(string_split(lower(p_name), ' ') || [lower(p_brand)]) from orders join lineitem on l_orderkey = o_orderkey join part_t on p_partkey = l_partkey),
chosen as (select object_id from words where word in {w} group by 1 having count(distinct word) >= {n})"""


def _word_sql(select: str, need: int) -> str:
    # The venue's CTE `part` would hide the table of that name, so it is read before under another name.
    words = _WORDS.replace("{w}", str(WORDS)).replace("{n}", str(need))
    body = O.sql(select, _POINTS, O.OBJECTS, _OD, words, pairs=True)
    return body.replace("with recursive ", "with recursive part_t as materialized (select p_partkey, p_name, p_brand from part), ", 1).replace("\npart as (", "\npart_v as (", 1).replace("join part p", "join part_v p")


query("keyword_range", _word_sql(f"select qid, object_id, dist_mm from od where dist_mm <= {R_MM} and object_id in (select object_id from chosen)", 1))(lambda v: extend.keyword_range("ag", v, V.query_points(v), V.objects(v), extend.object_words(v, WORDS), list(WORDS), R_MM, False))
query("keyword_knn", _word_sql(f"select qid, row_number() over (partition by qid order by dist_mm, object_id) as rank, object_id, dist_mm from od where object_id in (select object_id from chosen) qualify rank <= {K}", 2))(lambda v: extend.keyword_knn("btd", v, V.query_points(v), V.objects(v), extend.object_words(v, WORDS), list(WORDS), K))
_COVER = f"""kw as (select * from words where word in {WORDS}),
cov as (select part_id, bit_or(case when word = '{WORDS[0]}' then 1 else 2 end)::bigint as mask from kw join obj using (object_id) group by part_id),
lab(qid, door, mask, l) using key (qid, door, mask) as (
    select src.qid, e.door, coalesce(c.mask, 0)::bigint, {{'d': {O.leg('src.', 'da.')}, 'p': [e.door]}} from src join exits e on e.part_id = src.part_id join door da on da.door = e.door left join cov c on c.part_id = src.part_id
    union
    select qid, door, mask, min(l) from (
        select r.qid, g.b as door, (r.mask | coalesce(c.mask, 0))::bigint as mask, {{'d': r.l.d + g.leg, 'p': list_append(r.l.p, g.b)}} as l from lab r join legs g on g.a = r.door left join cov c on c.part_id = g.part_id) n
    left join (select qid as kq, door as kd, mask as km, l as kl from recurring.lab) k on kq = qid and kd = door and km = mask where kl is null or l < kl group by qid, door, mask),
whole as (select lab.qid, lab.l.d + {O.leg('d.', 'dst.')} as total_mm, lab.l.p as p from lab join entries n on n.door = lab.door join dst on dst.qid = lab.qid and dst.part_id = n.part_id join door d on d.door = lab.door
        left join cov c on c.part_id = dst.part_id where (lab.mask | coalesce(c.mask, 0)) = 3
    union select src.qid, {O.leg('src.', 'dst.')}, cast([] as bigint[]) from src join dst using (qid, part_id) join cov using (part_id) where cov.mask = 3)"""


def _route_sql() -> str:
    words = _WORDS.replace("{w}", str(WORDS)).replace("{n}", "1")
    body = O.sql("select qid, rank, total_mm, array_to_string(p, '>') as door_path from (select *, row_number() over (partition by qid order by total_mm, p) as rank from whole) where rank <= 2", _POINTS, O.OBJECTS, O.PAIR_SIDES, words, _COVER)
    return body.replace("with recursive ", "with recursive part_t as materialized (select p_partkey, p_name, p_brand from part), ", 1).replace("\npart as (", "\npart_v as (", 1).replace("join part p", "join part_v p")


query("keyword_route", _route_sql())(lambda v: extend.keyword_route(v, V.query_pairs(v), V.objects(v), extend.object_words(v, WORDS), list(WORDS), 2).withColumn("door_path", _text("door_path")))
query("keyword_knn_bt", _word_sql(f"select qid, row_number() over (partition by qid order by dist_mm, object_id) as rank, object_id, dist_mm from od where object_id in (select object_id from chosen) qualify rank <= {K}", 2))(lambda v: extend.keyword_knn("bt", v, V.query_points(v), V.objects(v), extend.object_words(v, WORDS), list(WORDS), K))
query("node_words")(lambda v: extend.node_words(v, V.objects(v), extend.object_words(v)))

# ---- surrounding operators ----------------------------------------------------------------------------------------

query("bucket_counts", O.sql("select part.part_id, count(object_id) as n from part left join obj using (part_id) group by 1", O.OBJECTS))(lambda v: surrounding.bucket_counts(v, V.objects(v)))
query("rooms_with_objects", O.sql("select part_id from part where kind = 'room' and part_id in (select part_id from obj)", O.OBJECTS))(lambda v: surrounding.rooms_with_objects(v, V.objects(v)))
query("rooms_without_objects", O.sql("select part_id from part where kind = 'room' and part_id not in (select part_id from obj)", O.OBJECTS))(lambda v: surrounding.rooms_without_objects(v, V.objects(v)))
query("space_rollup", O.sql("select part.floor, kind, count(*) as n from obj join part using (part_id) group by rollup (part.floor, kind)", O.OBJECTS))(lambda v: surrounding.space_rollup(v, V.objects(v)))
query("top_objects_per_room", O.sql(f"select part_id, row_number() over (partition by part_id order by leg_mm, object_id) as rank, object_id, leg_mm from (select obj.part_id, object_id, {O.leg('obj.', 'd.')} as leg_mm from obj join door d on d.door = obj.part_id and d.kind = 'room_main') qualify rank <= 3", O.OBJECTS))(lambda v: surrounding.top_objects_per_room(v, V.objects(v)))
query("requested_k", "select event_id::bigint as event_id, cast(props->>'$.k' as int) as k from events where props->>'$.k' is not null")(surrounding.requested_k)


def _s2t(v: V.Venue) -> DataFrame:
    return workload.s2t_pairs(v).select("s2t_mm", "qid", "dist_mm")


query("s2t_pairs", O.sql("select s2t_mm, qid, dist_mm from sdq, (select unnest([30000, 60000, 90000, 120000, 150000])::bigint as s2t_mm) qualify row_number() over (partition by s2t_mm order by abs(dist_mm - s2t_mm), qid) <= 10", _POINTS, O.PAIR_SIDES, O.pair_distances(), pairs=True))(_s2t)


# ---- SQL surface and twins ----------------------------------------------------------------------------------------


def _sql(text: str):
    def make(v: V.Venue) -> DataFrame:
        sqlapi.register(v.spark, v)
        return v.spark.sql(text)

    return make


query("sql_range", _RQ)(_sql(f"select * from indoor_range({R_MM})"))
query("sql_knn", _KNN)(_sql(f"select * from indoor_knn({K})"))
query("sql_route", O.sql("select qid, (i - 1)::int as step, c.p[i] as door from best, range(1, 100) r(i) where i <= len(c.p)", _POINTS, O.PAIR_SIDES, O.pair_paths()))(_sql("select p.qid, r.step, r.door from indoor_paths p, lateral indoor_unroll(p.path) r"))
query("sql_one_route", O.sql("select (i - 1)::int as step, c.p[i] as door from best, range(1, 100) r(i) where i <= len(c.p) and qid = (select min(qid) from pr)", _POINTS, O.PAIR_SIDES, O.pair_paths()))(lambda v: _sql(f"select * from indoor_route({V.query_pairs(v).agg(F.min('qid')).first()[0]})")(v))
query("sql_nearest_doors", O.sql("select qid, door as door_id, leg_mm from (select qid, d.door, min(" + O.leg("pt.", "d.") + ") as leg_mm from pt join move m on m.f = pt.part_id join door d on d.door = m.door group by 1, 2) qualify row_number() over (partition by qid order by leg_mm, door) <= 2", _POINTS))(
    lambda v: _sql("""select p.qid, n.door_id, n.leg_mm from (select q.qid, q.x_mm, q.y_mm, a.part_id from indoor_points q join indoor_partitions a on a.floor = q.floor and q.x_mm >= a.xmin and q.x_mm < a.xmax and q.y_mm >= a.ymin and q.y_mm < a.ymax) p,
    lateral (select d.door_id, indoor_leg(p.x_mm, p.y_mm, d.x_mm, d.y_mm) as leg_mm from indoor_doors d join indoor_moves m on m.door_id = d.door_id where m.from_part = p.part_id group by 1, 2 order by leg_mm, door_id limit 2) n""")(v)
)


def _unrolled(v: V.Venue) -> DataFrame:
    sqlapi.register(v.spark, v)
    return v.spark.sql("select qid, step, door from indoor_paths, lateral indoor_unroll(path)")


query("path_unroll", O.sql("select qid, (i - 1)::int as step, c.p[i] as door from best, range(1, 100) r(i) where i <= len(c.p)", _POINTS, O.PAIR_SIDES, O.pair_paths()))(_unrolled)


def _legs_py(v: V.Venue) -> DataFrame:
    points = V.query_points(v).select("qid", "floor", "x_mm", "y_mm")
    doors = v.doors.select("floor", "door_id", F.col("x_mm").alias("dx"), F.col("y_mm").alias("dy"))
    return points.join(doors, "floor").select("qid", "door_id", leg_mm_py("x_mm", "y_mm", "dx", "dy").alias("leg_mm"))


def _least_sums(v: V.Venue) -> DataFrame:
    source, target = route.sides(v, V.query_pairs(v))
    ends = entry_legs(v, target).select("qid", F.col("door").alias("b_door"), F.col("dist").alias("rest"))
    ways = exit_legs(v, source).join(matrix.matrix_dist(v), F.col("door") == F.col("a_door")).join(ends, ["qid", "b_door"])
    return ways.groupBy("qid").agg(least_sum(F.col("dist") + F.col("dist_mm"), F.col("rest")).alias("dist_mm"))


query("least_sum_twin", O.sql(f"""select src.qid, min({O.leg('src.', 'da.')} + dist.d + {O.leg('db.', 'dst.')}) as dist_mm from src join exits e on e.part_id = src.part_id join door da on da.door = e.door
    join dist on dist.a = e.door join entries n on n.door = dist.b join dst on dst.qid = src.qid and dst.part_id = n.part_id join door db on db.door = n.door group by 1""", _POINTS, O.PAIR_SIDES, pairs=True))(_least_sums)
query("leg_twin", O.sql("select qid, door as door_id, " + O.leg("pt.", "d.") + " as leg_mm from pt join door d using (floor)", _POINTS))(_legs_py)
query("cumulative_objects", O.sql("""select d.b as b_door, row_number() over (order by d.d, d.b) as rank, (sum(coalesce(n, 0)) over (order by d.d, d.b))::bigint as seen from dist d
    left join (select m.door, sum(k) as n from (select distinct door, t from move) m join (select part_id, count(*) as k from obj group by 1) o on o.part_id = m.t group by 1) c on c.door = d.b where d.a = 10000000""", O.OBJECTS, pairs=True))(lambda v: surrounding.cumulative_objects(matrix.door_matrix(v, v.doors.where("door_id = 10000000")), v, V.objects(v), 10_000_000))
query("generated_pairs", O.sql("""select qid, s_floor, s_x, s_y, t_floor, t_x, t_y from (
    select n.qid, pt.floor as s_floor, pt.x as s_x, pt.y as s_y, obj.floor as t_floor, obj.x as t_x, obj.y as t_y, obj.object_id, od.dist_mm
    from (select * from reach qualify row_number() over (partition by qid order by abs(d - 90000), door) = 1) n join pt using (qid)
    join dist e on e.a = n.door join move m on m.door = e.b and m.t <> 0 join obj on obj.part_id = m.t join od on od.qid = n.qid and od.object_id = obj.object_id
    qualify e.d = min(e.d) over (partition by n.qid))
    qualify row_number() over (partition by qid order by abs(dist_mm - 90000), object_id) = 1""", _POINTS, O.OBJECTS, _OD, pairs=True))(lambda v: workload.generated_pairs(v, 90_000))
query("ranked_scan", O.sql(f"select qid, door, d as dist from reach where d <= {R_MM}", _POINTS, O.OBJECTS, _OD, pairs=True))(lambda v: matrix_labels(v, ranges.placed_points(v, V.query_points(v)), R_MM))
for _how in ("scan", "rtree"):
    query(f"rq_init_{_how}", _RQ)(lambda v, how=_how: ranges.range_query("ag", v, V.query_points(v), V.objects(v), R_MM, how))

# Searches of every order whose id is divisible by 20.
_MANY = O.points(where="o_orderkey % 20 = 0")
_NEAR = 20_000
_many = lambda v: v.remember("many", lambda: materialize(V.order_points(v).where("qid % 20 = 0")))
for _m in METHODS:
    query(f"rq_many_{_m}", O.sql(f"select qid, object_id, dist_mm from od where dist_mm <= {_NEAR}", _MANY, O.OBJECTS, _OD, pairs=True))(lambda v, m=_m: ranges.range_query(m, v, _many(v), V.objects(v), _NEAR))
query("knn_many_dm", O.sql("select qid, row_number() over (partition by qid order by dist_mm, object_id) as rank, object_id, dist_mm from od qualify rank <= 3", _MANY, O.OBJECTS, _OD, pairs=True))(lambda v: knn.knn_query("dm", v, _many(v), V.objects(v), 3))

# ---- experiment tasks: counters -----------------------------------------------------------------------------------

_names = ", ".join(f"('{NAMES[m]}')" for m in METHODS)
_list = lambda xs: "unnest([" + ", ".join(map(str, xs)) + "])"
query("task_b2", O.sql(f"select method, objects, count(dist_mm) as answers from (values {_names}) m(method), (select {_list(workload.OBJECTS)}::int as objects) left join od on object_id < objects and dist_mm <= {R_MM} group by 1, 2", _POINTS, O.OBJECTS, _OD, pairs=True))(workload.object_counters)
query("task_b3", O.sql(f"select method, r_mm, (select count(*) from reach where d <= r_mm) as labels, (select count(*) from od where dist_mm <= r_mm) as answers from (values {_names}) m(method), (select {_list(workload.RADII)}::bigint as r_mm)", _POINTS, O.OBJECTS, _OD, pairs=True))(workload.radius_counters)
query("task_b4", O.sql(f"select method, k, count(*) as answers, sum(dist_mm)::bigint as sum_mm from (values {_names}) m(method), (select {_list(workload.KS)}::int as k) join (select *, row_number() over (partition by qid order by dist_mm, object_id) as rank from od) on rank <= k group by 1, 2", _POINTS, O.OBJECTS, _OD, pairs=True))(workload.neighbour_counters)
query("task_b5", O.sql(f"""select method, s2t_mm, count(*) as pairs, sum(dist_mm)::bigint as sum_mm, sum(case when method = 'door_matrix' then look else spread end)::bigint as nvd
    from (values ('access_graph'), ('door_matrix'), ('layered_rtree')) m(method),
    (select s2t_mm, qid, dist_mm from sdq, (select {_list(workload.S2T)}::bigint as s2t_mm) qualify row_number() over (partition by s2t_mm order by abs(dist_mm - s2t_mm), qid) <= 10)
    join (select src.qid, (select count(*) from exits e where e.part_id = src.part_id) + (select count(*) from entries n where n.part_id = dst.part_id) as look from src join dst using (qid)) using (qid)
    join (select sdq.qid, count(*) as spread from sdq join ahead on ahead.qid = sdq.qid and d <= dist_mm group by 1) using (qid) group by 1, 2""", _POINTS, O.PAIR_SIDES, O.pair_distances(), _AG_NVD, pairs=True))(workload.distance_counters)


def _each(select, names, variant: bool) -> str:
    return " union all ".join(f"select * from ({select(n)})" for n in names)


_variant_sql = lambda n: O.sql(f"select '{n}' as variant, (select count(*) from door) as doors, (select count(*) from legs) as legs, count(dist_mm) as reached, sum(dist_mm)::bigint as sum_mm from pr left join sdq using (qid)", _POINTS, O.PAIR_SIDES, O.pair_distances(), variant=n, pairs=True)
query("task_b6", _each(_variant_sql, workload.TOPOLOGY, True))(lambda v: workload.variant_counters(v.spark, v.sf_dir, workload.TOPOLOGY))
query("task_b7", _each(_variant_sql, ("nocut", "base", "fine"), True))(lambda v: workload.variant_counters(v.spark, v.sf_dir, ("nocut", "base", "fine")))
query("task_b7_merged")(lambda v: workload.variant_counters(v.spark, v.sf_dir, workload.DECOMPOSITION))
query("task_a", _each(lambda n: O.sql(f"select {n}::int as floors, (select count(*) from door) as doors, count(*) as matrix_rows, sum(d)::bigint as sum_mm, max(d) as max_mm from dist", floors=n, pairs=True), workload.FLOORS, False))(lambda v: workload.floor_counters(v.spark, v.sf_dir))
query("stats_of_variants", _each(lambda n: O.sql(f"""select '{n}' as variant, (select count(distinct floor) from part) as floors, (select count(*) from part) as partitions, (select count(distinct door) from door) as doors,
    (select count(*) from part where kind = 'hall')::bigint as hallways, (select count(*) from dv where dv > {GAMMA}) as crucial,
    quantile_disc(dv, 0.25)::bigint as q1, quantile_disc(dv, 0.5)::bigint as q2, quantile_disc(dv, 0.75)::bigint as q3, max(dv) as max_dv from dv""", _DV, variant=n), ("sparse", "base", "dense", "fine", "nocut"), True))(lambda v: workload.stats_of_variants(v.spark, v.sf_dir))
_labels_of = lambda n: O.sql(f"select count(*) as n from reach where d <= {R_MM}", _POINTS, O.OBJECTS, _OD, variant=n, pairs=True)
query("growth_ratio", f"select method, ((select n from ({_labels_of('dense')})) / (select n from ({_labels_of('sparse')})))::double as ratio from (values {_names}) m(method)")(lambda v: workload.growth(v.spark, v.sf_dir))
_AG_BYTES = "(select count(*) from move) * 24 + (select count(*) from legs) * 32 + (select count(*) from (select distinct door, t from move where t <> 0)) * 24"
query("query_memory", O.sql(f"""select 'access_graph' as method, {_AG_BYTES} as resident_bytes, (select count(*) from reach join graph g on g.a = reach.door where d <= {R_MM}) * 24 as read_bytes, (select count(*) from reach where d <= {R_MM}) * 24 as label_bytes
    union all select 'door_matrix', {_AG_BYTES} + (select count(*) from dist) * 44, (select count(*) from ex join dist on a = ex.door and leg + d <= {R_MM}) * 24, (select count(*) from reach where d <= {R_MM}) * 24""", _POINTS, O.OBJECTS, _OD, pairs=True))(
    lambda v: metrics.query_memory("ag", v, V.query_points(v), R_MM).union(metrics.query_memory("dm", v, V.query_points(v), R_MM))
)
query("query_memory_trees")(lambda v: metrics.query_memory("lr", v, V.query_points(v), R_MM).union(metrics.query_memory("bt", v, V.query_points(v), R_MM)).union(metrics.query_memory("btd", v, V.query_points(v), R_MM)))
query("predicted_counted")(lambda v: metrics.predicted_and_counted(v, V.query_points(v), V.query_pairs(v), V.objects(v), R_MM, 9.0))
query("measured_winner", "select * from (values ('space', 'access_graph'), ('sdq', 'door_matrix')) t(measure, method)")(
    lambda v: metrics.measured_winner(metrics.predicted_and_counted(v, V.query_points(v), V.query_pairs(v), V.objects(v), R_MM, 9.0).where("measure <> 'rq_knn'"))
)
query("bench_task_a")(lambda v: workload.run_task(v.spark, v.sf_dir, "A"))
query("border_report")(lambda v: workload.border_report(v.spark, v.sf_dir))


def queries() -> dict[str, Query]:
    return dict(_queries)


def oracle_sql() -> dict[str, str]:
    return dict(_oracles)
