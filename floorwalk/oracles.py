"""Independent DuckDB SQL for the registered queries: the venue as CTEs over the given tables, distances by keyed recursion."""

from __future__ import annotations


def leg(a: str, b: str) -> str:
    return f"cast(ceil(sqrt(cast(({a}x-{b}x)*({a}x-{b}x)+({a}y-{b}y)*({a}y-{b}y) as double))) as bigint)"


def venue(floors: int = 5, variant: str = "base") -> str:
    cut = {"fine": 2, "nocut": 99}.get(variant, 4)
    second = {"sparse": "false", "dense": "true"}.get(variant, "s % 3 = 0")
    through = "false" if variant == "sparse" else "true"
    return f"""
fl as (select range::bigint as floor, (range % 5)::bigint as template, (range * 100000000)::bigint as base from range({floors})),
na as (select n_nationkey::bigint as nation, n_regionkey::bigint as template, row_number() over (partition by n_regionkey order by n_nationkey) - 1 as g from nation),
nr as (select s_nationkey::bigint as nation, count(*) as rooms from supplier group by 1),
hall as (select floor, base, na.nation, g, coalesce(rooms, 0)::bigint as rooms, greatest(1, (coalesce(rooms, 0) + 1) // 2)::bigint as cols,
    greatest(1, (coalesce(rooms, 0) + 1) // 2)::bigint * 10000 as length, g * 20000 as hy from fl join na using (template) left join nr using (nation)),
sup as (select s_suppkey::bigint as s, s_nationkey::bigint as nation, row_number() over (partition by s_nationkey order by s_suppkey) - 1 as i from supplier),
room as (select s, i, i // 2 as c, i % 2 as side, hall.* from sup join hall using (nation)),
cell as (select hall.*, k as s, (cols + {cut} - 1) // {cut} as n, base + 1000000 + nation * 1000 as c0 from hall, range(100) t(k) where k < (cols + {cut} - 1) // {cut}),
stairs as (
    select floor, base, case when g = 0 then 0 else 1 end as k, base + 2000000 + g as host, -6000 as x, case when g = 0 then 10000 else 90000 end as y from hall where g in (0, 4)
    union all select floor, base, case when g = 1 then 2 else 3 end, base + 1000000 + nation * 1000 + (cols + {cut} - 1) // {cut} - 1, length, case when g = 1 then 30000 else 70000 end from hall where g in (1, 3)),
part as (
    select c0 + s as part_id, 'hall' as kind, floor, s * 10000 * {cut} as xmin, hy + 8000 as ymin, least(length, (s + 1) * 10000 * {cut}) as xmax, hy + 12000 as ymax, cast(null as bigint) as stair_mm from cell
    union all select base + 2000000 + g, 'lobby', floor, -6000, hy, 0, hy + 20000, null from hall
    union all select base + 10000000 + s, 'room', floor, c * 10000, hy + case side when 0 then 12000 else 0 end, (c + 1) * 10000, hy + case side when 0 then 20000 else 8000 end, null from room
    union all select base + 3000000 + k, 'stair', floor, null, null, null, null, 20000 from stairs where floor < {floors - 1}),
both_ways as (
    select c0 + s as door, 'segment' as kind, floor, (s + 1) * 10000 * {cut} as x, hy + 10000 as y, c0 + s as f, c0 + s + 1 as t, true as back from cell where s < n - 1
    union all select base + 2000000 + g, 'lobby_hall', floor, 0, hy + 10000, base + 2000000 + g, base + 1000000 + nation * 1000, true from hall
    union all select base + 2001000 + g, 'lobby_lobby', floor, -3000, hy + 20000, base + 2000000 + g, base + 2000001 + g, true from hall where g < 4
    union all select base + 10000000 + s, 'room_main', floor, c * 10000 + 5000, hy + case side when 0 then 12000 else 8000 end, base + 1000000 + nation * 1000 + c // {cut}, base + 10000000 + s, true from room
    union all select base + 20000000 + s, 'room_second', floor, c * 10000 + 8000, hy + case side when 0 then 12000 else 8000 end, base + 10000000 + s, base + 1000000 + nation * 1000 + c // {cut}, s % 2 <> 0 from room where {second}
    union all select u.base + 30000000 + u.s, 'through', u.floor, u.c * 10000 + 5000, 20000 * (u.g + 1), u.base + 10000000 + u.s, u.base + 10000000 + l.s, u.s % 5 <> 0
        from room u join room l on l.floor = u.floor and l.g = u.g + 1 and l.c = u.c and u.side = 0 and l.side = 1 where {through}
    union all select base + 3000000 + k, 'stair_low', floor, x, y, host, base + 3000000 + k, k <> 3 from stairs where floor < {floors - 1}
    union all select base - 100000000 + 4000000 + k, 'stair_high', floor, x, y, base - 100000000 + 3000000 + k, host, k <> 3 from stairs where floor > 0
    union all select 5000000, 'entrance', 0, -6000, 50000, 0, 2000002, true
    union all select 5000001, 'exit_only', 0, -3000, 100000, 2000004, 0, false),
door as (select door::bigint as door, kind, floor::bigint as floor, x::bigint as x, y::bigint as y from both_ways),
move as (select door::bigint as door, f::bigint as f, t::bigint as t from both_ways union all select door, t, f from both_ways where back),
legs as (select m.t::bigint as part_id, a.door as a, b.door as b, coalesce(p.stair_mm, {leg('a.', 'b.')}) as leg
    from move m join door a on a.door = m.door join move o on o.f = m.t and o.door <> m.door join door b on b.door = o.door join part p on p.part_id = m.t
    group by all),
graph as (select a, b, min(leg) as leg from legs group by a, b)"""


PAIRS = """
dist(a, b, d) using key (a, b) as (
    select door, door, 0::bigint from door
    union
    select r.a, g.b, min(r.d + g.leg) from dist r join graph g on g.a = r.b left join recurring.dist k on k.a = r.a and k.b = g.b
    where k.d is null or r.d + g.leg < k.d group by r.a, g.b)"""


def place(keys: str, name: str, limit: str = "true") -> str:
    """CTE `name` (key, floor, x, y, host) of points of the 5-floor venue from a subquery of (key, nation)."""
    return f"""
{name} as (select key, floor, case when o < rooms then (o // 2) * 10000 + 1 + (7919 * key) % 9998 else 1 + (7919 * key) % (length - 2) end as x,
    case when o < rooms then hy + case o % 2 when 0 then 12000 else 0 end + 1 + (104729 * key) % 7998 else hy + 8001 + (104729 * key) % 3998 end as y
    from (select q.key, hall.*, q.key % (rooms + 1) as o from ({keys}) q join hall using (nation)) where {limit})"""


OBJECTS = place("select c_custkey::bigint as key, c_nationkey::bigint as nation from customer", "obj0") + """,
obj as (select key as object_id, obj0.floor, x, y, part_id from obj0 join part p on p.floor = obj0.floor and x >= xmin and x < xmax and y >= ymin and y < ymax)"""


def points(n: int | None = 10, where: str | None = None) -> str:
    where = f"where {where}" if where else f"where o_orderkey < {n}" if n else ""
    return place(f"select o_orderkey::bigint as key, c_nationkey::bigint as nation from orders join customer on c_custkey = o_custkey {where}", "pt0") + """,
pt as (select key as qid, pt0.floor, x, y, part_id from pt0 join part p on p.floor = pt0.floor and x >= xmin and x < xmax and y >= ymin and y < ymax)"""


PAIR_SIDES = """
pr as (select distinct l_orderkey::bigint * 1000000 + l_suppkey::bigint as qid, l_orderkey::bigint as o, l_suppkey::bigint as s from lineitem where l_orderkey < 10),
src as (select pr.qid, pt.floor, pt.x, pt.y, pt.part_id from pr join pt on pt.qid = o),
dst as (select pr.qid, r.floor, r.c * 10000 + 5000 as x, r.hy + case side when 0 then 12000 else 0 end + 4000 as y, base + 10000000 + r.s as part_id from pr join room r on r.s = pr.s
    qualify row_number() over (partition by pr.qid order by r.floor) = 1),
exits as (select distinct f as part_id, door from move), entries as (select distinct t as part_id, door from move)"""


def object_distances() -> str:
    return f"""
ex as (select distinct pt.qid, d.door, {leg('pt.', 'd.')} as leg from pt join move m on m.f = pt.part_id join door d on d.door = m.door),
reach as (select qid, b as door, min(ex.leg + d) as d from ex join dist on a = ex.door group by 1, 2),
od as (select qid, object_id, min(d) as dist_mm from (
    select qid, object_id, r.d + {leg('d.', 'obj.')} as d from reach r join move m on m.door = r.door join door d on d.door = r.door join obj on obj.part_id = m.t
    union all select qid, object_id, {leg('pt.', 'obj.')} from pt join obj using (part_id)) group by 1, 2)"""


def pair_distances() -> str:
    return f"""
sdq as (select qid, min(d) as dist_mm from (
    select src.qid, {leg('src.', 'da.')} + dist.d + {leg('db.', 'dst.')} as d from src join exits e on e.part_id = src.part_id join door da on da.door = e.door
      join dist on dist.a = e.door join entries n on n.door = dist.b join dst on dst.qid = src.qid and dst.part_id = n.part_id join door db on db.door = n.door
    union all select src.qid, {leg('src.', 'dst.')} from src join dst using (qid, part_id)) group by 1)"""


def pair_paths() -> str:
    return f"""
lab(qid, door, l) using key (qid, door) as (
    select src.qid, e.door, {{'d': {leg('src.', 'da.')}, 'p': [e.door]}} from src join exits e on e.part_id = src.part_id join door da on da.door = e.door
    union
    select r.qid, g.b, min({{'d': r.l.d + g.leg, 'p': list_append(r.l.p, g.b)}}) from lab r join graph g on g.a = r.door left join recurring.lab k on k.qid = r.qid and k.door = g.b
    where k.l is null or {{'d': r.l.d + g.leg, 'p': list_append(r.l.p, g.b)}} < k.l group by r.qid, g.b),
best as (select qid, min(c) as c from (
    select lab.qid, {{'d': lab.l.d + {leg('d.', 'dst.')}, 'p': lab.l.p}} as c from lab join entries n on n.door = lab.door join dst on dst.qid = lab.qid and dst.part_id = n.part_id join door d on d.door = lab.door
    union all select src.qid, {{'d': {leg('src.', 'dst.')}, 'p': cast([] as bigint[])}} from src join dst using (qid, part_id)) group by qid)"""


def sql(select: str, *parts: str, floors: int = 5, variant: str = "base", pairs: bool = False) -> str:
    body = ",".join([venue(floors, variant), *([PAIRS] if pairs else []), *parts])
    return f"with recursive {body}\n{select}"


OPEN_HOURS = """
hours as (select base + 10000000 + s as door, 3600 * (6 + s % 5) as open_s, case when s % 10 = 9 then 43200 else 3600 * (18 + s % 6) end as close_s from room
    union all select base + 10000000 + s, 46800, 3600 * (18 + s % 6) from room where s % 10 = 9)"""
