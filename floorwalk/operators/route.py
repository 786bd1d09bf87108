"""Shortest distance and shortest path queries, and the doors that each method visits for them.

The answer of a pair is the least of the direct leg (one host for both points) and leg + door distance + leg. The canonical
path is the lexicographically least door sequence among the shortest.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from floorwalk.functions.geometry import leg_mm
from floorwalk.operators.host import locate_grid
from floorwalk.operators.labels import climb, point_labels
from floorwalk.operators.topology import entry_legs, exit_legs, graph_legs
from floorwalk.plans.border import build_border_tree
from floorwalk.plans.matrix import door_matrix
from floorwalk.plans.relax import is_local, local_routes, relational_routes, walk_hops
from floorwalk.sources.scratch import materialize
from floorwalk.sources.venue import Venue

START_MM = 64_000


def sides(venue: Venue, pairs: DataFrame) -> tuple[DataFrame, DataFrame]:
    """Placed sources and targets (qid, floor, x_mm, y_mm, part_id)."""
    parts = venue.cache["original"].partitions if venue.override is not None else venue.partitions
    source = pairs.select("qid", F.col("s_floor").alias("floor"), F.col("s_x").alias("x_mm"), F.col("s_y").alias("y_mm"))
    target = pairs.select("qid", F.col("t_floor").alias("floor"), F.col("t_x").alias("x_mm"), F.col("t_y").alias("y_mm"))
    return locate_grid(source, parts), locate_grid(target, parts)


def direct_legs(source: DataFrame, target: DataFrame) -> DataFrame:
    """(qid, dist) for pairs inside one partition."""
    other = target.select("qid", "part_id", F.col("x_mm").alias("tx"), F.col("y_mm").alias("ty"))
    return source.join(other, ["qid", "part_id"]).select("qid", leg_mm("x_mm", "y_mm", "tx", "ty").alias("dist"))


def _doubled(method: str, venue: Venue, source: DataFrame, target: DataFrame) -> DataFrame:
    """Expansion with a doubled radius until the best complete candidate lies within it, so it is exact: for any size."""
    ends = entry_legs(venue, target).select("qid", "door", F.col("dist").alias("rest"))
    radius, open_points, done, before = START_MM, source, None, None
    while True:
        found = materialize(point_labels(method, venue, open_points, radius))
        best = materialize(found.join(ends, ["qid", "door"]).groupBy("qid").agg(F.min(F.col("dist") + F.col("rest")).alias("dist")))
        settled = best.where(F.col("dist") <= radius)
        done = settled if done is None else done.union(settled)
        open_points = materialize(open_points.join(settled, "qid", "left_anti"))
        state = (found.count(), open_points.count())
        if not state[1]:
            return done
        if state == before:  # nothing new within twice the radius; a longer leg may still lead on
            found = point_labels(method, venue, open_points)
            return done.union(found.join(ends, ["qid", "door"]).groupBy("qid").agg(F.min(F.col("dist") + F.col("rest")).alias("dist")))
        before, radius = state, radius * 2


def local_graph(venue: Venue) -> bool:
    return venue.remember("local", lambda: is_local(graph_legs(venue)))


def _expanded(method: str, venue: Venue, source: DataFrame, target: DataFrame, with_path: bool) -> DataFrame:
    """(qid, dist [, path]) by expansion from the source until the target is met; the layered tree rules doors out by the
    straight line to the target. One job where the legs are of a checked size, else a round at a time."""
    starts, legs = exit_legs(venue, source), graph_legs(venue)
    ends = entry_legs(venue, target).select("qid", "door", F.col("dist").alias("rest"))
    if local_graph(venue):
        more = (venue.doors, target) if method == "lr" else (None, None)
        return local_routes(starts, ends, legs, with_path, *more)
    best = _doubled(method, venue, source, target)
    if not with_path:
        return best
    return relational_routes(starts, ends, legs, materialize(best.withColumnRenamed("dist", "bound")))


def _matrix_lookup(venue: Venue, source: DataFrame, target: DataFrame) -> DataFrame:
    a = exit_legs(venue, source).select("qid", F.col("door").alias("a_door"), F.col("dist").alias("first"))
    b = entry_legs(venue, target).select("qid", F.col("door").alias("b_door"), F.col("dist").alias("rest"))
    rows = a.join(b, "qid").join(door_matrix(venue), ["a_door", "b_door"])
    return rows.select("qid", "a_door", "b_door", (F.col("first") + F.col("dist_mm") + F.col("rest")).alias("dist"))


def _common_ancestor(tree, source: DataFrame, target: DataFrame) -> DataFrame:
    """(qid, lca, from_node, to_node): the lowest node over both host leaves and its children on the two sides."""
    lines = tree.nodes.where("level = 0").select(F.col("node_id").alias("leaf"), "ancestors")
    home = lambda frame, name: frame.join(tree.members, "part_id").join(lines, "leaf").select("qid", F.col("ancestors").alias(name))
    pair = home(source, "up").join(home(target, "down"), "qid").withColumn("lca", F.element_at(F.array_intersect("up", "down"), 1))
    child = lambda name: F.when(F.array_position(name, F.col("lca")) > 1, F.element_at(F.col(name), (F.array_position(name, F.col("lca")) - 1).cast("int")))
    return pair.select("qid", "lca", child("up").alias("from_node"), child("down").alias("to_node"))


def _through_tree(venue: Venue, source: DataFrame, target: DataFrame, deep: bool) -> DataFrame:
    """(qid, dist, up_door, down_door): up to the children of the lowest common ancestor, across its inner cells, down
    again; leaf pairs inside one leaf (doors NULL)."""
    tree = build_border_tree(venue)
    pair = materialize(_common_ancestor(tree, source, target))
    up, down = climb(venue, tree, source, False, deep), climb(venue, tree, target, True, deep)
    first = pair.join(up, (pair["qid"] == up["qid"]) & (pair["from_node"] == up["node_id"])).select(pair["qid"], "lca", F.col("door").alias("a_door"), F.col("dist").alias("d1"))
    last = pair.join(down, (pair["qid"] == down["qid"]) & (pair["to_node"] == down["node_id"])).select(pair["qid"], F.col("door").alias("b_door"), F.col("dist").alias("d2"))
    inner = tree.inner.select(F.col("node_id").alias("lca"), "a_door", "b_door", "dist_mm")
    across = first.join(last, "qid").join(inner, ["lca", "a_door", "b_door"]).select("qid", (F.col("d1") + F.col("dist_mm") + F.col("d2")).alias("dist"), F.col("a_door").alias("up_door"), F.col("b_door").alias("down_door"))
    same = pair.where("from_node is null").select("qid", F.col("lca").alias("leaf"))
    a = exit_legs(venue, source).select("qid", F.col("door").alias("a_door"), F.col("dist").alias("d1")).join(same, "qid")
    b = entry_legs(venue, target).select("qid", F.col("door").alias("b_door"), F.col("dist").alias("d2"))
    none = F.lit(None).cast("long")
    inside = a.join(b, "qid").join(tree.leaf_pairs, ["leaf", "a_door", "b_door"]).select("qid", (F.col("d1") + F.col("dist_mm") + F.col("d2")).alias("dist"), none, none)
    return across.union(inside)


def _tree_paths(venue: Venue, source: DataFrame, target: DataFrame, best: DataFrame, deep: bool) -> DataFrame:
    """(qid, path): pieces of the shortest ways, host door to the common ancestor's child's access door, across, and to the
    host door at the end, each walked along stored first hops; a piece whose doors lack one is walked over the legs."""
    tree = build_border_tree(venue)
    at = lambda name: F.col(name)
    won = materialize(_through_tree(venue, source, target, deep).join(best.withColumnRenamed("dist_mm", "dist"), ["qid", "dist"]))
    starts = exit_legs(venue, source).select("qid", F.col("door").alias("a"), F.col("dist").alias("d1"))
    ends = entry_legs(venue, target).select("qid", F.col("door").alias("b"), F.col("dist").alias("d2"))
    pairs_of = tree.leaf_pairs.select(F.col("a_door").alias("a"), F.col("b_door").alias("b"), "dist_mm").distinct()
    inside = won.where("up_door is null").select("qid", "dist").distinct().join(starts, "qid").join(ends, "qid").join(pairs_of, ["a", "b"]).where("d1 + dist_mm + d2 = dist")
    inside = inside.select("qid", F.array(F.struct(at("a").alias("f"), at("b").alias("t"))).alias("pieces"))
    out_cell = tree.deep_out.select(F.col("door_id").alias("a"), F.col("access_door").alias("up_door"), F.col("dist_mm").alias("m1")).distinct()
    in_cell = tree.deep_in.select(F.col("door_id").alias("b"), F.col("access_door").alias("down_door"), F.col("dist_mm").alias("m3")).distinct()
    mid = tree.inner.select(F.col("a_door").alias("up_door"), F.col("b_door").alias("down_door"), F.col("dist_mm").alias("m2")).distinct()
    across = won.where("up_door is not null").join(starts, "qid").join(out_cell, ["a", "up_door"]).join(ends, "qid").join(in_cell, ["b", "down_door"]).join(mid, ["up_door", "down_door"])
    across = across.where("d1 + m1 + m2 + m3 + d2 = dist")
    step = lambda f, t: F.struct(at(f).alias("f"), at(t).alias("t"))
    across = across.select("qid", F.array(step("a", "up_door"), step("up_door", "down_door"), step("down_door", "b")).alias("pieces"))
    ways = materialize(inside.union(across).distinct().withColumn("way", F.monotonically_increasing_id()))
    parts = ways.select("qid", "way", F.posexplode("pieces").alias("place", "piece")).select("qid", "way", "place", at("piece.f").alias("a_door"), at("piece.t").alias("b_door"))
    wanted = materialize(parts.select("a_door", "b_door").distinct())
    cells = [tree.deep_out.select(F.col("door_id").alias("a_door"), F.col("access_door").alias("b_door"), "first_hop", "stride_hop"), tree.deep_in.select(F.col("access_door").alias("a_door"), F.col("door_id").alias("b_door"), "first_hop", "stride_hop"), tree.leaf_pairs.select("a_door", "b_door", "first_hop", "stride_hop"), tree.inner.select("a_door", "b_door", "first_hop", "stride_hop")]
    hops = cells[0].union(cells[1]).union(cells[2]).union(cells[3]).where("first_hop is not null").join(wanted.select("b_door").distinct(), "b_door", "left_semi").distinct()
    walked = materialize(walk_hops(hops, graph_legs(venue).where("leg_mm = 0"), wanted))
    stuck = materialize(wanted.join(walked, ["a_door", "b_door"], "left_anti").withColumn("qid", F.monotonically_increasing_id()))
    if not stuck.isEmpty():
        begin, finish = stuck.select("qid", F.col("a_door").alias("door"), F.lit(0).cast("long").alias("dist")), stuck.select("qid", F.col("b_door").alias("door"), F.lit(0).cast("long").alias("rest"))
        if local_graph(venue):
            found = local_routes(begin, finish, graph_legs(venue))
        else:
            far = cells_distance(tree).join(stuck, ["a_door", "b_door"]).groupBy("qid").agg(F.min("dist_mm").alias("bound"))
            found = relational_routes(begin, finish, graph_legs(venue), materialize(far))
        walked = walked.union(found.join(stuck, "qid").select("a_door", "b_door", "path"))
    lists = parts.join(walked, ["a_door", "b_door"]).groupBy("qid", "way").agg(F.array_sort(F.collect_list(F.struct("place", "path"))).alias("l"), F.count("*").alias("n"))
    whole = lists.join(ways.select("way", F.size("pieces").alias("n")), ["way", "n"])
    joined = F.aggregate("l", F.array().cast("array<bigint>"), lambda s, x: F.when(F.size(s) == 0, x["path"]).otherwise(F.concat(s, F.slice(x["path"], F.lit(2), F.greatest(F.size(x["path"]) - 1, F.lit(0))))))
    once = whole.select("qid", joined.alias("path")).where(F.size("path") == F.size(F.array_distinct("path")))  # no way turns back
    return once.groupBy("qid").agg(F.min("path").alias("path"))


def cells_distance(tree) -> DataFrame:
    """(a_door, b_door, dist_mm) of all cells of a tree."""
    out = tree.deep_out.select(F.col("door_id").alias("a_door"), F.col("access_door").alias("b_door"), "dist_mm")
    back = tree.deep_in.select(F.col("access_door").alias("a_door"), F.col("door_id").alias("b_door"), "dist_mm")
    return out.union(back).union(tree.leaf_pairs.select("a_door", "b_door", "dist_mm")).union(tree.inner.select("a_door", "b_door", "dist_mm"))


def distance_query(method: str, venue: Venue, pairs: DataFrame) -> DataFrame:
    """(qid, dist_mm); dist_mm is NULL where the target cannot be reached."""
    source, target = sides(venue, pairs)
    if method in ("ag", "lr"):
        via = _expanded(method, venue, source, target, False)
    elif method == "dm":
        via = _matrix_lookup(venue, source, target).select("qid", "dist")
    else:
        via = _through_tree(venue, source, target, deep=method == "btd")
    best = via.select("qid", "dist").union(direct_legs(source, target)).groupBy("qid").agg(F.min("dist").alias("dist_mm"))
    return pairs.select("qid").join(best, "qid", "left").select("qid", "dist_mm")


def visited_doors(method: str, venue: Venue, source: DataFrame, target: DataFrame, best: DataFrame) -> DataFrame:
    """(qid, nvd): doors that a method's own search reads for a pair."""
    if method in ("ag", "lr"):
        limit = best.select("qid", F.col("dist_mm").alias("bound"))
        return point_labels(method, venue, source, limit).groupBy("qid").agg(F.count("*").alias("nvd"))
    ends = exit_legs(venue, source).select("qid", "door", F.lit(0).alias("side")).union(entry_legs(venue, target).select("qid", "door", F.lit(1).alias("side")))
    if method == "dm":
        return ends.groupBy("qid").agg(F.count("*").alias("nvd"))
    tree = build_border_tree(venue)
    deep = method == "btd"
    up, down = climb(venue, tree, source, False, deep), climb(venue, tree, target, True, deep)
    if deep:  # only the two children of the common ancestor are read
        nodes = _common_ancestor(tree, source, target).select("qid", F.explode(F.array("from_node", "to_node")).alias("node_id")).where("node_id is not null")
        up, down = up.join(nodes, ["qid", "node_id"], "left_semi"), down.join(nodes, ["qid", "node_id"], "left_semi")
    doors = ends.select("qid", "door", "side").union(up.select("qid", "door", F.lit(0))).union(down.select("qid", "door", F.lit(1))).distinct()
    return doors.groupBy("qid").agg(F.count("*").alias("nvd"))


def route_query(method: str, venue: Venue, pairs: DataFrame, with_nvd: bool = True) -> DataFrame:
    """(qid, dist_mm, door_path [, nvd]): distance and canonical path; both NULL where the target cannot be reached."""
    source, target = sides(venue, pairs)
    direct = direct_legs(source, target)
    if method in ("ag", "lr"):
        found = materialize(_expanded(method, venue, source, target, True))
        best = found.select("qid", "dist").union(direct).groupBy("qid").agg(F.min("dist").alias("dist_mm"))
        best = materialize(pairs.select("qid").join(best, "qid", "left").select("qid", "dist_mm"))
    else:
        best = materialize(distance_query(method, venue, pairs))
    straight = direct.withColumnRenamed("dist", "dist_mm").join(best, ["qid", "dist_mm"]).select("qid", F.array().cast("array<bigint>").alias("path"))
    walked = best.where("dist_mm is not null").join(straight, "qid", "left_anti")
    if method == "dm":
        tied = materialize(_matrix_lookup(venue, source, target).join(walked.withColumnRenamed("dist_mm", "dist"), ["qid", "dist"]).select("qid", "a_door", "b_door"))
        ends = tied.select("a_door", "b_door").distinct()
        ways = walk_hops(door_matrix(venue).join(ends.select("b_door").distinct(), "b_door", "left_semi"), graph_legs(venue).where("leg_mm = 0"), ends)
        paths = tied.join(ways, ["a_door", "b_door"]).groupBy("qid").agg(F.min("path").alias("path"))
    elif method in ("ag", "lr"):
        paths = found.join(walked.select("qid"), "qid", "left_semi").select("qid", "path")
    else:
        keep = walked.select("qid")
        paths = _tree_paths(venue, source.join(keep, "qid", "left_semi"), target.join(keep, "qid", "left_semi"), walked, method == "btd")
    out = best.join(paths.unionByName(straight), "qid", "left").select("qid", "dist_mm", F.col("path").alias("door_path"))
    if with_nvd:
        out = out.join(visited_doors(method, venue, source, target, best.where("dist_mm is not null")), "qid", "left")
    return out


def path_query(method: str, venue: Venue, pairs: DataFrame) -> DataFrame:
    return route_query(method, venue, pairs, with_nvd=False).select("qid", "door_path")
