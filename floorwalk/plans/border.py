"""border_tree and border_tree_deep: a hierarchy of adjacent partitions with distance cells on border ("access") doors.

Leaves grow from crucial partitions by synchronous spreading, upper levels join each node with the neighbour it shares
most border doors with. Cells hold global shortest distances and the first door of a shortest path, so combining them is
exact. Tables: members (part_id, leaf), nodes (node_id, level, parent_id, ancestors), access (node_id, door_id), leaf_out /
leaf_in (leaf door to and from the leaf's access doors), leaf_pairs, inner (node, a, b), deep_out / deep_in (leaf door to and
from every ancestor's access doors); each with dist_mm, first_hop, stride_hop (see matrix.first_hops). All come from one
kernel at any size: the legs and their ladder go to each task, cells are dealt by where their doors lie.
"""

from __future__ import annotations

from dataclasses import dataclass
from functools import cached_property

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from floorwalk.operators.topology import crucial_parts, graph_legs
from floorwalk.plans.relax import FAR, LOCAL_LEGS, _Legs, is_local, leg_arrays, local_graph, local_hops  # noqa: F401  a test names is_local
from floorwalk.sources.scratch import materialize
from floorwalk.sources.venue import OUTDOOR, Venue

GAMMA = 6
FEW = 4  # of the leaves, one in so many at most are few
LEVEL_STEP = 1_000_000_000_000
CELL = ("dist_mm", "first_hop", "stride_hop")


@dataclass
class BorderTree:
    """The hierarchy is made at once, each kind of cells when it is first asked for."""

    venue: Venue
    members: DataFrame
    nodes: DataFrame
    access: DataFrame
    leaf_doors: DataFrame
    chain: DataFrame
    height: int

    @cached_property
    def _legs(self) -> DataFrame:
        return graph_legs(self.venue)

    @property
    def _graph(self):
        return self.venue.remember("ladder", lambda: local_graph(self.venue.doors.select("door_id"), self._legs))

    @cached_property
    def _wide(self) -> DataFrame:
        """(leaf, door_id, anc_node, access_door): a leaf's doors and the access doors of its ancestors, itself included."""
        line = self.chain.select(F.col("node_id").alias("leaf"), F.explode("ancestors").alias("anc_node"))
        return materialize(self.leaf_doors.join(line, "leaf").join(self.access.select(F.col("node_id").alias("anc_node"), F.col("door_id").alias("access_door")), "anc_node").select("leaf", "door_id", "anc_node", "access_door"))

    @cached_property
    def _inside(self) -> DataFrame:
        return self.leaf_doors.select("leaf", F.col("door_id").alias("a_door")).join(self.leaf_doors.select("leaf", F.col("door_id").alias("b_door")), "leaf")

    @cached_property
    def _across(self) -> DataFrame:
        children = self.nodes.where("parent_id is not null").select("node_id", "parent_id")
        rim = materialize(self.access.join(children, "node_id").select(F.col("parent_id").alias("node_id"), "door_id").distinct())
        return rim.select("node_id", F.col("door_id").alias("a_door")).join(rim.select("node_id", F.col("door_id").alias("b_door")), "node_id")

    def _hops(self, wanted: DataFrame) -> DataFrame:
        """wanted (a_door, b_door) -> (a_door, b_door, dist_mm, first_hop, stride_hop)."""
        return local_hops(wanted.groupBy(F.col("b_door").alias("door_id")).agg(F.collect_set("a_door").alias("starts")), self._legs, self._graph)

    def cell_counts(self) -> tuple[int, int]:
        """Rows of leaf_out and leaf_in together, and of inner, counted by what their doors can reach: cells are not made.

        Doors are counted by their strong components, so the driver sees a row for each pair of components.
        """
        reach = self.venue.remember("reach", lambda: _Reach(leg_arrays(self.venue.doors.select("door_id"), self._legs)))
        door = self.venue.remember("components", lambda: materialize(self.venue.spark.createDataFrame(pa.table({"door_id": reach.nodes, "component": reach.component}))))

        def reached(pairs: DataFrame) -> int:
            a, b = (door.select(F.col("door_id").alias(f"{x}_door"), F.col("component").alias(x)) for x in "ab")
            found = pairs.join(a, "a_door").join(b, "b_door").groupBy("a", "b").agg(F.count("*").alias("n")).collect()
            return sum(r["n"] for r in found if reach.beyond[r["a"]] >> r["b"] & 1)

        leaf = self._wide.where("anc_node = leaf")
        out, into = (leaf.select(F.col(x).alias("a_door"), F.col(y).alias("b_door")) for x, y in (("door_id", "access_door"), ("access_door", "door_id")))
        return reached(out) + reached(into), reached(self._across)

    @cached_property
    def inner(self) -> DataFrame:
        return materialize(self._across.join(self._hops(self._across.select("a_door", "b_door")), ["a_door", "b_door"]).select("node_id", "a_door", "b_door", *CELL))

    @cached_property
    def leaf_pairs(self) -> DataFrame:
        return self._pairs(self._inside)

    def _deep(self, wide: DataFrame, inward: bool) -> DataFrame:
        """Cells of the given doors and access doors: to the access doors, or from them."""
        ends = ("access_door", "door_id") if inward else ("door_id", "access_door")
        cells = self._hops(wide.select(F.col(ends[0]).alias("a_door"), F.col(ends[1]).alias("b_door"))).toDF(*ends, *CELL)
        return materialize(wide.join(cells, ["access_door", "door_id"]).select("leaf", "door_id", "anc_node", "access_door", *CELL))

    @cached_property
    def deep_out(self) -> DataFrame:
        return self._deep(self._wide, False)

    @cached_property
    def deep_in(self) -> DataFrame:
        return self._deep(self._wide, True)

    def home_cells(self, kind: str, leaves: DataFrame) -> DataFrame:
        """deep_out, deep_in or leaf_pairs for searches from some leaves (leaf): for few leaves, cells that are not made yet are
        made of these alone, once for the same leaves."""
        if kind in self.__dict__:
            return getattr(self, kind)
        names = sorted(r[0] for r in leaves.collect())  # no more than the leaves
        if FEW * len(names) > self.chain.count():
            return getattr(self, kind)

        def make():
            few = F.col("leaf").isin(names)
            if kind == "leaf_pairs":
                return self._pairs(self._inside.where(few))
            return self._deep(self._wide.where(few), kind == "deep_in")

        return self.venue.remember(("homes", id(self), kind, tuple(names)), make)

    def _pairs(self, inside: DataFrame) -> DataFrame:
        return materialize(inside.join(self._hops(inside.select("a_door", "b_door")), ["a_door", "b_door"]).select("leaf", "a_door", "b_door", *CELL))

    def _leaf(self, deep: str) -> DataFrame:
        if deep in self.__dict__:  # made before: only the leaves' part of it
            return materialize(self.__dict__[deep].where("anc_node = leaf").select("leaf", "door_id", "access_door", *CELL))
        return self._deep(self._wide.where("anc_node = leaf"), deep == "deep_in").select("leaf", "door_id", "access_door", *CELL)

    @cached_property
    def leaf_out(self) -> DataFrame:
        return self._leaf("deep_out")

    @cached_property
    def leaf_in(self) -> DataFrame:
        return self._leaf("deep_in")


class _Reach:
    """Which doors can be reached from which: strong components of the legs, and a bit set of components for each."""

    def __init__(self, graph: _Legs) -> None:
        n = len(graph.nodes)
        begin, target = graph.begin.tolist(), graph.target.tolist()
        self.nodes, self.component, self.beyond = graph.nodes, np.full(n, -1), []
        found, low, trail = [-1] * n, [0] * n, []
        count = 0
        for root in range(n):
            if found[root] >= 0:
                continue
            found[root] = low[root] = count
            count += 1
            trail.append(root)
            walk = [(root, begin[root])]
            while walk:
                v, leg = walk.pop()
                if leg < begin[v + 1]:
                    walk.append((v, leg + 1))
                    w = target[leg]
                    if found[w] < 0:
                        found[w] = low[w] = count
                        count += 1
                        trail.append(w)
                        walk.append((w, begin[w]))
                    elif self.component[w] < 0:
                        low[v] = min(low[v], found[w])
                    continue
                if walk:
                    low[walk[-1][0]] = min(low[walk[-1][0]], low[v])
                if low[v] == found[v]:  # components come after all that they lead to
                    number, bits, members = len(self.beyond), 1 << len(self.beyond), []
                    while not members or members[-1] != v:
                        members.append(trail.pop())
                    self.component[members] = number
                    for w in {int(c) for m in members for c in self.component[target[begin[m] : begin[m + 1]]]} - {number}:
                        bits |= self.beyond[w]
                    self.beyond.append(bits)

    def __call__(self, a: np.ndarray, b: np.ndarray) -> np.ndarray:
        pairs = np.stack([self.component[np.searchsorted(self.nodes, x)] for x in (a, b)])
        kinds, which = np.unique(pairs, axis=1, return_inverse=True)
        yes = np.array([self.beyond[x] >> y & 1 for x, y in kinds.T.tolist()], dtype=bool)
        return yes[which.ravel()]


def _neighbours(venue: Venue) -> DataFrame:
    edges = venue.moves.where(f"from_part <> {OUTDOOR} and to_part <> {OUTDOOR}")
    both = edges.select(F.col("from_part").alias("a"), F.col("to_part").alias("b"))
    return both.union(both.select("b", "a")).distinct()


def form_leaves(venue: Venue, gamma: int = GAMMA) -> DataFrame:
    """(part_id, leaf): every partition joins the nearest crucial one in hops, ties to the least id."""
    edges = materialize(_neighbours(venue))
    parts = venue.partitions.where(F.col("part_id") != OUTDOOR).select("part_id", "kind")
    seeds = crucial_parts(venue, gamma).select("part_id")
    for fallback in (seeds, parts.where("kind in ('lobby', 'concave')").select("part_id"), parts.agg(F.min("part_id").alias("part_id"))):
        labels_now = fallback.select("part_id", F.col("part_id").alias("leaf"))
        if not labels_now.isEmpty():
            break
    labels_now = materialize(labels_now)
    while True:
        spread = labels_now.join(edges, labels_now["part_id"] == edges["a"]).groupBy(F.col("b").alias("part_id")).agg(F.min("leaf").alias("leaf"))
        fresh = materialize(spread.join(labels_now, "part_id", "left_anti"))
        if fresh.isEmpty():
            rest = parts.join(labels_now, "part_id", "left_anti")
            if rest.isEmpty():
                return labels_now
            fresh = materialize(rest.agg(F.min("part_id").alias("part_id")).select("part_id", F.col("part_id").alias("leaf")))
        labels_now = materialize(labels_now.union(fresh))


def access_doors(venue: Venue, part_node: DataFrame) -> DataFrame:
    """part_node (part_id, node_id) -> (node_id, door_id): doors with one side inside the node and another outside."""
    sides = venue.moves.select("door_id", F.col("from_part").alias("part_id")).union(venue.moves.select("door_id", "to_part")).distinct()
    named = sides.join(part_node, "part_id", "left")
    span = named.groupBy("door_id").agg(F.count_distinct(F.coalesce("node_id", F.lit(-1).cast("long"))).alias("n"))
    return named.where("node_id is not null").join(span.where("n > 1"), "door_id").select("node_id", "door_id").distinct()


def _merge(access: DataFrame, members: DataFrame, level: int) -> DataFrame:
    """(node_id, parent_id): each node proposes the neighbour with most shared doors; proposal groups become parents."""
    shared = access.alias("x").join(access.alias("y"), (F.col("x.door_id") == F.col("y.door_id")) & (F.col("x.node_id") != F.col("y.node_id")))
    counts = shared.groupBy(F.col("x.node_id").alias("node_id"), F.col("y.node_id").alias("other")).agg(F.count("*").alias("n"))
    best = counts.withColumn("r", F.row_number().over(Window.partitionBy("node_id").orderBy(F.col("n").desc(), "other"))).where("r = 1")
    edges = best.select(F.col("node_id").alias("a"), F.col("other").alias("b"))
    edges = materialize(edges.union(edges.select("b", "a")).distinct())
    nodes = members.select("node_id").distinct()
    root = materialize(nodes.select("node_id", F.col("node_id").alias("root")))
    while True:
        low = root.join(edges, root["node_id"] == edges["a"]).groupBy(F.col("b").alias("node_id")).agg(F.min("root").alias("low"))
        near = root.join(low, "node_id", "left").select("node_id", F.least("root", F.coalesce("low", "root")).alias("root"))
        # A node also takes the root of its root: chains shrink by doubling instead of a step a round.
        far = near.select(F.col("node_id").alias("root"), F.col("root").alias("far"))
        new = materialize(near.join(far, "root").select("node_id", F.col("far").alias("root")))
        if new.join(root.withColumnRenamed("root", "old"), "node_id").where("root <> old").isEmpty():
            break
        root = new
    groups = root.select("root").distinct().count()
    total = root.count()
    if groups == total:  # nothing is adjacent: one artificial root
        return root.select("node_id", F.lit(level * LEVEL_STEP).cast("long").alias("parent_id"))
    return root.select("node_id", (F.lit(level * LEVEL_STEP) + F.col("root") % LEVEL_STEP).cast("long").alias("parent_id"))


def build_border_tree(venue: Venue, gamma: int = GAMMA) -> BorderTree:
    return venue.remember(("border", gamma), lambda: _build(venue, gamma))


def local_roots(left: np.ndarray, right: np.ndarray, root: np.ndarray) -> np.ndarray:
    """Least number reachable under links, by doubling."""
    while True:
        new = root.copy()
        low = np.minimum(root[left], root[right])
        np.minimum.at(new, root[left], low)
        np.minimum.at(new, root[right], low)
        new = new[new]
        if np.array_equal(new, root):
            return root
        root = new


def _grown(parts: np.ndarray, a: np.ndarray, b: np.ndarray, seeds: np.ndarray) -> np.ndarray:
    """form_leaves() over arrays: the leaf of every part, edges (a, b) both ways."""
    at_a, at_b, leaf = np.searchsorted(parts, a), np.searchsorted(parts, b), np.full(len(parts), FAR)
    fresh = np.searchsorted(parts, seeds)
    leaf[fresh] = seeds
    while True:
        open_edges = (leaf[at_a] < FAR) & (leaf[at_b] == FAR)
        if open_edges.any():
            low = np.full(len(parts), FAR)
            np.minimum.at(low, at_b[open_edges], leaf[at_a[open_edges]])
            leaf = np.minimum(leaf, low)
            continue
        rest = np.flatnonzero(leaf == FAR)
        if not len(rest):
            return leaf
        leaf[rest[0]] = parts[rest[0]]


def _rims(door: np.ndarray, node: np.ndarray) -> pd.DataFrame:
    """access_doors() over arrays: sides of doors with the node of each, -1 outside of all nodes."""
    sides = pd.DataFrame({"node_id": node, "door_id": door}).drop_duplicates()
    sides = sides[sides.groupby("door_id")["node_id"].transform("size") > 1]
    return sides[sides["node_id"] >= 0].reset_index(drop=True)


def _joined(rims: pd.DataFrame, nodes: np.ndarray, level: int) -> np.ndarray:
    """_merge() over arrays: the parent of each node."""
    shared = rims.merge(rims, on="door_id", suffixes=("", "_other"))
    shared = shared[shared["node_id"] != shared["node_id_other"]]
    counts = shared.groupby(["node_id", "node_id_other"]).size().reset_index(name="n")
    best = counts.sort_values(["node_id", "n", "node_id_other"], ascending=[True, False, True]).drop_duplicates("node_id")
    root = local_roots(np.searchsorted(nodes, best["node_id"].to_numpy()), np.searchsorted(nodes, best["node_id_other"].to_numpy()), np.arange(len(nodes)))
    if len(np.unique(root)) == len(nodes):  # nothing is adjacent: one artificial root
        return np.full(len(nodes), level * LEVEL_STEP)
    return level * LEVEL_STEP + nodes[root] % LEVEL_STEP


def _local_hierarchy(venue: Venue, gamma: int) -> tuple[DataFrame, DataFrame, DataFrame, DataFrame, int]:
    """Members, nodes, access doors, chains of ancestors and height from arrays, for moves of a checked size."""
    moves = venue.moves.select("door_id", "from_part", "to_part").toPandas()
    parts = venue.partitions.where(F.col("part_id") != OUTDOOR).select("part_id", "kind").toPandas().sort_values("part_id")
    seeds = np.array([r[0] for r in crucial_parts(venue, gamma).select("part_id").collect()], dtype=np.int64)
    ids = parts["part_id"].to_numpy(dtype=np.int64)
    if not len(seeds):
        seeds = ids[parts["kind"].isin(["lobby", "concave"]).to_numpy()]
    source, target = moves["from_part"].to_numpy(dtype=np.int64), moves["to_part"].to_numpy(dtype=np.int64)
    inner = (source != OUTDOOR) & (target != OUTDOOR)
    a, b = source[inner], target[inner]
    leaf = _grown(ids, np.concatenate([a, b]), np.concatenate([b, a]), seeds if len(seeds) else ids[:1])
    door, side = np.tile(moves["door_id"].to_numpy(dtype=np.int64), 2), np.concatenate([source, target])
    at = np.where(side == OUTDOOR, -1, np.searchsorted(ids, side))
    node, tip, level, rows, rims = leaf, np.unique(leaf), 0, [], []
    chains = [tip]
    while True:
        rims.append(_rims(door, np.where(at < 0, -1, node[np.maximum(at, 0)])))
        nodes = np.unique(node)
        if len(nodes) == 1:
            rows.append((nodes, level, None))
            break
        level += 1
        parent = _joined(rims[-1], nodes, level)
        rows.append((nodes, level - 1, parent))
        node = parent[np.searchsorted(nodes, node)]
        chains.append(parent[np.searchsorted(nodes, chains[-1])])
    long = lambda x: pa.array(np.asarray(x, dtype=np.int64))
    table = lambda **columns: materialize(venue.spark.createDataFrame(pa.table(columns)))
    members = table(part_id=long(ids), leaf=long(leaf))
    chain = table(node_id=long(tip), ancestors=pa.array(list(np.stack(chains, axis=1)), pa.list_(pa.int64())))
    parents = pa.chunked_array([pa.nulls(len(n), pa.int64()) if up is None else long(up) for n, _, up in rows])
    nodes = table(node_id=long(np.concatenate([n for n, _, _ in rows])), level=pa.array(np.concatenate([np.full(len(n), k, dtype=np.int32) for n, k, _ in rows])), parent_id=parents)
    access = pd.concat(rims)
    return members, materialize(nodes.join(chain, "node_id", "left")), table(node_id=long(access["node_id"]), door_id=long(access["door_id"])), chain, level


def _build(venue: Venue, gamma: int) -> BorderTree:
    if venue.moves.count() <= LOCAL_LEGS:
        members, nodes, access, chain, level = _local_hierarchy(venue, gamma)
    else:
        members, nodes, access, chain, level = _relational_hierarchy(venue, gamma)
    sides = venue.moves.select("door_id", F.col("from_part").alias("part_id")).union(venue.moves.select("door_id", "to_part"))
    leaf_doors = materialize(sides.join(members, "part_id").select("leaf", "door_id").distinct())
    return BorderTree(venue, members, nodes, access, leaf_doors, chain, level)


def _relational_hierarchy(venue: Venue, gamma: int) -> tuple[DataFrame, DataFrame, DataFrame, DataFrame, int]:
    members = materialize(form_leaves(venue, gamma))
    part_node = members.select("part_id", F.col("leaf").alias("node_id"))
    chain = members.select(F.col("leaf").alias("node_id")).distinct().withColumn("ancestors", F.array(F.col("node_id")))
    levels, access_all, level = [], [], 0
    while True:
        access = materialize(access_doors(venue, part_node))
        access_all.append(access)
        count = part_node.select("node_id").distinct().count()
        if count == 1:
            levels.append(part_node.select("node_id", F.lit(level).alias("level"), F.lit(None).cast("long").alias("parent_id")).distinct())
            break
        level += 1
        up = materialize(_merge(access, part_node, level))
        levels.append(up.select("node_id", F.lit(level - 1).alias("level"), "parent_id"))
        part_node = materialize(part_node.join(up, "node_id").select("part_id", F.col("parent_id").alias("node_id")))
        tip = chain.withColumn("tip", F.element_at("ancestors", -1)).join(up.withColumnRenamed("node_id", "tip"), "tip")
        chain = materialize(tip.select("node_id", F.array_append("ancestors", F.col("parent_id")).alias("ancestors")))
    nodes = levels[0]
    for frame in levels[1:]:
        nodes = nodes.union(frame)
    nodes = materialize(nodes.join(chain, "node_id", "left"))
    access = access_all[0]
    for frame in access_all[1:]:
        access = access.union(frame)
    return members, nodes, materialize(access), chain, level
