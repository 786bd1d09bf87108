"""Distance labels of query points under each of the five methods.

forward: (qid, door, dist) from the point to doors within the bound; backward: from doors to the point. Every method gives
exact labels for all doors within the bound; they differ in what they read on the way, which the callers may count.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from floorwalk.operators.topology import door_enters, door_leaves, entry_legs, exit_legs, graph_legs
from floorwalk.plans.border import BorderTree, build_border_tree
from floorwalk.plans.matrix import door_matrix
from floorwalk.plans.relax import labels, reverse
from floorwalk.plans.rtree import build_rtree, candidate_cells
from floorwalk.sources.scratch import materialize
from floorwalk.sources.venue import Venue

METHODS = ("ag", "dm", "lr", "bt", "btd")
NAMES = {"ag": "access_graph", "dm": "door_matrix", "lr": "layered_rtree", "bt": "border_tree", "btd": "border_tree_deep"}


def _within(frame: DataFrame, bound) -> DataFrame:
    if bound is None:
        return frame
    if isinstance(bound, int):
        return frame.where(F.col("dist") <= bound)
    return frame.join(bound, "qid").where(F.col("dist") <= F.col("bound")).drop("bound")


def _least(frame: DataFrame) -> DataFrame:
    return frame.groupBy("qid", "door").agg(F.min("dist").alias("dist"))


def graph_labels(venue: Venue, placed: DataFrame, bound=None, backward: bool = False, engine: str = "auto") -> DataFrame:
    """access_graph: best-first expansion over local legs, nothing precomputed."""
    seeds = entry_legs(venue, placed) if backward else exit_legs(venue, placed)
    legs = reverse(graph_legs(venue)) if backward else graph_legs(venue)
    return labels(seeds, legs, bound, engine)


def matrix_labels(venue: Venue, placed: DataFrame, bound=None, backward: bool = False, matrix: DataFrame | None = None) -> DataFrame:
    """door_matrix: a scan of the row of each door of the host partition up to what the bound leaves behind its leg.

    A common bound also cuts the scan itself: rows lie by distance, so pages behind it are not read. matrix: the rows to
    scan, if they are at hand.
    """
    matrix = (door_matrix(venue) if matrix is None else matrix).select("a_door", "b_door", "dist_mm")
    if isinstance(bound, int):
        matrix = matrix.where(F.col("dist_mm") <= bound)
    near, far = ("b_door", "a_door") if backward else ("a_door", "b_door")
    seeds = _within(entry_legs(venue, placed) if backward else exit_legs(venue, placed), bound)
    if bound is None:
        left = F.lit(True)
    elif isinstance(bound, int):
        left = F.col("dist_mm") <= F.lit(bound) - F.col("dist")
    else:
        seeds = seeds.join(bound, "qid")
        left = F.col("dist_mm") <= F.col("bound") - F.col("dist")
    rows = seeds.join(matrix, (F.col("door") == F.col(near)) & left)
    return _least(rows.select("qid", F.col(far).alias("door"), (F.col("dist") + F.col("dist_mm")).alias("dist")))


def layered_labels(venue: Venue, placed: DataFrame, bound=None, backward: bool = False, engine: str = "auto") -> DataFrame:
    """layered_rtree: expansion over the links of those cells that the R-tree cannot rule out.

    Without a bound nothing can be ruled out. Cells are ruled out for a whole batch: a leg stays if any query may need it;
    labels themselves are exact for each query, as its own bound holds.
    """
    seeds = entry_legs(venue, placed) if backward else exit_legs(venue, placed)
    legs = graph_legs(venue)
    if bound is not None and not backward:
        tree = build_rtree(venue)
        asked = placed if isinstance(bound, int) else placed.join(bound, "qid")
        cells = candidate_cells(venue, tree, asked, bound).select("part_id").distinct()
        stairs = venue.partitions.where("xmin is null and part_id <> 0").select("part_id")
        from floorwalk.operators.topology import door_legs

        kept = door_legs(venue).join(cells.union(stairs).distinct(), "part_id", "left_semi")
        legs = kept.groupBy("a_door", "b_door").agg(F.min("leg_mm").alias("leg_mm"))
    return labels(seeds, reverse(legs) if backward else legs, bound, engine)


def _tree_start(venue: Venue, tree: BorderTree, placed: DataFrame, backward: bool) -> DataFrame:
    """(qid, leaf, door, dist): seeds with the leaf of the host partition."""
    seeds = entry_legs(venue, placed) if backward else exit_legs(venue, placed)
    leaf = placed.select("qid", "part_id").join(tree.members, "part_id").select("qid", "leaf")
    return seeds.join(leaf, "qid")


def _homes(tree: BorderTree, placed: DataFrame) -> DataFrame:
    """(leaf): the leaves of the host partitions."""
    return placed.select("part_id").join(tree.members, "part_id").select("leaf").distinct()


def climb(venue: Venue, tree: BorderTree, placed: DataFrame, backward: bool = False, deep: bool = False) -> DataFrame:
    """(qid, node_id, door, dist): labels on the access doors of the host leaf and of all its ancestors.

    The plain tree goes up a level at a time through the inner cells; the deep one reads all levels at once.
    """
    start = _tree_start(venue, tree, placed, backward)
    if deep:
        cells = tree.home_cells("deep_in" if backward else "deep_out", _homes(tree, placed))
        rows = start.join(cells, (start["leaf"] == cells["leaf"]) & (start["door"] == cells["door_id"]))
        return rows.groupBy("qid", F.col("anc_node").alias("node_id"), F.col("access_door").alias("door")).agg(F.min(F.col("dist") + F.col("dist_mm")).alias("dist"))
    cells = tree.leaf_in if backward else tree.leaf_out
    rows = start.join(cells, (start["leaf"] == cells["leaf"]) & (start["door"] == cells["door_id"]))
    level = rows.groupBy("qid", start["leaf"].alias("node_id"), F.col("access_door").alias("door")).agg(F.min(F.col("dist") + F.col("dist_mm")).alias("dist"))
    level = materialize(level)
    out = level
    near, far = ("b_door", "a_door") if backward else ("a_door", "b_door")
    parents = tree.nodes.select("node_id", "parent_id")
    for _ in range(tree.height):
        up = level.join(parents, "node_id").where("parent_id is not null").select("qid", F.col("parent_id").alias("node_id"), "door", "dist")
        inner = tree.inner.select("node_id", F.col(near).alias("door"), F.col(far).alias("other"), "dist_mm")
        grown = up.join(inner, ["node_id", "door"]).join(tree.access.select("node_id", F.col("door_id").alias("other")), ["node_id", "other"])
        level = materialize(grown.groupBy("qid", "node_id", F.col("other").alias("door")).agg(F.min(F.col("dist") + F.col("dist_mm")).alias("dist")))
        out = out.union(level)
    return out


def tree_labels(venue: Venue, placed: DataFrame, bound=None, backward: bool = False, deep: bool = False, narrow=None, nodes: DataFrame | None = None) -> DataFrame:
    """border_tree(_deep): climb from the host leaf, then descend into every node whose access-door bound allows it.

    narrow(labels of open nodes) may give a bound (qid, bound) anew at each level. Without it the labels of all doors within
    the bound come back; with it the last bound instead, of which the answer is made (see knn.tree_bounds). nodes
    (node_id): the descent enters no others.
    """
    only, tree = nodes, build_border_tree(venue)
    near, far = ("b_door", "a_door") if backward else ("a_door", "b_door")
    inner = tree.inner.select("node_id", F.col(near).alias("door"), F.col(far).alias("other"), "dist_mm")
    up = materialize(_within(climb(venue, tree, placed, backward, deep), bound))
    home = placed.select("qid", "part_id").join(tree.members, "part_id").select("qid", F.col("leaf").alias("leaf"))
    line = home.join(tree.nodes.where("level = 0").select(F.col("node_id").alias("leaf"), "ancestors"), "leaf").select("qid", F.explode("ancestors").alias("node_id"))
    line = materialize(line)
    parents = tree.nodes.select("node_id", "parent_id", "level").where("parent_id is not null")
    kids = parents.select(F.col("node_id").alias("child"), F.col("parent_id").alias("node_id"))
    entered = kids if only is None else kids.join(only.withColumnRenamed("node_id", "child"), "child", "left_semi")
    kid_access = entered.join(tree.access.select(F.col("node_id").alias("child"), F.col("door_id").alias("other")), "child")
    # From an ancestor's child on the home branch over to its siblings.
    branch = up.join(kids, up["node_id"] == kids["child"]).select("qid", F.col("child").alias("from_child"), kids["node_id"], "door", "dist")
    crossed = branch.join(inner, ["node_id", "door"]).join(kid_access, ["node_id", "other"]).where("child <> from_child")
    nodes = _within(crossed.groupBy("qid", F.col("child").alias("node_id"), F.col("other").alias("door")).agg(F.min(F.col("dist") + F.col("dist_mm")).alias("dist")), bound)
    nodes = materialize(nodes.join(line, ["qid", "node_id"], "left_anti"))
    reached, leaves = nodes, tree.members.select(F.col("leaf").alias("node_id")).distinct()
    if narrow is not None:
        # Siblings of the home branch at all levels cover the venue but for the home leaf; a node gives way to its children.
        cover = materialize(nodes)
        while True:
            limit = materialize(narrow(cover))
            live = cover.join(limit, "qid", "left").where(F.col("bound").isNull() | (F.col("dist") <= F.col("bound"))).drop("bound")
            low = live.join(leaves, "node_id", "left_semi")
            inside = materialize(live.join(leaves, "node_id", "left_anti"))
            if inside.isEmpty():
                return limit
            down = inside.join(inner, ["node_id", "door"]).join(kid_access, ["node_id", "other"])
            down = down.groupBy("qid", F.col("child").alias("node_id"), F.col("other").alias("door")).agg(F.min(F.col("dist") + F.col("dist_mm")).alias("dist"))
            cover = materialize(low.unionByName(down.select(*low.columns)))
    for _ in range(tree.height):
        down = nodes.join(inner, ["node_id", "door"]).join(kid_access, ["node_id", "other"])
        nodes = materialize(_within(down.groupBy("qid", F.col("child").alias("node_id"), F.col("other").alias("door")).agg(F.min(F.col("dist") + F.col("dist_mm")).alias("dist")), bound))
        if nodes.isEmpty():
            break
        reached = reached.union(nodes)
    cells = tree.leaf_out if backward else tree.leaf_in
    at_leaf = reached.join(cells, (reached["node_id"] == cells["leaf"]) & (reached["door"] == cells["access_door"])).select("qid", F.col("door_id").alias("door"), (F.col("dist") + F.col("dist_mm")).alias("dist"))
    start = _tree_start(venue, tree, placed, backward)
    pairs = tree.home_cells("leaf_pairs", _homes(tree, placed)).select("leaf", F.col(near).alias("door"), F.col(far).alias("other"), "dist_mm")
    own = start.join(pairs, ["leaf", "door"]).select("qid", F.col("other").alias("door"), (F.col("dist") + F.col("dist_mm")).alias("dist"))
    return _least(_within(at_leaf.union(own), bound))


def point_labels(method: str, venue: Venue, placed: DataFrame, bound=None, backward: bool = False) -> DataFrame:
    if method == "ag":
        return graph_labels(venue, placed, bound, backward)
    if method == "dm":
        return matrix_labels(venue, placed, bound, backward)
    if method == "lr":
        return layered_labels(venue, placed, bound, backward)
    return tree_labels(venue, placed, bound, backward, deep=method == "btd")


def cells_entered(venue: Venue, found: DataFrame) -> DataFrame:
    """(qid, door, dist) -> + part_id: partitions that each labelled door enters."""
    return found.join(door_enters(venue.moves).where("part_id <> 0"), found["door"] == F.col("door_id")).select("qid", "door", "dist", "part_id")


def cells_left(venue: Venue, found: DataFrame) -> DataFrame:
    return found.join(door_leaves(venue.moves).where("part_id <> 0"), found["door"] == F.col("door_id")).select("qid", "door", "dist", "part_id")
