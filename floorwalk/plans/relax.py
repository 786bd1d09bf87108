"""Distance kernels: relational relaxation, min-plus doubling, and a compiled local search over Arrow batches."""

from __future__ import annotations

import heapq
from collections.abc import Callable, Iterable, Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from floorwalk.sources.scratch import discard, materialize

LOCAL_LEGS, LOCAL_DOORS = 400_000, 20_000
ROUND_LEGS = 2_000_000  # legs that go to tasks for searches with one row of labels a query
BLOCK_CELLS = 4_000_000
CORE_DOORS = 128  # doors that are left for doubling
DEAL_DOORS, TASK_DOORS = 256, 2048  # doors that lie together and share a part of the ladder, and doors a task
FAR = np.int64(1) << 60


def reverse(legs: DataFrame) -> DataFrame:
    """Legs against the direction of movement: distances *to* a door are distances from it over these."""
    return legs.select(F.col("b_door").alias("a_door"), F.col("a_door").alias("b_door"), "leg_mm")


def relax(seeds: DataFrame, legs: DataFrame, bound: DataFrame | int | None = None, with_path: bool = False, max_rounds: int = 10_000) -> DataFrame:
    """Best labels (qid, door, dist [, path]) over seeds (qid, door, dist) and legs (a_door, b_door, leg_mm).

    One plan per round: the frontier meets the legs, candidates above the bound go, the least label per (qid, door)
    stays if it improves what is known. Each round is written out, so plans stay short and lost executors cost one round. The
    driver sees only whether the frontier is empty. bound is a number or a table (qid, bound).
    """
    def capped(frame: DataFrame) -> DataFrame:
        if bound is None:
            return frame
        if isinstance(bound, int):
            return frame.where(F.col("dist") <= bound)
        return frame.join(bound, "qid").where(F.col("dist") <= F.col("bound")).drop("bound")

    label = F.struct("dist", "path") if with_path else F.struct("dist")
    names = ("dist", "path") if with_path else ("dist",)

    def least(frame: DataFrame) -> DataFrame:
        if not with_path:
            return frame.groupBy("qid", "door").agg(F.min("dist").alias("dist"))
        low = frame.groupBy("qid", "door").agg(F.min(label).alias("low"))
        return low.select("qid", "door", *[F.col("low")[n].alias(n) for n in names])

    start = seeds.withColumn("path", F.array("door")) if with_path else seeds
    first = best = frontier = materialize(least(capped(start.select("qid", "door", *names))))
    for _ in range(max_rounds):
        step = frontier.join(legs, frontier["door"] == legs["a_door"])
        grown = [(F.col("dist") + F.col("leg_mm")).alias("dist")] + ([F.array_append("path", F.col("b_door")).alias("path")] if with_path else [])
        candidates = least(capped(step.select("qid", F.col("b_door").alias("door"), *grown)))
        known = best.select("qid", "door", label.alias("known"))
        last, frontier = frontier, materialize(candidates.join(known, ["qid", "door"], "left").where(F.col("known").isNull() | (label < F.col("known"))).select("qid", "door", *names))
        if last is not first:
            discard(last)
        if frontier.isEmpty():
            return best
        last, best = best, materialize(least(best.union(frontier)))
        if last is not first:
            discard(last)
    raise RuntimeError("relaxation did not settle")


def square(matrix: DataFrame) -> DataFrame:
    """One min-plus doubling of (a_door, b_door, dist_mm)."""
    left = matrix.select("a_door", F.col("b_door").alias("mid"), F.col("dist_mm").alias("d1"))
    right = matrix.select(F.col("a_door").alias("mid"), "b_door", F.col("dist_mm").alias("d2"))
    both = left.join(right, "mid").groupBy("a_door", "b_door").agg(F.min(F.col("d1") + F.col("d2")).alias("dist_mm"))
    return matrix.union(both).groupBy("a_door", "b_door").agg(F.min("dist_mm").alias("dist_mm"))


def is_local(legs: DataFrame) -> bool:
    """Whether a leg table is of a size that may be sent to every task."""
    rows, doors = legs.agg(F.count("*"), F.count_distinct("a_door")).first()
    return rows <= LOCAL_LEGS and doors <= LOCAL_DOORS


def local_search(seeds: DataFrame, legs: DataFrame, bound: DataFrame | int | None = None) -> DataFrame:
    """The labels of relax() from a compiled search: queries are dealt over tasks, legs (of a checked size) go to each.

    A block of queries is one matrix of labels; a round relaxes all legs of all of them at once.
    """
    table = legs.select("a_door", "b_door", "leg_mm").toPandas()
    nodes = np.unique(np.concatenate([table["a_door"].to_numpy(), table["b_door"].to_numpy()])).astype(np.int64)
    order = np.argsort(table["b_door"].to_numpy(), kind="stable")
    source, target, length = (table[c].to_numpy()[order] for c in ("a_door", "b_door", "leg_mm"))
    source, target = np.searchsorted(nodes, source), np.searchsorted(nodes, target)
    first = np.flatnonzero(np.diff(target, prepend=-1))
    hit = target[first]
    fixed = bound if isinstance(bound, int) else None
    rows = seeds.select("qid", "door", "dist")
    rows = rows.join(bound, "qid") if isinstance(bound, DataFrame) else rows.withColumn("bound", F.lit(int(FAR) if fixed is None else fixed).cast("long"))

    def search(qid: np.ndarray, door: np.ndarray, dist: np.ndarray, limit: np.ndarray) -> Iterator[pd.DataFrame]:
        keys, row = np.unique(qid, return_inverse=True)
        step = max(1, BLOCK_CELLS // max(1, len(source)))
        for low in range(0, len(keys), step):
            pick = (row >= low) & (row < low + step)
            n = min(step, len(keys) - low)
            cap = np.full(n, FAR)
            np.minimum.at(cap, row[pick] - low, limit[pick])
            label = np.full((n, len(nodes)), FAR)
            at = np.minimum(np.searchsorted(nodes, door[pick]), len(nodes) - 1)
            known = nodes[at] == door[pick]
            np.minimum.at(label, (row[pick][known] - low, at[known]), dist[pick][known])
            label[label > cap[:, None]] = FAR
            live = np.arange(n)
            while len(live) and len(first):
                old = label[live]
                new = np.minimum.reduceat(old[:, source] + length, first, axis=1)
                new[new > cap[live][:, None]] = FAR
                merged = old.copy()
                merged[:, hit] = np.minimum(old[:, hit], new)
                changed = (merged != old).any(axis=1)
                label[live] = merged
                live = live[changed]
            r, c = np.nonzero(label < FAR)
            yield pd.DataFrame({"qid": keys[low + r], "door": nodes[c], "dist": label[r, c]})
            lone = np.flatnonzero(~known & (dist[pick] <= cap[row[pick] - low]))  # doors without any leg keep their seed
            if len(lone):
                alone = pd.DataFrame({"qid": qid[pick][lone], "door": door[pick][lone], "dist": dist[pick][lone]})
                yield alone.groupby(["qid", "door"], as_index=False)["dist"].min()

    def run(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        whole = list(frames)
        if whole and sum(map(len, whole)):
            data = pd.concat(whole)
            yield from search(*(data[c].to_numpy(dtype=np.int64) for c in ("qid", "door", "dist", "bound")))

    if not len(nodes):
        return rows.where("dist <= bound").groupBy("qid", "door").agg(F.min("dist").alias("dist"))
    return rows.repartition("qid").mapInPandas(run, "qid long, door long, dist long")


class _Legs:
    """A leg table of a checked size as arrays over numbered doors, sorted by the door that a leg starts from."""

    def __init__(self, table: pd.DataFrame, more_doors: np.ndarray) -> None:
        a, b, length = (table[c].to_numpy(dtype=np.int64) for c in ("a_door", "b_door", "leg_mm"))
        self.nodes = np.unique(np.concatenate([a, b, more_doors]))
        source, target = np.searchsorted(self.nodes, a), np.searchsorted(self.nodes, b)
        self.order = order = np.lexsort((target, source))  # rows of the table
        self.source, self.target, self.length = source[order], target[order], length[order]
        self.out = np.flatnonzero(np.diff(self.source, prepend=-1))
        self.begin = np.searchsorted(self.source, np.arange(len(self.nodes) + 1))
        self.back = np.argsort(self.target, kind="stable")
        self.into = np.flatnonzero(np.diff(self.target[self.back], prepend=-1))

    def settle(self, label: np.ndarray, limit, backward: bool = False) -> np.ndarray:
        """Least labels (queries x doors) over the legs, or against them; limit(new labels, queries) names what may stay."""
        if not len(self.source):
            return label
        if backward:
            near, far, length, first = self.target, self.source, self.length, self.out
        else:
            near, far, length, first = self.source[self.back], self.target[self.back], self.length[self.back], self.into
        hit, live = far[first], np.arange(len(label))
        while len(live):
            old = label[live]
            new = np.minimum.reduceat(old[:, near] + length, first, axis=1)
            merged = old.copy()
            merged[:, hit] = np.minimum(old[:, hit], new)
            merged[~limit(merged, live)] = FAR
            merged = np.minimum(merged, old)
            changed = (merged != old).any(axis=1)
            label[live] = merged
            live = live[changed]
        return label

    def hops(self, tight: np.ndarray, stops: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """tight (queries x legs), stops (queries x doors) -> first and stride hop of every door as numbers, or len(nodes).

        A step of length 0 counts as a first hop only if it arrives or if a step of positive length follows it.
        """
        n, none = len(tight), len(self.nodes)
        first, stride = np.full((n, none + 1), none), np.full((n, none + 1), none)
        if not len(self.source):
            return first, stride
        from_door = self.source[self.out]
        moves = np.where(tight & (self.length > 0), self.target, none)
        stride[:, from_door] = np.minimum.reduceat(moves, self.out, axis=1)
        still = np.flatnonzero(self.length == 0)
        first[:] = stride
        for leg in still.tolist():  # few: staircase ends that share a place
            a, b = self.source[leg], self.target[leg]
            use = tight[:, leg] & (stops[:, b] | (stride[:, b] < none))
            first[use, a] = np.minimum(first[use, a], b)
        return first, stride


    def legs_of(self, a: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Legs out of doors a: the place of the door in a, and the leg."""
        count = self.begin[a + 1] - self.begin[a]
        pair = np.repeat(np.arange(len(a)), count)
        return pair, np.repeat(self.begin[a] - (np.cumsum(count) - count), count) + np.arange(len(pair))

    def asked_by_hops(self, a: np.ndarray) -> np.ndarray:
        """All doors whose distances pair_hops() reads for start doors a."""
        legs = self.legs_of(a)[1]
        still = self.target[legs[self.length[legs] == 0]]
        return np.unique(np.concatenate([a, self.target[legs], self.target[self.legs_of(np.unique(still))[1]]]))

    def tight(self, rest: np.ndarray, row: np.ndarray, a: np.ndarray, column: np.ndarray | None = None) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """Legs out of doors a that lie on a shortest way to the target of a row of rest: pair, next door and length of each.

        column: where rest holds each door, if it does not hold all.
        """
        pair, leg = self.legs_of(a)
        here, there = (a, self.target[leg]) if column is None else (column[a], column[self.target[leg]])
        then = rest[row[pair], there]
        on = (then < FAR) & (rest[row, here][pair] == self.length[leg] + then)
        return pair[on], self.target[leg[on]], self.length[leg[on]]

    def pair_hops(self, rest: np.ndarray, row: np.ndarray, a: np.ndarray, b: np.ndarray, column: np.ndarray | None = None) -> tuple[np.ndarray, np.ndarray]:
        """hops() for pairs of doors alone: row names the row of rest that belongs to b."""
        none = len(self.nodes)
        pair, then, length = self.tight(rest, row, a, column)
        stride, go = np.full(len(a), none), length > 0
        np.minimum.at(stride, pair[go], then[go])
        first, pair, then = stride.copy(), pair[~go], then[~go]
        onward, _, length = self.tight(rest, row[pair], then, column)
        use = then == b[pair]
        use[onward[length > 0]] = True
        np.minimum.at(first, pair[use], then[use])
        return first, stride


class _Ladder:
    """The graph with its doors taken out one by one, fewest neighbours first; legs that bridge a door taken out are added.

    What remains of a shortest path then climbs and descends once: labels settle in one pass over the doors in that order and
    one against it, however many legs the path has. Made once, for searches from many doors.
    """

    def __init__(self, legs: _Legs, keep: int = 0) -> None:
        """keep: so many doors stay as a core, with the legs among them that bridge all others."""
        self.size = left = len(legs.nodes)
        out: list[dict[int, int]] = [{} for _ in range(self.size)]
        into: list[dict[int, int]] = [{} for _ in range(self.size)]
        for a, b, length in zip(legs.source.tolist(), legs.target.tolist(), legs.length.tolist(), strict=True):
            if a != b and length < out[a].get(b, FAR):
                out[a][b] = into[b][a] = length
        queue = [(len(out[v]) + len(into[v]), v) for v in range(self.size)]
        heapq.heapify(queue)
        gone = np.zeros(self.size, dtype=bool)
        doors, counts, flat, ups, downs = [], [], [], [], []
        while queue and left > keep:
            degree, v = heapq.heappop(queue)
            if gone[v]:
                continue
            if degree != len(out[v]) + len(into[v]):
                heapq.heappush(queue, (len(out[v]) + len(into[v]), v))
                continue
            gone[v] = True
            left -= 1
            above = sorted(out[v].keys() | into[v].keys())
            for a, first in into[v].items():
                ahead = out[a]
                for b, then in out[v].items():
                    if a != b and first + then < ahead.get(b, FAR):
                        ahead[b] = into[b][a] = first + then
            for u in above:
                out[u].pop(v, None)
                into[u].pop(v, None)
                heapq.heappush(queue, (len(out[u]) + len(into[u]), u))
            if above:
                doors.append(v)
                counts.append(len(above))
                flat += above
                ups += [out[v].get(u, FAR) for u in above]
                downs += [into[v].get(u, FAR) for u in above]
        self.core = np.flatnonzero(~gone)
        self.core_legs = [(v, u, length) for v in self.core.tolist() for u, length in out[v].items()]
        # A step is a door, its doors above, and the legs to them and from them; few flat arrays travel to tasks quickly.
        self.door, self.begin = np.array(doors, dtype=np.int64), np.concatenate([[0], np.cumsum(np.array(counts, dtype=np.int64))]).astype(np.int64)
        self.above, self.up, self.down = (np.array(x, dtype=np.int64) for x in (flat, ups, downs))
        self.step = np.full(self.size, len(doors))
        self.step[self.door] = np.arange(len(doors))
        # A door's parent is the first of the doors above it to be taken out.
        self.parent = np.full(self.size, -1)
        if doors:
            turn = self.step[self.above] * self.size + self.above
            self.parent[self.door] = np.minimum.reduceat(turn, self.begin[:-1]) % self.size

    def places(self) -> np.ndarray:
        """A number for each door by which doors with nearly the same doors above lie together: a walk of the tree of parents."""
        weight, place = np.ones(self.size, dtype=np.int64), np.zeros(self.size, dtype=np.int64)
        for v in self.door.tolist():
            weight[self.parent[v]] += weight[v]
        roots = np.flatnonzero(self.parent < 0)
        place[roots] = np.cumsum(weight[roots]) - weight[roots]
        free = place + 1
        for v in self.door[::-1].tolist():
            up = self.parent[v]
            place[v] = free[up]
            free[up] += weight[v]
            free[v] = place[v] + 1
        return place

    def part(self, doors: np.ndarray) -> tuple[np.ndarray, list[tuple[int, np.ndarray, np.ndarray, np.ndarray]]]:
        """The given doors and all above them, and the steps among these, for settle_part(); the doors as their columns there."""
        marked = np.zeros(self.size, dtype=bool)
        while len(doors):
            marked[doors] = True
            steps = self.step[doors]
            steps = steps[steps < len(self.door)]
            size = self.begin[steps + 1] - self.begin[steps]
            doors = np.unique(self.above[np.repeat(self.begin[steps] - (np.cumsum(size) - size), size) + np.arange(int(size.sum()))])
            doors = doors[~marked[doors]]
        held = np.flatnonzero(marked)
        column = np.full(self.size, -1)
        column[held] = np.arange(len(held))
        steps = np.sort(self.step[held])
        rows = []
        for i in steps[steps < len(self.door)].tolist():
            legs = slice(self.begin[i], self.begin[i + 1])
            rows.append((column[self.door[i]], column[self.above[legs]], self.up[legs, None], self.down[legs, None]))
        return column, rows

    def settle_part(self, ends: np.ndarray, column: np.ndarray, steps: list[tuple[int, np.ndarray, np.ndarray, np.ndarray]]) -> np.ndarray:
        """Distances (ends x doors of the part) from the doors of a part to ends of it, as settle() backward gives them."""
        rows = np.full((int(column.max()) + 1, len(ends)), FAR)
        rows[column[ends], np.arange(len(ends))] = 0
        for v, above, _, down in steps:
            rows[above] = np.minimum(rows[above], rows[v] + down)
        for v, above, up, _ in reversed(steps):
            np.minimum(rows[v], (rows[above] + up).min(axis=0), out=rows[v])
        return rows.T

    def settle(self, label: np.ndarray, backward: bool = False, core: np.ndarray | None = None) -> np.ndarray:
        """Least labels (queries x doors) over all legs, or against them; core: distances among the doors that stay."""
        rows = np.ascontiguousarray(label.T)
        climb, descend = (self.down, self.up) if backward else (self.up, self.down)
        steps = list(zip(self.door.tolist(), self.begin[:-1].tolist(), self.begin[1:].tolist(), strict=True))
        for v, low, high in steps:
            above = self.above[low:high]
            rows[above] = np.minimum(rows[above], rows[v] + climb[low:high, None])
        if len(self.core):
            held, core = rows[self.core], core.T if backward else core
            rows[self.core] = np.stack([(held + core[:, k, None]).min(axis=0) for k in range(len(self.core))])
        for v, low, high in reversed(steps):
            np.minimum(rows[v], (rows[self.above[low:high]] + descend[low:high, None]).min(axis=0), out=rows[v])
        return np.ascontiguousarray(rows.T)


def rounds(graph: _Legs, label: np.ndarray, passable: Callable[[np.ndarray, np.ndarray], np.ndarray] | None = None) -> np.ndarray:
    """The rounds of relax() over labels (queries x doors): legs out of doors that improved in the last round only.

    passable(doors, labels) names the new labels that may stand; all labels of a round come from those of the round before.
    """
    n, flat = len(graph.nodes), label.ravel()
    turn, frontier = np.zeros(flat.size, dtype=np.int32), np.flatnonzero(flat < FAR)
    while len(frontier):
        door = frontier % n
        count = graph.begin[door + 1] - graph.begin[door]
        leg = np.repeat(graph.begin[door] - (np.cumsum(count) - count), count) + np.arange(int(count.sum()))
        key = np.repeat(frontier - door, count) + graph.target[leg]
        dist = np.repeat(flat[frontier], count) + graph.length[leg]
        better = dist < flat[key]
        if passable is not None:
            better[better] = passable(key[better] % n, dist[better])
        key, dist = key[better], dist[better]
        np.minimum.at(flat, key, dist)
        turn[key] = np.arange(len(key), dtype=np.int32)
        frontier = key[turn[key] == np.arange(len(key))]
    return flat.reshape(label.shape)


def _dealt(rows: DataFrame) -> DataFrame:
    """Small rows, one a door, that stand for much work, over all tasks.

    Dealt in turn: Spark leaves out a repartition by the key that the rows are grouped by already if the number of
    partitions is the same, and then coalesces the grouped rows into one task for their few bytes.
    """
    return rows.repartition(3 * rows.sparkSession.sparkContext.defaultParallelism)


def _door_blocks(frames: Iterable[pa.RecordBatch], legs: _Legs) -> Iterator[tuple[np.ndarray, np.ndarray]]:
    """The task's distinct doors a block at a time, with labels that are 0 at the door itself."""
    doors = [batch.column(0).to_numpy() for batch in frames if batch.num_rows]
    keys = np.unique(np.concatenate(doors)) if doors else np.zeros(0, dtype=np.int64)
    step = max(1, BLOCK_CELLS // max(1, len(legs.nodes)))
    for low in range(0, len(keys), step):
        part = keys[low : low + step]
        label = np.full((len(part), len(legs.nodes)), FAR)
        label[np.arange(len(part)), np.searchsorted(legs.nodes, part)] = 0
        yield part, label


def leg_arrays(doors: DataFrame, legs: DataFrame) -> _Legs:
    """The legs as arrays over their doors and the given ones (door_id)."""
    table = legs.select("a_door", "b_door", "leg_mm").toPandas()
    return _Legs(table, np.array([r[0] for r in doors.distinct().collect()], dtype=np.int64))  # as many as the legs' doors, of a checked size


def local_graph(doors: DataFrame, legs: DataFrame) -> tuple[_Legs, _Ladder]:
    """What searches from many doors (door_id) run on; worth keeping when several follow."""
    graph = leg_arrays(doors, legs)
    return graph, _Ladder(graph)


def doubled(matrix: DataFrame, max_rounds: int = 64) -> DataFrame:
    """(a_door, b_door, dist_mm), closed under min-plus doubling; each doubling is written out."""
    matrix, before = materialize(matrix.groupBy("a_door", "b_door").agg(F.min("dist_mm").alias("dist_mm"))), None
    for _ in range(max_rounds):
        state = matrix.agg(F.count("*"), F.sum("dist_mm")).first()
        if state == before:
            return matrix
        before, matrix = state, materialize(square(matrix))
    raise RuntimeError("doubling did not settle")


def local_pairs(sources: DataFrame, legs: DataFrame, by: str = "ladder") -> DataFrame:
    """sources (door_id) -> (a_door, b_door, dist_mm): from each source to every door, one job over sources.

    A source's rows come together, by distance. by: the ladder; rounds of relaxation, each source's within its task; or the
    ladder down to a core of doors, whose distances come from min-plus doubling.
    """
    if by == "doubling":
        graph = leg_arrays(sources.select("door_id"), legs)
        ladder, spark = _Ladder(graph, CORE_DOORS), legs.sparkSession
        ends = ladder.core_legs + [(v, v, 0) for v in ladder.core.tolist()]
        core = np.full((len(ladder.core),) * 2, FAR)
        if ends:
            rows = doubled(spark.createDataFrame(ends, "a_door long, b_door long, dist_mm long")).toPandas()  # the square of CORE_DOORS at most
            core[tuple(np.searchsorted(ladder.core, rows[c].to_numpy()) for c in ("a_door", "b_door"))] = rows["dist_mm"].to_numpy()
        settle = lambda label: ladder.settle(label, core=core)
    elif by == "rounds":
        graph = leg_arrays(sources.select("door_id"), legs)
        settle = lambda label: rounds(graph, label)
    else:
        graph, ladder = local_graph(sources.select("door_id"), legs)
        settle = ladder.settle

    def run(frames: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for keys, label in _door_blocks(frames, graph):
            label = settle(label)
            for low in range(0, len(keys), 32):
                part = label[low : low + 32]
                order = np.argsort(part, axis=1, kind="stable")
                dist = np.take_along_axis(part, order, axis=1)
                r, c = np.nonzero(dist < FAR)
                yield pa.RecordBatch.from_pydict({"a_door": pa.array(keys[low + r]), "b_door": pa.array(graph.nodes[order[r, c]]), "dist_mm": pa.array(dist[r, c])})

    return _dealt(sources.select("door_id").distinct()).mapInArrow(run, "a_door long, b_door long, dist_mm long")


def _blocks(qid: np.ndarray, legs: _Legs) -> Iterator[tuple[np.ndarray, np.ndarray]]:
    """Queries a block at a time: their ids, and which rows belong to them."""
    keys, row = np.unique(qid, return_inverse=True)
    step = max(1, BLOCK_CELLS // max(1, len(legs.source), len(legs.nodes)))
    for low in range(0, len(keys), step):
        yield keys[low : low + step], np.flatnonzero((row >= low) & (row < low + step))


def local_routes(starts: DataFrame, ends: DataFrame, legs: DataFrame, with_path: bool = True, spots: DataFrame | None = None, targets: DataFrame | None = None) -> DataFrame:
    """starts (qid, door, dist), ends (qid, door, rest) -> (qid, dist [, path]): the least door way, canonical path.

    One job: queries are dealt over tasks, legs (of a checked size) go to each. Labels above the best complete way found so
    far are dropped as the search goes on. With spots (door_id, floor, x_mm, y_mm) and targets (qid, floor, x_mm, y_mm) the
    straight line to a target on the door's own floor bounds the rest from below and rules doors out sooner.
    """
    table = legs.select("a_door", "b_door", "leg_mm").toPandas()
    place = spots.select("door_id", "floor", "x_mm", "y_mm").toPandas().set_index("door_id") if spots is not None else None
    none = F.lit(None).cast("long")
    rows = starts.select("qid", F.lit(0).alias("kind"), "door", "dist", none.alias("x"), none.alias("y"))
    rows = rows.union(ends.select("qid", F.lit(1), "door", "rest", none, none))
    if targets is not None:
        rows = rows.union(targets.select("qid", F.lit(2), F.col("floor").cast("long"), F.lit(0).cast("long"), "x_mm", "y_mm"))

    def answer(data: pd.DataFrame) -> Iterator[pd.DataFrame]:
        kind = data["kind"].to_numpy()
        graph = _Legs(table, data["door"].to_numpy(dtype=np.int64)[kind < 2])
        for keys, pick in _blocks(data["qid"].to_numpy(), graph):
            part, what, n = data.iloc[pick], kind[pick], len(keys)
            row = np.searchsorted(keys, part["qid"].to_numpy())
            at = np.searchsorted(graph.nodes, part["door"].to_numpy(dtype=np.int64))
            value = part["dist"].to_numpy(dtype=np.int64)
            begin, finish = np.full((n, len(graph.nodes)), FAR), np.full((n, len(graph.nodes)), FAR)
            for kind_no, matrix in ((0, begin), (1, finish)):
                use = what == kind_no
                np.minimum.at(matrix, (row[use], at[use]), value[use])
            ahead = np.zeros((n, len(graph.nodes)), dtype=np.int64)
            if place is not None and (what == 2).any():
                known = place.reindex(graph.nodes)
                floor, x, y = (known[c].to_numpy(dtype=float) for c in ("floor", "x_mm", "y_mm"))
                for r, f, tx, ty in zip(row[what == 2], part["door"].to_numpy()[what == 2], part["x"].to_numpy(dtype=float)[what == 2], part["y"].to_numpy(dtype=float)[what == 2], strict=True):
                    ahead[r] = np.where(floor == f, np.floor(np.hypot(x - tx, y - ty)), 0)
            best = (begin + finish).min(axis=1)

            def forward(label, live):
                best[live] = np.minimum(best[live], (label + finish[live]).min(axis=1))
                return label + ahead[live] <= best[live][:, None]

            label = graph.settle(begin.copy(), forward)
            best = np.minimum(best, (label + finish).min(axis=1))
            found = np.flatnonzero(best < FAR)
            if not len(found):
                continue
            if not with_path:
                yield pd.DataFrame({"qid": keys[found], "dist": best[found]})
                continue
            rest = graph.settle(finish.copy(), lambda back, live: label[live] + back <= best[live][:, None], backward=True)
            on = (label + rest == best[:, None]) & (label < FAR)
            tight = on[:, graph.source] & on[:, graph.target] & (label[:, graph.source] + graph.length == label[:, graph.target])
            stops = on & (label + finish == best[:, None])
            first, stride = graph.hops(tight, stops)
            opens = on & (begin == label)
            paths: list[list[int]] = [[] for _ in range(n)]
            live = found
            here = opens[live].argmax(axis=1)
            still = np.zeros(len(live), dtype=bool)
            while len(live):
                for q, door in zip(live.tolist(), graph.nodes[here].tolist(), strict=True):
                    paths[q].append(door)
                go = ~stops[live, here]
                live, here, still = live[go], here[go], still[go]
                then = np.where(still, stride[live, here], first[live, here])
                still = label[live, then] == label[live, here]
                here = then
            yield pd.DataFrame({"qid": keys[found], "dist": best[found], "path": [paths[q] for q in found.tolist()]})

    def run(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        whole = list(frames)
        if whole and sum(map(len, whole)):
            yield from answer(pd.concat(whole))

    return rows.repartition("qid").mapInPandas(run, "qid long, dist long" + (", path array<long>" if with_path else ""))


def round_ways(starts: DataFrame, ends: DataFrame, graph: _Legs, passable: Callable[[np.ndarray, np.ndarray], np.ndarray] | None = None) -> DataFrame:
    """starts (qid, door, dist), ends (qid, door, rest) -> (qid, dist): the least whole way by rounds(), one query at a time."""
    rows = starts.select("qid", F.lit(0).alias("kind"), "door", "dist").union(ends.select("qid", F.lit(1), "door", "rest"))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        whole = pa.Table.from_batches([b for b in batches if b.num_rows] or [pa.RecordBatch.from_pylist([], pa.schema([(c, pa.int64()) for c in ("qid", "kind", "door", "dist")]))])
        qid, kind, door, dist = (whole[c].to_numpy().astype(np.int64) for c in ("qid", "kind", "door", "dist"))
        at = np.searchsorted(graph.nodes, door)
        for q in np.unique(qid):
            label = np.full((1, len(graph.nodes)), FAR)
            first, last = np.flatnonzero((qid == q) & (kind == 0)), np.flatnonzero((qid == q) & (kind == 1))
            np.minimum.at(label[0], at[first], dist[first])
            found = rounds(graph, label, passable)[0, at[last]] + dist[last]
            if len(found) and found.min() < FAR:
                yield pa.RecordBatch.from_pydict({"qid": pa.array([q]), "dist": pa.array([found.min()])})

    tasks = rows.sparkSession.sparkContext.defaultParallelism
    return rows.repartition(tasks, "qid").mapInArrow(run, "qid long, dist long")


class _Cover:
    """Shortest ways that gather words: states are a door and the set of words seen so far, as a mask."""

    def __init__(self, graph: _Legs, seen: np.ndarray, full: int) -> None:
        self.graph, self.seen, self.full, self.n = graph, seen[graph.order], full, len(graph.nodes)
        self.into = np.searchsorted(graph.target[graph.back], np.arange(self.n + 1))
        self.step = max(1, 4 * int(graph.length.mean())) if len(graph.length) else 1

    def search(self, door: np.ndarray, dist: np.ndarray, mask: int, last: np.ndarray, rest: np.ndarray, ends_in: int, k: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """Labels of all states, and the complete states and totals that hold the k best routes with all their ties.

        Labels settle in windows of distance: a window's rounds end before the next begins, so labels below its limit are final,
        and the search ends once k different routes lie below it. Pairs of a last door and a total stand for different routes.
        """
        graph, n = self.graph, self.n
        label = np.full((self.full + 1) * n, FAR)
        np.minimum.at(label, mask * n + door, dist)
        masks = np.array([m for m in range(self.full + 1) if m | ends_in == self.full], dtype=np.int64)
        goal, ahead = (masks[:, None] * n + last).ravel(), np.tile(rest, len(masks))
        waiting = np.flatnonzero(label < FAR)
        limit = np.int64(0)
        while True:
            near = label[waiting] < limit
            if not near.any():  # the window is settled
                total = label[goal] + ahead
                known = label[goal] < (limit if len(waiting) else FAR)
                routes = np.unique(np.stack([total[known], goal[known] % n]), axis=1)[0]
                if not len(waiting) or (len(routes) >= k and routes[k - 1] < limit):
                    known &= total <= (routes[k - 1] if len(routes) >= k else FAR)
                    return label, goal[known], total[known]
                limit = label[waiting].min() + self.step
                continue
            at, waiting = waiting[near], waiting[~near]
            here = at % n
            count = graph.begin[here + 1] - graph.begin[here]
            leg = np.repeat(graph.begin[here] - (np.cumsum(count) - count), count) + np.arange(int(count.sum()))
            key = (np.repeat(at // n, count) | self.seen[leg]) * n + graph.target[leg]
            far = np.repeat(label[at], count) + graph.length[leg]
            better = far < label[key]
            key = key[better]
            np.minimum.at(label, key, far[better])
            waiting = np.unique(np.concatenate([waiting, key]))

    def paths(self, label: np.ndarray, first: dict[int, int], goals: list[int]) -> dict[int, tuple[int, ...]]:
        """The least door path of each goal state among the shortest; first: states that the way may begin in, with their labels."""
        graph, n = self.graph, self.n
        before: dict[int, list[tuple[int, int]]] = {}
        trail = list(goals)
        while trail:
            state = trail.pop()
            if state in before:
                continue
            mask, door = divmod(state, n)
            legs = graph.back[self.into[door] : self.into[door + 1]]
            seen, a, length = self.seen[legs], graph.source[legs], graph.length[legs]
            before[state] = [
                (int(m * n + a[i]), int(length[i])) for m in range(self.full + 1) for i in np.flatnonzero(((seen | m) == mask) & (label[m * n + a] + length == label[state]))
            ]
            trail += [s for s, _ in before[state]]
        found: dict[int, tuple[int, ...]] = {}
        by_label: dict[int, list[int]] = {}
        for state in before:
            by_label.setdefault(int(label[state]), []).append(state)
        for dist in sorted(by_label):
            for state in by_label[dist]:
                own = (int(graph.nodes[state % n]),)
                ways = [found[s] + own for s, length in before[state] if length > 0]
                ways += [own] if first.get(state) == dist else []
                if ways:
                    found[state] = min(ways)
            still = [(s, state) for state in by_label[dist] for s, length in before[state] if length == 0]
            changed = bool(still)
            while changed:  # steps of length 0, few: staircase ends that share a place
                changed, old = False, dict((s, found[s]) for s, _ in still if s in found)
                for s, state in still:
                    if s in old:
                        way = old[s] + (int(graph.nodes[state % n]),)
                        if state not in found or way < found[state]:
                            found[state], changed = way, True
        return found


def cover_ways(starts: DataFrame, ends: DataFrame, legs: DataFrame, full: int, k: int) -> DataFrame:
    """starts (qid, door, dist, mask), ends (qid, door, rest, mask), legs (a_door, b_door, leg_mm, seen) -> (qid, total_mm, path).

    The complete states of the k shortest routes of each query, with all that tie with the last; a query is searched within one
    task, and legs (of a checked size) go to each. full is the mask of all words; a start's mask is what its partition holds,
    an end's mask what is seen behind the last door.
    """
    table = legs.select("a_door", "b_door", "leg_mm", "seen").toPandas()
    cover = _Cover(_Legs(table, np.zeros(0, dtype=np.int64)), table["seen"].to_numpy(dtype=np.int64), full)
    rows = starts.select("qid", F.lit(0).alias("kind"), "door", "dist", "mask").union(ends.select("qid", F.lit(1), "door", "rest", "mask"))

    def answer(qid: int, kind: np.ndarray, door: np.ndarray, dist: np.ndarray, mask: np.ndarray) -> list[dict]:
        graph = cover.graph
        if (kind == 0).all() or (kind == 1).all():
            return []
        own, there = int(mask[kind == 0][0]), int(mask[kind == 1][0])
        at = np.minimum(np.searchsorted(graph.nodes, door), max(len(graph.nodes) - 1, 0))
        known = graph.nodes[at] == door if len(graph.nodes) else np.zeros(len(door), dtype=bool)
        out = []
        if own | there == full:  # doors without any leg are passed alone
            rest = dict(zip(door[(kind == 1) & ~known].tolist(), dist[(kind == 1) & ~known].tolist(), strict=True))
            out = [{"qid": qid, "total_mm": d + rest[x], "path": [x]} for x, d in zip(door[(kind == 0) & ~known].tolist(), dist[(kind == 0) & ~known].tolist(), strict=True) if x in rest]
        go, stop = known & (kind == 0), known & (kind == 1)
        if go.any() and stop.any():
            label, goals, totals = cover.search(at[go], dist[go], own, at[stop], dist[stop], there, k)
            first = dict(zip((own * cover.n + at[go]).tolist(), dist[go].tolist(), strict=True))
            path = cover.paths(label, first, goals.tolist())
            out += [{"qid": qid, "total_mm": t, "path": list(path[s])} for s, t in zip(goals.tolist(), totals.tolist(), strict=True)]
        return out

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        whole = pa.Table.from_batches([b for b in batches if b.num_rows] or [pa.RecordBatch.from_pylist([], pa.schema([(c, pa.int64()) for c in ("qid", "kind", "door", "dist", "mask")]))])
        columns = [whole[c].to_numpy().astype(np.int64) for c in ("qid", "kind", "door", "dist", "mask")]
        for q in np.unique(columns[0]):
            found = answer(int(q), *(c[columns[0] == q] for c in columns[1:]))
            if found:
                yield pa.RecordBatch.from_pylist(found, pa.schema([("qid", pa.int64()), ("total_mm", pa.int64()), ("path", pa.list_(pa.int64()))]))

    tasks = 3 * rows.sparkSession.sparkContext.defaultParallelism
    return rows.repartition(tasks, "qid").mapInArrow(run, "qid long, total_mm long, path array<long>")


def relational_routes(starts: DataFrame, ends: DataFrame, legs: DataFrame, best: DataFrame) -> DataFrame:
    """(qid, dist, path) from path-carrying labels, bounded by the known answers best (qid, bound): for graphs of any size."""
    found = relax(starts, legs, best, with_path=True)
    whole = found.join(ends, ["qid", "door"]).groupBy("qid").agg(F.min(F.struct((F.col("dist") + F.col("rest")).alias("dist"), "path")).alias("low"))
    return whole.select("qid", "low.dist", "low.path")


def local_hops(targets: DataFrame, legs: DataFrame, made: tuple[_Legs, _Ladder] | None = None) -> DataFrame:
    """targets (door_id) -> (a_door, b_door, dist_mm, first_hop, stride_hop): of every door a to each target b.

    One job over targets; first_hop is NULL on the diagonal (see matrix.first_hops for stride_hop). Targets with a column
    starts (array of doors) give the rows of those doors a only, and hops are looked for at those doors only. made: the
    local_graph() of these legs and of all targets, if at hand.
    """
    graph, ladder = made or local_graph(targets.select("door_id"), legs)
    names = np.append(graph.nodes, -1)

    chosen = "starts" in targets.columns

    def rows_of(a: np.ndarray, b: np.ndarray, dist: np.ndarray, hops: tuple[np.ndarray, np.ndarray]) -> pa.RecordBatch:
        hop = [np.where(a == b, -1, names[h]) for h in hops]
        found = {k: pa.array(h, mask=h < 0) for k, h in zip(("first_hop", "stride_hop"), hop, strict=True)}
        return pa.RecordBatch.from_pydict({"a_door": pa.array(graph.nodes[a]), "b_door": pa.array(graph.nodes[b]), "dist_mm": pa.array(dist), **found})

    def to_all(frames: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        step = max(1, BLOCK_CELLS // max(1, len(graph.source), len(graph.nodes)))
        for doors, label in _door_blocks(frames, graph):
            settled = ladder.settle(label, backward=True)
            for low in range(0, len(doors), step):
                rest = settled[low : low + step]
                at = np.searchsorted(graph.nodes, doors[low : low + step])
                stops = np.zeros(rest.shape, dtype=bool)
                stops[np.arange(len(at)), at] = True
                tight = (rest[:, graph.target] < FAR) & (rest[:, graph.source] == graph.length + rest[:, graph.target])
                first, stride = graph.hops(tight, stops)
                r, c = np.nonzero(rest < FAR)
                yield rows_of(c, at[r], rest[r, c], (first[r, c], stride[r, c]))

    def to_chosen(frames: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        """Targets that lie together, with about as many starts, run over one part of the ladder."""
        batches = [batch for batch in frames if batch.num_rows]
        if not batches:
            return
        whole = pa.Table.from_batches(batches)
        end = np.searchsorted(graph.nodes, whole["door_id"].to_numpy())
        count = pc.list_value_length(whole["starts"]).to_numpy()
        a = pc.list_flatten(whole["starts"]).to_numpy()
        row, at = np.repeat(np.arange(len(end)), count), np.minimum(np.searchsorted(graph.nodes, a), len(graph.nodes) - 1)
        known = graph.nodes[at] == a
        pairs = np.unique(row[known] * len(graph.nodes) + at[known])
        row, a = pairs // len(graph.nodes), pairs % len(graph.nodes)
        begin = np.searchsorted(row, np.arange(len(end) + 1))
        group = np.unique(np.stack([whole["deal"].to_numpy(), np.frexp(count)[1]]), axis=1, return_inverse=True)[1].ravel()
        for targets in np.split(np.argsort(group, kind="stable"), np.cumsum(np.bincount(group))[:-1]):
            mine = np.concatenate([a[begin[t] : begin[t + 1]] for t in targets.tolist()])
            column, steps = ladder.part(np.union1d(graph.asked_by_hops(np.unique(mine)), end[targets]))
            step = max(1, BLOCK_CELLS // (int(column.max()) + 1))
            for low in range(0, len(targets), step):
                block = targets[low : low + step]
                rest = ladder.settle_part(end[block], column, steps)
                size = begin[block + 1] - begin[block]
                r, x = np.repeat(np.arange(len(block)), size), np.concatenate([a[begin[t] : begin[t + 1]] for t in block.tolist()])
                far = rest[r, column[x]]
                r, x, far = r[far < FAR], x[far < FAR], far[far < FAR]
                part = np.cumsum(graph.begin[x + 1] - graph.begin[x]) // BLOCK_CELLS
                for piece in np.split(np.arange(len(x)), np.flatnonzero(np.diff(part)) + 1):
                    b = end[block][r[piece]]
                    yield rows_of(x[piece], b, far[piece], graph.pair_hops(rest, r[piece], x[piece], b, column))

    schema = "a_door long, b_door long, dist_mm long, first_hop long, stride_hop long"
    if chosen:
        tasks = max(3 * legs.sparkSession.sparkContext.defaultParallelism, len(graph.nodes) // TASK_DOORS)
        deals = pa.table({"door_id": pa.array(graph.nodes), "deal": pa.array(ladder.places() // DEAL_DOORS)})
        found = targets.select("door_id", "starts").join(legs.sparkSession.createDataFrame(deals), "door_id").repartition(tasks, "deal").mapInArrow(to_chosen, schema)
    else:
        found = _dealt(targets.select("door_id").distinct()).mapInArrow(to_all, schema)
    return found.select("a_door", "b_door", "dist_mm", "first_hop", "stride_hop")


def hops_of(matrix: DataFrame, legs: DataFrame) -> DataFrame:
    """matrix (a_door, b_door, dist_mm) -> (a_door, b_door, first_hop, stride_hop), as matrix.first_hops() has them by joins.

    Rows meet at their end door: its column of the matrix lies in one task, and legs (of a checked size) go to each.
    """
    graph = leg_arrays(legs.select(F.col("a_door").alias("door_id")), legs)
    names, n = np.append(graph.nodes, -1), len(graph.nodes)
    step = max(1, BLOCK_CELLS // max(1, len(graph.source), n))
    parts = max(8 * matrix.sparkSession.sparkContext.defaultParallelism, -(-n * n // BLOCK_CELLS))

    def found(a: np.ndarray, b: np.ndarray, dist: np.ndarray) -> pa.RecordBatch:
        """Whole columns of the matrix, sorted by end door."""
        keys, row = np.unique(b, return_inverse=True)
        at = np.minimum(np.searchsorted(graph.nodes, a), n - 1)
        known = graph.nodes[at] == a  # doors without any leg have no hop
        rest = np.full((len(keys), n), FAR)
        rest[row[known], at[known]] = dist[known]
        then = rest[:, graph.target]
        tight = (then < FAR) & (rest[:, graph.source] == graph.length + then)
        end = np.minimum(np.searchsorted(graph.nodes, keys), n - 1)
        stops = np.zeros(rest.shape, dtype=bool)
        stops[np.arange(len(keys)), end] = graph.nodes[end] == keys
        hop = [np.where(known, names[h[row, at]], -1) for h in graph.hops(tight, stops)]
        return pa.RecordBatch.from_pydict({"a_door": pa.array(a), "b_door": pa.array(b), **{k: pa.array(h, mask=h < 0) for k, h in zip(("first_hop", "stride_hop"), hop, strict=True)}})

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held = [batch for batch in batches if batch.num_rows]
        if not held:
            return
        whole = pa.Table.from_batches(held)
        a, b, dist = (whole[c].to_numpy() for c in ("a_door", "b_door", "dist_mm"))
        del held, whole
        order = np.argsort(b, kind="stable")
        begin = np.append(np.flatnonzero(np.diff(b[order], prepend=b[order[0]] - 1)), len(b))
        for low in range(0, len(begin) - 1, step):
            rows = order[begin[low] : begin[min(low + step, len(begin) - 1)]]
            yield found(a[rows], b[rows], dist[rows])

    if not n:
        return matrix.select("a_door", "b_door", *[F.lit(None).cast("long").alias(c) for c in ("first_hop", "stride_hop")])
    columns = matrix.select("a_door", "b_door", "dist_mm").repartition(parts, "b_door")
    return columns.mapInArrow(run, "a_door long, b_door long, first_hop long, stride_hop long")


def walk_hops(hops: DataFrame, still: DataFrame, ends: DataFrame, per_task: int = 100_000) -> DataFrame:
    """ends (a_door, b_door, distinct) and hops (a_door, b_door, first_hop, stride_hop) -> (a_door, b_door, path).

    All walks towards one door are one grouped pass over the hops that are stored for it; a door that many walks end at is
    dealt to several tasks. A walk that comes to a door without a stored hop has no row. still (a_door, b_door) names the
    legs of length 0.
    """
    places = [(r[0], r[1]) for r in still.select("a_door", "b_door").collect()]  # few: staircase ends that share a place
    deals = materialize(ends.groupBy("b_door").agg(F.ceil(F.count("*") / per_task).cast("int").alias("deals")))
    asked = ends.join(deals, "b_door").select("a_door", "b_door", F.pmod(F.xxhash64("a_door"), F.col("deals")).cast("int").alias("deal"))
    copies = deals.select(F.col("b_door").alias("goal"), F.explode(F.sequence(F.lit(0), F.col("deals") - 1)).alias("deal"))
    known = hops.join(copies, F.col("b_door") == F.col("goal")).select("a_door", "b_door", "deal", "first_hop", "stride_hop")

    def walk(step: pd.DataFrame, ask: pd.DataFrame) -> pd.DataFrame:
        empty = pd.DataFrame({"a_door": pd.Series([], dtype="int64"), "b_door": pd.Series([], dtype="int64"), "path": pd.Series([], dtype=object)})
        if ask.empty:
            return empty
        goal = int(ask["b_door"].iloc[0])
        rows = zip(step["a_door"], step["first_hop"], step["stride_hop"], strict=True)
        onward = {int(a): (None if pd.isna(f) else int(f), None if pd.isna(s) else int(s)) for a, f, s in rows}
        zero, out, seen = set(places), [], {}
        for a in ask["a_door"].astype(int).unique().tolist():
            path, at, rested = [a], a, False
            while at != goal and at is not None and len(path) <= len(onward) + 2:
                then = onward.get(at, (None, None))[1 if rested else 0]
                rested = (at, then) in zero
                at = then
                path.append(at)
            seen[a] = path if at == goal else None
            if seen[a]:
                out.append((a, goal, path))
        return pd.DataFrame(out, columns=["a_door", "b_door", "path"]) if out else empty

    pairs = known.groupBy("b_door", "deal").cogroup(asked.groupBy("b_door", "deal"))
    return pairs.applyInPandas(walk, "a_door long, b_door long, path array<long>")


def labels(seeds: DataFrame, legs: DataFrame, bound: DataFrame | int | None = None, engine: str = "auto") -> DataFrame:
    """relax() or local_search(), by the checked size of the leg table unless the engine is named."""
    if engine == "auto":
        engine = "local" if is_local(legs) else "relax"
    return local_search(seeds, legs, bound) if engine == "local" else relax(seeds, legs, bound)


def all_pairs(legs: DataFrame, sources: DataFrame, engine: str = "auto", max_rounds: int = 64) -> DataFrame:
    """(a_door, b_door, dist_mm) from every source door, itself at distance 0."""
    if engine == "square":
        if is_local(legs):
            return local_pairs(sources, legs, "doubling")
        zero = sources.select(F.col("door_id").alias("a_door"), F.col("door_id").alias("b_door"), F.lit(0).cast("long").alias("dist_mm"))
        return doubled(zero.union(legs.select("a_door", "b_door", F.col("leg_mm").alias("dist_mm"))), max_rounds)
    if engine == "local" or (engine == "auto" and is_local(legs)):
        return local_pairs(sources, legs)
    if is_local(legs):
        return local_pairs(sources, legs, "rounds")
    seeds = sources.select(F.col("door_id").alias("qid"), F.col("door_id").alias("door"), F.lit(0).cast("long").alias("dist"))
    found = relax(seeds, legs)
    return found.select(F.col("qid").alias("a_door"), F.col("door").alias("b_door"), F.col("dist").alias("dist_mm"))
