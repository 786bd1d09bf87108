"""Embedding near-duplicates by spherical-cap filters from random product codes.

The sphere is covered by caps whose centres form a product code: the vector space is rotated at random and split into
blocks, each block has a small random codebook, and a centre is one code word per block. A vector belongs to every cap whose
centre it exceeds; those are list-decoded block by block with the best possible rest as a bound, so the full set
of centres is never listed. Vectors of one label that share a cap are compared exactly, in double precision.

The code grows with the table: `suited` takes more words and a tighter cut-off as vectors get more, so that caps keep their
number of members, and few-dimensional spaces get one block and just the words that make lists of the wanted length.

Equal vectors collapse first and count with their multiplicity. A pair that shares several caps is counted in the
first cap that both hold (lists are decoded anew where they are needed, not shipped); a full cap is cut into blocks of
members, and each pair of blocks is a task's work of its own.
"""

from __future__ import annotations

import math
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from floorwalk.llm.runtime import connected_components, materialize
from floorwalk.llm.textkit import local_roots

COSINE, SEED = 0.93, 20240101
LIST, PER_CAP, LEAST_CENTRES, WIDE = 24, 48, 1 << 14, 8
SPLIT_ROWS, TILE, SMALL, PAIRS = 4096, 512, 128, 1 << 15


class ProductCode:
    """Random product code on the sphere of a dimension, and its list decoder."""

    def __init__(self, dimension: int, blocks: int, words: int, seed: int = SEED) -> None:
        rng = np.random.default_rng(seed)
        self.dimension, self.blocks, self.words = dimension, min(blocks, dimension), words
        self.rotation = np.linalg.qr(rng.standard_normal((dimension, dimension)))[0]
        self.bounds = np.linspace(0, dimension, self.blocks + 1).astype(int)
        self.books = []
        for low, high in zip(self.bounds[:-1], self.bounds[1:], strict=True):
            book = rng.standard_normal((words, high - low))
            self.books.append(book / np.linalg.norm(book, axis=1, keepdims=True) / np.sqrt(self.blocks))

    def decode(self, unit: np.ndarray, cutoff: float) -> tuple[np.ndarray, np.ndarray]:
        """(vector number, centre number) of every centre whose inner product with the vector is at least the cutoff
        times the best inner product that any centre has with it.

        Relative cut-offs keep the lists of all vectors alike in length, and every vector is indexed.
        """
        turned = unit @ self.rotation
        scores = [turned[:, a:b] @ book.T for a, b, book in zip(self.bounds[:-1], self.bounds[1:], self.books, strict=True)]
        best = np.stack([s.max(axis=1) for s in scores], axis=1)
        rest = np.cumsum(best[:, ::-1], axis=1)[:, ::-1]
        who, code, total = np.arange(len(unit)), np.zeros(len(unit), dtype=np.int64), np.zeros(len(unit))
        for block, score in enumerate(scores):
            open_rest = rest[:, block + 1] if block + 1 < self.blocks else np.zeros(len(unit))
            grown = total[:, None] + score[who]
            row, word = np.nonzero(grown + open_rest[who][:, None] >= cutoff * rest[who, 0][:, None] - 1e-12)
            total, code, who = grown[row, word], code[row] * self.words + word, who[row]
        return who, code


@dataclass(frozen=True)
class Design:
    """Parameters of the filter of one dimension: blocks and words of the code, and the relative cut-off."""

    dimension: int
    blocks: int
    words: int
    cutoff: float

    def code(self) -> ProductCode:
        return ProductCode(self.dimension, self.blocks, self.words)


def mean_list(design: Design, cutoff: float | None = None) -> float:
    """Mean number of caps of random directions."""
    probe = unit(np.random.default_rng(SEED + 1).standard_normal((256, design.dimension)))
    return len(design.code().decode(probe, design.cutoff if cutoff is None else cutoff)[0]) / len(probe)


def suited(dimension: int, n: int) -> Design:
    """The design for n vectors: about PER_CAP members a cap and LIST caps a vector, whatever n and the dimension are."""
    blocks = 2 if dimension >= WIDE else 1
    centres = max(LEAST_CENTRES, LIST * n / PER_CAP)
    if blocks == 1:  # few dimensions need few words: lists at a fixed cut-off grow with them
        words = 2
        while words < 4096 and mean_list(Design(dimension, 1, words, 0.85)) < LIST:
            words *= 2
        return Design(dimension, 1, words, 0.85)
    words = 1 << math.ceil(math.log2(centres) / 2)
    low, high = 0.5, 0.999
    for _ in range(12):  # the cut-off that gives lists of the wanted length
        middle = (low + high) / 2
        low, high = (middle, high) if mean_list(Design(dimension, blocks, words, middle)) > LIST else (low, middle)
    return Design(dimension, blocks, words, low)


def unit(values: np.ndarray) -> np.ndarray:
    """Rows scaled to length one; by their largest component first, so that squares neither overflow nor vanish."""
    scaled = values / np.abs(values).max(axis=1, keepdims=True)
    return scaled / np.sqrt((scaled * scaled).sum(axis=1, keepdims=True))


def _vectors(column: pa.Array, dimension: int) -> np.ndarray:
    return column.flatten().to_numpy(zero_copy_only=False).astype(np.float64).reshape(-1, dimension)


def _lists(code: ProductCode, directions: np.ndarray, cutoff: float) -> Iterator[tuple[int, np.ndarray, np.ndarray]]:
    """Tile by tile: its first row, the sorted centres of its rows end to end, and the bounds of each row's list."""
    for low in range(0, len(directions), TILE):
        who, centre = code.decode(directions[low : low + TILE], cutoff)
        order = np.lexsort((centre, who))
        n = min(TILE, len(directions) - low)
        yield low, centre[order], np.searchsorted(who[order], np.arange(n + 1))


def _decode(design: Design):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        """A row per vector and cap, without the vector itself."""
        code = design.code()
        for batch in batches:
            for low, centre, cuts in _lists(code, unit(_vectors(batch.column("embedding"), design.dimension)), design.cutoff):
                owner = np.repeat(np.arange(low, low + len(cuts) - 1), np.diff(cuts))
                rows = batch.drop_columns(["embedding"]).take(pa.array(owner))
                yield pa.RecordBatch.from_arrays([*rows.columns, pa.array(centre.astype(np.int64))], names=[*rows.schema.names, "centre"])

    return run


class _Cap:
    """Links inside one run of whole (label, cap, tile) groups; rows are sorted by group.

    A tile compares block `low` of a cap's members with block `high`; where both are one, all of its members with each other.
    """

    def __init__(self, table: pa.Table, begin: np.ndarray, cosine: float, design: Design, code: ProductCode) -> None:
        self.values = unit(_vectors(table["embedding"].combine_chunks(), design.dimension))
        self.copies, self.block = table["copies"].to_numpy(), table["block"].to_numpy()
        self.mixed = table["low"].to_numpy() != table["high"].to_numpy()
        self.begin, self.size, self.cosine = begin, np.diff(np.append(begin, table.num_rows)), cosine
        self.root, self.links = np.arange(table.num_rows), np.zeros(table.num_rows, dtype=np.int64)
        below = table["centre"].to_numpy()
        parts, lengths = [], []
        for low, centre, cuts in _lists(code, self.values, design.cutoff):
            owner = np.repeat(np.arange(len(cuts) - 1), np.diff(cuts))
            early = centre < below[low + owner]  # caps before the row's own one
            parts.append(centre[early])
            lengths.append(np.bincount(owner[early], minlength=len(cuts) - 1))
        self.flat, length = np.concatenate(parts), np.concatenate(lengths)
        self.first, self.length = np.cumsum(length) - length, length

    def _count(self, a: np.ndarray, b: np.ndarray) -> None:
        np.add.at(self.links, a, self.copies[b])
        self.root = local_roots(a, b, self.root)

    def _padded(self, rows: np.ndarray) -> np.ndarray:
        """The earlier caps of some rows as one matrix, filled up with -1."""
        length = self.length[rows]
        out = np.full((len(rows), max(1, int(length.max(initial=0)))), -1, dtype=np.int64)
        row = np.repeat(np.arange(len(rows)), length)
        step = np.arange(len(row)) - np.repeat(np.cumsum(length) - length, length)
        out[row, step] = self.flat[np.repeat(self.first[rows], length) + step]
        return out

    def _met_before(self, a: np.ndarray, b: np.ndarray) -> np.ndarray:
        x, y = self._padded(a), self._padded(b)
        return ((x[:, :, None] == y[:, None, :]) & (x[:, :, None] >= 0)).any(axis=(1, 2))

    def small(self) -> None:
        """All pairs of the small whole caps, as one list in pieces."""
        few = (self.size <= SMALL) & ~self.mixed[self.begin]
        ask = np.flatnonzero(np.repeat(few, self.size))
        owner = np.searchsorted(self.begin, ask, side="right") - 1
        width = self.size[owner]
        step = np.searchsorted(np.cumsum(width), np.arange(0, int(width.sum()), PAIRS), side="left")
        for low, high in zip(step, np.append(step[1:], len(ask)), strict=True) if len(step) else ():
            w = width[low:high]
            a = np.repeat(ask[low:high], w)
            b = np.repeat(self.begin[owner[low:high]], w) + np.arange(w.sum()) - np.repeat(np.cumsum(w) - w, w)
            near = (np.einsum("ij,ij->i", self.values[a], self.values[b]) >= self.cosine) & (a != b)
            self._new(a[near], b[near])

    def _new(self, a: np.ndarray, b: np.ndarray) -> None:
        for low in range(0, len(a), TILE):
            x, y = a[low : low + TILE], b[low : low + TILE]
            new = ~self._met_before(x, y)
            if new.any():
                self._count(x[new], y[new])

    def large(self) -> None:
        """Other groups, a tile of query rows against the members at a time; a pair of two blocks counts for both sides."""
        for g in np.flatnonzero((self.size > SMALL) | self.mixed[self.begin]):
            low, high = self.begin[g], self.begin[g] + self.size[g]
            rows = np.arange(low, high)
            if self.mixed[low]:
                side = self.block[low:high] == self.block[low:high].min()
                left, right = rows[side], rows[~side]
            else:
                left = right = rows
            if not len(left) or not len(right):
                continue
            values = self.values[right]
            earlier = self._padded(right)
            known, column = np.unique(earlier, return_inverse=True)
            held = np.zeros((len(right), len(known)), dtype=np.float32)
            held[np.repeat(np.arange(len(right)), earlier.shape[1]), column.ravel()] = 1
            held[:, known < 0] = 0
            for i in range(0, len(left), TILE):
                ask = left[i : i + TILE]
                near = self.values[ask] @ values.T >= self.cosine - 1e-9
                near &= ask[:, None] != right[None, :]
                if not near.any():
                    continue
                mine = self._padded(ask)
                at = np.minimum(np.searchsorted(known, mine), len(known) - 1)
                shares = np.zeros((len(ask), len(known)), dtype=np.float32)
                r, c = np.nonzero((known[at] == mine) & (mine >= 0))
                shares[r, at[r, c]] = 1
                near &= shares @ held.T == 0
                a, b = np.nonzero(near)
                for k in range(0, len(a), PAIRS):
                    x, y = ask[a[k : k + PAIRS]], right[b[k : k + PAIRS]]
                    exact = np.einsum("ij,ij->i", self.values[x], self.values[y]) >= self.cosine
                    self._count(x[exact], y[exact])
                    if left is not right:
                        self._count(y[exact], x[exact])


GROUP = ["label_text", "centre", "low", "high"]


def _compare(cosine: float, design: Design):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        """Rows come sorted by label, cap and tile; a group may span batches and is held until it is whole: two blocks at most."""
        held: pa.Table | None = None
        code = design.code()

        def links(table: pa.Table, begin: np.ndarray) -> pa.RecordBatch:
            cap = _Cap(table, begin, cosine, design, code)
            cap.small()
            cap.large()
            number = table["class_id"].to_numpy()
            out = np.flatnonzero(cap.links)
            return pa.RecordBatch.from_pydict({"class_id": pa.array(number[out]), "links": pa.array(cap.links[out]), "near_class": pa.array(number[cap.root[out]])})

        def starts(table: pa.Table) -> np.ndarray:
            new = np.zeros(table.num_rows, dtype=bool)
            new[:1] = True
            for name in GROUP:
                column = table[name].combine_chunks()
                codes = column.dictionary_encode().indices.to_numpy() if pa.types.is_string(column.type) else column.to_numpy()
                new[1:] |= codes[1:] != codes[:-1]
            return np.flatnonzero(new)

        for batch in batches:
            if not batch.num_rows:
                continue
            table = pa.Table.from_batches([batch])
            table = pa.concat_tables([held, table]).combine_chunks() if held is not None else table
            begin = starts(table)
            if len(begin) > 1:
                yield links(table.slice(0, begin[-1]).combine_chunks(), begin[:-1])
                table = table.slice(begin[-1]).combine_chunks()
            held = table
        if held is not None and held.num_rows:
            yield links(held, starts(held))

    return run


def cap_links(own: DataFrame, design: Design, cosine: float) -> DataFrame:
    """own (class_id, label, copies, embedding), all of the design's dimension -> (class_id, links, near_class)."""
    none = "class_id long, links long, near_class long"
    caps = own.select("class_id", "label", "embedding").mapInArrow(_decode(design), T.StructType([*own.select("class_id", "label").schema.fields, T.StructField("centre", T.LongType())]))
    caps = materialize(caps)
    # Caps with one member need no task; full ones are cut into blocks, and a member goes to the tiles of its block.
    sizes = caps.groupBy("label", "centre").agg(F.ceil(F.count("*") / SPLIT_ROWS).cast("int").alias("blocks"), F.count("*").alias("members")).where("members > 1")
    dealt = caps.join(sizes.drop("members"), ["label", "centre"]).withColumn("block", F.pmod(F.xxhash64("class_id"), F.col("blocks")).cast("int"))
    dealt = dealt.withColumn("other", F.explode(F.sequence(F.lit(0), F.col("blocks") - 1)))
    dealt = dealt.withColumn("low", F.least("block", "other")).withColumn("high", F.greatest("block", "other"))
    dealt = dealt.withColumn("label_text", F.col("label").cast("string")).select("class_id", "block", *GROUP)
    dealt = dealt.join(own.select("class_id", "copies", "embedding"), "class_id").repartition(*GROUP).sortWithinPartitions(*GROUP)
    return dealt.mapInArrow(_compare(cosine, design), none)


def link_vectors(vectors: DataFrame, cosine: float = COSINE, design: Design | None = None) -> DataFrame:
    """A row per vector: vec_id, n_links, component_id, kept.

    Only vectors of equal, non-null labels and equal length are compared. A null, empty or zero vector, or one with a null or
    non-finite component, links with nothing and is kept; components of any finite size count; repeated rows are vectors of
    their own; a null id is never the least of a component; an empty table gives no row; other columns are not read.
    """
    spark = vectors.sparkSession
    rows = vectors.select(F.col("vec_id").cast("long").alias("vec_id"), "label", "embedding")
    sound = F.col("label").isNotNull() & F.col("embedding").isNotNull() & (F.size("embedding") > 0)
    sound &= ~F.exists("embedding", lambda x: x.isNull() | F.isnan(x) | (F.abs(x) == float("inf")))
    sound &= F.exists("embedding", lambda x: x != 0.0)
    rows = rows.withColumn("sound", F.coalesce(sound, F.lit(False)))
    classes = rows.where("sound").groupBy("label", "embedding").agg(F.count("*").alias("copies"), F.min("vec_id").alias("least"))
    classes = materialize(classes.withColumn("class_id", F.monotonically_increasing_id()).withColumn("dimension", F.size("embedding")))
    found = spark.createDataFrame([], "class_id long, links long, near_class long")
    for dimension, n in classes.groupBy("dimension").count().collect():  # few: one per embedding model in the table
        own = classes.where(F.col("dimension") == dimension).select("class_id", "label", "copies", "embedding")
        found = found.union(cap_links(own, design or suited(dimension, n), cosine))
    found = materialize(found)
    roots = connected_components(found.select(F.col("class_id").alias("a"), F.col("near_class").alias("b")))
    links = found.groupBy("class_id").agg(F.sum("links").alias("links"))
    named = classes.select("class_id", "label", "embedding", "copies", "least").join(links, "class_id", "left")
    named = named.join(roots.withColumnRenamed("node", "class_id"), "class_id", "left").withColumn("root", F.coalesce("root", "class_id"))
    least = named.groupBy("root").agg(F.min("least").alias("component_id"))
    named = named.join(least, "root").select("label", "embedding", (F.coalesce("links", F.lit(0)) + F.col("copies") - 1).alias("n_links"), "component_id")
    linked = rows.where("sound").join(named, ["label", "embedding"]).select("vec_id", "n_links", "component_id")
    alone = rows.where("not sound").select("vec_id", F.lit(0).cast("long").alias("n_links"), F.col("vec_id").alias("component_id"))
    both = linked.union(alone)
    return both.withColumn("kept", F.coalesce(F.col("vec_id") == F.col("component_id"), F.lit(False)))


def query(spark, sf_dir: str) -> DataFrame:
    return link_vectors(spark.read.parquet(f"{sf_dir}/embeddings.parquet"))
