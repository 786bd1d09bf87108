"""SimHash near-duplicates found through a Gray-ordered hierarchical Hamming index.

A fingerprint is made once per text; equal ones collapse before any search. Codes are indexed several times over, each time
with their bits in another order (a table). Within a table they stand in Gray order, cut into slices by their leading
bits, and a slice is searched as a hierarchy: the bits that neighbours in Gray order share move up into their node, and a
node with all below it is pruned as soon as the differences accumulated on the way down exceed the radius.

A slice is one task's work only up to MEMBERS codes. A fuller one is cut along the Gray order into parts; the bits that a
part shares are its upper node, and a code is sent to just those parts whose upper node it does not exceed the radius of.

`exact_tables` is for small radii: with b blocks of bits, two codes within the radius agree on b - radius of them, so one
table for each such choice of blocks loses nothing. `sampled_tables` is for wide radii: each table leads with bits drawn
at random, and as many tables are taken as make a pair at the given share of equal bits meet almost surely.
"""

from __future__ import annotations

import math
from collections.abc import Iterator
from dataclasses import dataclass
from itertools import combinations

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from floorwalk.llm.runtime import connected_components, content_keys, discard, guarded, materialize, materialize_texts
from floorwalk.llm.textkit import HASH_A, HASH_B, IS_SPACE, TO_LOWER, chunks, local_roots, mix64

SHINGLE, RADIUS, SEED = 3, 3, 42
SLICE, MEMBERS, ASKED, FANOUT = 1024, 8192, 1024, 32
FOREST, FIRST, SURE, SPAN, EVERY = "forest", "first", "sure", "span", "every"
# The near-copy rule of stages: five-word shingles as sets, similarity 0.8 and more, found in fingerprints of two words.
NEAR_SHINGLE, NEAR_WORDS, NEAR_SHARE, NEAR_RADIUS, NEAR_MISS = 5, 2, 0.8485, 34, 5e-4
VERIFY_ROWS = 4096
BUCKETS, MOST_BUCKETS = 8, 1 << 16


def majority(hashes: np.ndarray, cuts: np.ndarray) -> np.ndarray:
    """For each run of hash rows (n x words), the bits that more than half of them set; empty runs give zero."""
    words = hashes.shape[1]
    out = np.zeros((len(cuts) - 1, words), dtype=np.uint64)
    full = np.flatnonzero(np.diff(cuts))
    ones = np.zeros((len(full), 64 * words), dtype=np.int32)
    begin, step = cuts[full], 1 << 14
    for i in range(0, len(hashes), step):
        part = np.unpackbits(hashes[i : i + step].astype(">u8").view(np.uint8), axis=1)
        lo, hi = np.searchsorted(begin, i, side="right") - 1, np.searchsorted(begin, i + len(part), side="left")
        ones[lo:hi] += np.add.reduceat(part, np.maximum(begin[lo:hi] - i, 0), axis=0, dtype=np.int32)
    bits = (2 * ones > np.diff(cuts)[full][:, None]).astype(np.uint8)
    out[full] = np.ascontiguousarray(np.packbits(bits, axis=1)).view(">u8")
    return out


def fingerprints(column: pa.Array, shingle: int = SHINGLE) -> np.ndarray:
    """The 64-bit SimHash of each text: the bits that more than half of its word shingles' hashes set."""
    out, digest = [], xxhash.xxh64_intdigest
    for chunk in chunks(column):
        start, end, doc = chunk.words()
        if not len(start):
            out.append(np.zeros(chunk.n_docs, dtype=np.uint64))
            continue
        keep = ~IS_SPACE[chunk.data]
        gap = np.flatnonzero(doc[1:] == doc[:-1]) + 1
        keep[start[gap] - 1] = True
        clean = TO_LOWER[chunk.data]
        clean[start[gap] - 1] = 32
        place = np.cumsum(keep)
        begin, stop = place[start] - 1, place[end - 1]
        text = clean[keep].tobytes()
        first, last, owner = _windows(doc, chunk.per_doc(doc), shingle)
        hashes = np.array([digest(text[i:j], SEED) for i, j in zip(begin[first].tolist(), stop[last].tolist(), strict=True)], dtype=np.uint64)
        out.append(majority(hashes[:, None], np.searchsorted(owner, np.arange(chunk.n_docs + 1)))[:, 0])
    return np.concatenate(out) if out else np.zeros(0, dtype=np.uint64)


def _windows(doc: np.ndarray, n: np.ndarray, shingle: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """First and last word and text of every shingle, by text; a text of fewer words is one shingle."""
    first = np.cumsum(n) - n
    short = np.flatnonzero((n > 0) & (n < shingle))
    head = np.arange(max(len(doc) - shingle + 1, 0))
    head = head[doc[head] == doc[head + shingle - 1]]
    a = np.concatenate([head, first[short]])
    b = np.concatenate([head + shingle - 1, first[short] + n[short] - 1])
    owner = np.concatenate([doc[head], short])
    order = np.argsort(owner, kind="stable")
    return a[order], b[order], owner[order]


def shingle_sets(column: pa.Array, shingle: int = NEAR_SHINGLE) -> Iterator[tuple[np.ndarray, np.ndarray]]:
    """Per chunk: the sorted distinct shingle hashes of its texts end to end, and the bounds of each text.

    Words are separated by any white space and A-Z is lower-cased; a text of fewer words is one shingle.
    """
    for chunk in chunks(column, 1 << 18):
        start, end, doc = chunk.words()
        words = HASH_B.prefix(HASH_A.spans(HASH_A.prefix(TO_LOWER[chunk.data]), start, end))
        a, b, owner = _windows(doc, chunk.per_doc(doc), shingle)
        value = HASH_B.spans(words, a, b + 1)
        order = np.lexsort((value, owner))
        value, owner = value[order], owner[order]
        new = np.ones(len(value), dtype=bool)
        new[1:] = (value[1:] != value[:-1]) | (owner[1:] != owner[:-1])
        yield value[new], np.searchsorted(owner[new], np.arange(chunk.n_docs + 1))


def similar(common: np.ndarray, a: np.ndarray, b: np.ndarray) -> np.ndarray:
    """Whether sets of a and b members with so many in common have a Jaccard similarity of 0.8 at least, in integers."""
    return (9 * common >= 4 * (a + b)) & (a > 0) & (b > 0)


def parity(hashes: np.ndarray) -> bytes:
    """A set's members dealt over buckets (a power of two, about BUCKETS a member): a bit each, whether it holds an odd number."""
    n = 1 << min(max(6, (BUCKETS * len(hashes) - 1).bit_length()), MOST_BUCKETS.bit_length() - 1)
    at = (hashes & np.uint64(n - 1)).astype(np.int64)
    return np.packbits((np.bincount(at, minlength=n) & 1).astype(np.uint8)).tobytes()


class Parities:
    """Which pairs of sets may have a similarity of 0.8, from sizes and parities alone; no pair that has it is ruled out.

    Buckets whose parity differs each hold a member that only one of the sets has. Twice as many buckets fold to half.
    """

    def __init__(self, size: np.ndarray, bits: pa.Array) -> None:
        self.size = size
        width = pc.binary_length(bits).to_numpy(zero_copy_only=False) // 8
        self.width, self.tables = width, {}
        for w in np.unique(width).tolist():
            place, parts = np.full(len(size), -1), []
            for own in (w, 2 * w):
                rows = np.flatnonzero(width == own)
                words = np.frombuffer(b"".join(bits.take(pa.array(rows)).to_pylist()), dtype=np.uint64).reshape(len(rows), own)
                place[rows] = sum(map(len, parts)) + np.arange(len(rows))
                parts.append(words if own == w else words[:, :w] ^ words[:, w:])
            self.tables[w] = place, np.concatenate(parts)

    def may_match(self, a: np.ndarray, b: np.ndarray, sure: bool = False) -> np.ndarray:
        """With sure, those only that match unless many of the members that one set has alone hide each other."""
        na, nb = self.size[a], self.size[b]
        near = similar(np.minimum(na, nb), na, nb)
        width = np.minimum(self.width[a], self.width[b])
        for w in np.unique(width[near]).tolist():
            place, table = self.tables[w]
            rows, step = np.flatnonzero(near & (width == w)), max(1, (1 << 20) // w)
            for low in range(0, len(rows), step):
                part = rows[low : low + step]
                odd = np.bitwise_count(table[place[a[part]]] ^ table[place[b[part]]]).sum(axis=1, dtype=np.int64)
                near[part] = (11 if sure else 9) * odd <= na[part] + nb[part]  # common <= (na + nb - odd) / 2, see similar()
        return near


@dataclass(frozen=True)
class Tables:
    """Bit orders of the index's tables (one row each) and the number of leading bits that name a slice."""

    orders: np.ndarray
    lead: int

    def turned(self, table: int, codes: np.ndarray) -> np.ndarray:
        """Codes (n x words) with their bits in the table's order."""
        bits = np.unpackbits(codes.astype(">u8", order="C").view(np.uint8), axis=1)
        return np.ascontiguousarray(np.packbits(bits[:, self.orders[table]], axis=1)).view(">u8").astype(np.uint64, order="C")


def lead_bits(n_codes: int, slice_size: int = SLICE) -> int:
    return max(0, math.ceil(math.log2(max(1, n_codes / slice_size))))


def exact_tables(n_codes: int, radius: int = RADIUS, slice_size: int = SLICE) -> Tables:
    """Tables that lose no pair of 64-bit codes within the radius; more and narrower blocks as codes get more."""
    lead = lead_bits(n_codes, slice_size)
    if not lead:
        return Tables(np.arange(64)[None, :], 0)
    blocks = radius + 1
    while True:
        cuts = np.linspace(0, 64, blocks + 1).astype(int)
        width = int(np.diff(cuts).min()) * (blocks - radius)
        if width >= lead or blocks == radius + 3:
            break
        blocks += 1
    orders = []
    for chosen in combinations(range(blocks), blocks - radius):
        front = np.concatenate([np.arange(cuts[b], cuts[b + 1]) for b in chosen])
        orders.append(np.concatenate([front, np.setdiff1d(np.arange(64), front)]))
    return Tables(np.array(orders), min(lead, width))


def sampled_tables(n_codes: int, words: int = NEAR_WORDS, share: float = NEAR_SHARE, miss: float = NEAR_MISS, slice_size: int = SLICE) -> Tables:
    """Tables in which a pair that agrees on the given share of bits shares a slice, but for a chance of `miss`."""
    lead, rng = lead_bits(n_codes, slice_size), np.random.default_rng(SEED)
    count = 1 if not lead else math.ceil(math.log(miss) / math.log1p(-(share**lead)))
    return Tables(np.array([rng.permutation(64 * words) for _ in range(count)]), lead)


def gray_rank(codes: np.ndarray) -> np.ndarray:
    """Place of each code (n x words, most significant word first) in the reflected Gray sequence."""
    rank = codes.copy()
    for shift in (1, 2, 4, 8, 16, 32):
        rank ^= rank >> np.uint64(shift)
    odd = np.zeros(len(rank), dtype=np.uint64)
    for word in range(rank.shape[1]):  # the parity of all words before runs through the rest
        rank[:, word] ^= np.uint64(0) - odd
        odd = rank[:, word] & np.uint64(1)
    return rank


class GrayHammingIndex:
    """Hierarchy over codes in Gray order. A node holds the bits its codes share that no ancestor holds already."""

    def __init__(self, codes: np.ndarray, fanout: int = FANOUT) -> None:
        rank = gray_rank(codes)
        self.order = np.lexsort(rank.T[::-1])
        self.codes, self.fanout = codes[self.order], fanout
        levels, ones, zeros = [], self.codes, ~self.codes
        while len(ones) > 1 or not levels:
            cuts = np.arange(0, len(ones), fanout)
            ones, zeros = np.bitwise_and.reduceat(ones, cuts, axis=0), np.bitwise_and.reduceat(zeros, cuts, axis=0)
            levels.append((ones, ones | zeros))
        self.levels, above = [], None  # top first: pattern, and the mask of the bits that this level adds
        for pattern, shared in reversed(levels):
            own = shared if above is None else shared & ~above[np.arange(len(shared)) // fanout]
            self.levels.append((pattern, own))
            above = shared

    def links(self, radius: int, queries: np.ndarray | None = None) -> Iterator[tuple[np.ndarray, np.ndarray]]:
        """Pairs (number, code number) within the radius, a leaf node at a time: of the given queries, or, without any,
        of the codes themselves (each pair once, no code with itself)."""
        own = queries is None
        asked = self.codes if own else queries
        bottom = len(self.levels) - 1
        for low in range(0, len(asked), ASKED):
            block = asked[low : low + ASKED]
            # Nodes still to visit: level, number, the queries that are alive there and the differences so far.
            todo = [(0, 0, np.arange(len(block)), np.zeros(len(block), dtype=np.uint8))]
            while todo:
                level, node, live, off = todo.pop()
                pattern, mask = self.levels[level]
                for w in range(block.shape[1]):
                    off = off + np.bitwise_count((block[live, w] ^ pattern[node, w]) & mask[node, w])
                alive = off <= radius
                if own:  # only codes behind the node's first one
                    alive &= low + live > node * self.fanout ** (bottom - level + 1)
                live, off = live[alive], off[alive]
                if not len(live):
                    continue
                first = node * self.fanout
                if level < bottom:
                    todo += [(level + 1, child, live, off) for child in range(first, min(first + self.fanout, len(self.levels[level + 1][0])))]
                    continue
                members = self.codes[first : first + self.fanout]
                apart = np.zeros((len(live), len(members)), dtype=np.uint8)
                for w in range(block.shape[1]):
                    apart += np.bitwise_count(block[live, w, None] ^ members[None, :, w])
                near = apart <= radius
                if own:
                    near &= (low + live)[:, None] > first + np.arange(len(members))[None, :]
                q, m = np.nonzero(near)
                if len(q):
                    at = low + live[q]
                    yield (self.order[at] if own else at), self.order[first + m]


SETS = {"shingles": "long", "parity": "binary"}


def _columns(codes: np.ndarray) -> dict[str, pa.Array]:
    return {f"w{i}": pa.array(np.ascontiguousarray(codes[:, i]).view(np.int64)) for i in range(codes.shape[1])}


def _codes(batch, words: int) -> np.ndarray:
    return np.stack([batch.column(f"w{i}").to_numpy().view(np.uint64) for i in range(words)], axis=1)


def _deal(tables: Tables, words: int):
    """Every code once per table, under its slice and with its place in Gray order (the upper 62 bits of the rank)."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            codes, number = _codes(batch, words), batch.column("id")
            for table in range(len(tables.orders)):
                turned = tables.turned(table, codes)
                lead = turned[:, 0] >> np.uint64(64 - tables.lead) if tables.lead else np.zeros(len(codes), dtype=np.uint64)
                key = lead.astype(np.int64) * len(tables.orders) + table
                place = (gray_rank(turned)[:, 0] >> np.uint64(2)).astype(np.int64)
                sets = {c: batch.column(c) for c in SETS if c in batch.schema.names}
                yield pa.RecordBatch.from_pydict({"key": pa.array(key), "place": pa.array(place), "id": number, "label": batch.column("label"), **_columns(codes), **sets})

    return run


def _spanning(a: np.ndarray, b: np.ndarray, rows: np.ndarray, root: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """The rows of pairs that join what root leaves apart, none of them needless, and the roots after that."""
    chosen = []
    while len(rows):
        x, y = root[a[rows]], root[b[rows]]
        open_rows = x != y
        rows, x, y = rows[open_rows], x[open_rows], y[open_rows]
        # One pair for each greater root: every such root goes under a lesser one, so no circle closes.
        one = np.unique(np.maximum(x, y), return_index=True)[1]
        chosen.append(rows[one])
        root = local_roots(x[one], y[one], root)
    return np.concatenate(chosen) if chosen else rows, root


def _search(tables: Tables, words: int, radius: int, mode: str):
    """Slices arrive sorted by (key, part); a slice may span batches. Rows with member = false only ask.

    Yields links (a, b) of ids. FOREST: as many as join all that is linked inside a slice; FIRST: each code with its first
    neighbour in Gray order; SPAN: pairs that may match (see Parities), as few as join all labels that such pairs join
    inside a slice; SURE: the same of pairs that hardly fail; EVERY: all pairs that may match and whose labels differ.
    """

    def batch_of(a: np.ndarray, b: np.ndarray) -> pa.RecordBatch:
        return pa.RecordBatch.from_pydict({"a": pa.array(np.minimum(a, b)), "b": pa.array(np.maximum(a, b))})

    def settle(key: int, table: pa.Table) -> Iterator[pa.RecordBatch]:
        codes, number, label = _codes(table.combine_chunks(), words), table["id"].to_numpy(), table["label"].to_numpy()
        member = table["member"].to_numpy()
        turned = tables.turned(key % len(tables.orders), codes)
        inside, asking = np.flatnonzero(member), np.flatnonzero(~member)
        if not len(inside):
            return
        index = GrayHammingIndex(turned[inside])
        searches = [(inside, index.links(radius))]
        if len(asking):
            searches.append((asking, index.links(radius, turned[asking])))
        root, linked = np.arange(len(number)), np.zeros(len(number), dtype=bool)
        sets = Parities(table["shingles"].to_numpy(), table["parity"].combine_chunks()) if mode in (SURE, SPAN, EVERY) else None
        if mode in (SURE, SPAN):
            _, first, same = np.unique(label, return_index=True, return_inverse=True)
            root = first[same]
        for rows, found in searches:
            for q, m in found:
                a, b = rows[q], inside[m]
                if mode == FOREST:
                    root = local_roots(a, b, root)
                    continue
                if mode == FIRST:
                    new = np.flatnonzero(~linked[a])
                    new = new[np.unique(a[new], return_index=True)[1]]
                    back = np.flatnonzero(~linked[b])
                    back = back[np.unique(b[back], return_index=True)[1]]
                    new = np.union1d(new, back)
                    a, b = a[new], b[new]
                    linked[a] = linked[b] = True
                apart = np.flatnonzero(label[a] != label[b])
                if mode in (SURE, SPAN):
                    apart = apart[root[a[apart]] != root[b[apart]]]
                if sets is not None:
                    apart = apart[sets.may_match(a[apart], b[apart], mode == SURE)]
                if mode in (SURE, SPAN):
                    apart, root = _spanning(a, b, apart, root)
                if len(apart):
                    yield batch_of(number[a[apart]], number[b[apart]])
        moved = np.flatnonzero(root != np.arange(len(root)))
        if mode == FOREST and len(moved):
            yield batch_of(number[moved], number[root[moved]])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held = None
        for batch in batches:
            if not batch.num_rows:
                continue
            table = pa.Table.from_batches([batch])
            table = table if held is None else pa.concat_tables([held, table])
            key, part = table["key"].to_numpy(), table["part"].to_numpy()
            begin = np.flatnonzero(np.concatenate([[True], (key[1:] != key[:-1]) | (part[1:] != part[:-1])]))
            for i, j in zip(begin[:-1].tolist(), begin[1:].tolist(), strict=True):
                if j - i > 1:
                    yield from settle(int(key[i]), table.slice(i, j - i))
            held = table.slice(int(begin[-1]))
        if held is not None and held.num_rows > 1:
            yield from settle(int(held["key"][0].as_py()), held)

    return run


def code_links(codes: DataFrame, tables: Tables, words: int, radius: int, mode: str = FOREST) -> DataFrame:
    """codes (id, label, w0 [, w1]), ids distinct -> links (a, b) of ids whose codes lie within the radius (see _search).

    SURE, SPAN and EVERY also need the columns shingles and parity of the codes' sets.
    Links are written, each once; what was dealt out for the search is dropped then.
    """
    columns = [f"w{i}" for i in range(words)]
    sets = SETS if mode in (SURE, SPAN, EVERY) else {}
    fields = "key long, place long, id long, label long" + "".join(f", {c} long" for c in columns) + "".join(f", {c} {t}" for c, t in sets.items())
    dealt = materialize(codes.select("id", "label", *columns, *sets).mapInArrow(_deal(tables, words), fields))
    hot = materialize(dealt.groupBy("key").agg(F.count("*").alias("n")).where(F.col("n") > MEMBERS))
    keys = ["key", "part", "id", "label", "member", *columns, *sets]
    rows = dealt.join(hot, "key", "left_anti").withColumn("part", F.lit(0)).withColumn("member", F.lit(True)).select(*keys)
    most = hot.agg(F.max("n")).first()[0]
    if most:
        # Cut full slices along the Gray order; a part's shared bits are its upper node, and codes visit the parts it allows.
        pieces = math.ceil(most / MEMBERS) * 2
        inside = dealt.join(hot.select("key"), "key")
        cuts = inside.groupBy("key").agg(F.array_distinct(F.percentile_approx("place", [i / pieces for i in range(1, pieces)], 50 * pieces)).alias("cuts"))
        placed = inside.join(cuts, "key").withColumn("part", F.size(F.filter("cuts", lambda c: c <= F.col("place")))).drop("cuts")
        placed = materialize(placed)
        nodes = placed.groupBy("key", "part").agg(*[F.bit_and(c).alias(f"and_{c}") for c in columns], *[F.bit_or(c).alias(f"or_{c}") for c in columns])
        off = F.lit(0)
        for c in columns:  # a part's codes agree on the bits where "and" equals "or"
            shared = F.bitwise_not(F.col(f"and_{c}").bitwiseXOR(F.col(f"or_{c}")))
            off = off + F.bit_count(F.col(c).bitwiseXOR(F.col(f"and_{c}")).bitwiseAND(shared))
        visits = placed.withColumnRenamed("part", "home").join(materialize(nodes), "key").where((F.col("part") <= F.col("home")) & (off <= radius))
        rows = rows.union(visits.withColumn("member", F.col("part") == F.col("home")).select(*keys))
    found = rows.repartition("key", "part").sortWithinPartitions("key", "part", "id").mapInArrow(_search(tables, words, radius, mode), "a long, b long")
    links = materialize(found.distinct())
    discard(dealt)
    return links


def link_fingerprints(codes: DataFrame, radius: int = RADIUS) -> DataFrame:
    """Distinct codes (column code) -> (node, root) for every code that has a link; codes are their own ids."""
    rows = codes.select(F.col("code").alias("id"), F.col("code").alias("label"), F.col("code").alias("w0"))
    return connected_components(code_links(rows, exact_tables(codes.count(), radius), 1, radius))


def _fingerprint(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        codes = fingerprints(batch.column("text")).view(np.int64)
        yield pa.RecordBatch.from_pydict({"doc_id": batch.column("doc_id"), "code": pa.array(codes)})


def components(docs: DataFrame, radius: int = RADIUS) -> DataFrame:
    """A row per document: doc_id, fingerprint (16 hex digits), component_id (least doc_id reachable by links).

    A null or wordless text has fingerprint zero, linked like any other; a null id is ignored as a least id, and such a
    row has the component of its text; repeated rows stay; an empty table gives no row; other columns are not read.
    """
    rows = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text"))
    marked = materialize_texts(rows.mapInArrow(_fingerprint, "doc_id long, code long"))
    codes = materialize(marked.groupBy("code").agg(F.min("doc_id").alias("least")))
    roots = link_fingerprints(codes.select("code"), radius)
    rooted = codes.join(roots.withColumnRenamed("node", "code"), "code", "left").withColumn("root", F.coalesce("root", "code"))
    least = rooted.groupBy("root").agg(F.min("least").alias("component_id"))
    labels = rooted.join(least, "root").select("code", "component_id")
    return marked.join(labels, "code").select("doc_id", F.lower(F.lpad(F.hex("code"), 16, "0")).alias("fingerprint"), "component_id")


def _sketch(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Per text the hash and size of its shingle set, and its wide fingerprint."""
    for batch in batches:
        first = 0
        for value, cuts in shingle_sets(batch.column("text")):
            mixed = mix64(value)
            total = np.concatenate([np.zeros(1, dtype=np.uint64), np.cumsum(mixed, dtype=np.uint64)])
            odd = [parity(mixed[i:j]) for i, j in zip(cuts[:-1], cuts[1:], strict=True)]
            content = mix64(total[cuts[1:]] - total[cuts[:-1]] + np.diff(cuts).astype(np.uint64))
            codes = majority(np.stack([mix64(value + np.uint64(7919 * (w + 1))) for w in range(NEAR_WORDS)], axis=1), cuts)
            part = batch.slice(first, len(cuts) - 1)
            first += len(cuts) - 1
            yield pa.RecordBatch.from_pydict({"rid": part.column("rid"), "k1": part.column("k1"), "k2": part.column("k2"), "doc_id": part.column("doc_id"), "content": pa.array(content.view(np.int64)), "shingles": pa.array(np.diff(cuts).astype(np.int64)), "parity": pa.array(odd, pa.binary()), **_columns(codes)})


def _sets(column: pa.Array) -> list[np.ndarray]:
    return [value[i:j] for value, cuts in shingle_sets(column) for i, j in zip(cuts[:-1], cuts[1:], strict=True)]


def _check_pairs(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for whole in batches:
        for low in range(0, whole.num_rows, 256):
            batch = whole.slice(low, 256)
            left, right = _sets(batch.column("text_a")), _sets(batch.column("text_b"))
            common = np.array([len(np.intersect1d(x, y, assume_unique=True)) for x, y in zip(left, right, strict=True)], dtype=np.int64)
            near = pa.array(similar(common, np.array([len(x) for x in left], dtype=np.int64), np.array([len(x) for x in right], dtype=np.int64)))
            yield pa.RecordBatch.from_pydict({"a": batch.column("a").filter(near), "b": batch.column("b").filter(near)})


def verified(pairs: DataFrame, texts: DataFrame) -> DataFrame:
    """The pairs (a, b) of row numbers whose texts (rid, text) have a similarity of 0.8 at least, decided on whole texts.

    A text that many pairs name is dealt to several tasks, so that no task sees more than VERIFY_ROWS of its pairs.
    """
    often = pairs.groupBy("a").agg(F.ceil(F.count("*") / VERIFY_ROWS).cast("int").alias("deals"))
    left = often.join(texts.select(F.col("rid").alias("a"), F.col("text").alias("text_a")), "a")
    left = left.withColumn("deal", F.explode(F.sequence(F.lit(0), F.col("deals") - 1))).drop("deals")
    asked = pairs.join(often, "a").withColumn("deal", F.pmod(F.xxhash64("b"), F.col("deals")).cast("int")).drop("deals")
    asked = asked.join(texts.select(F.col("rid").alias("b"), F.col("text").alias("text_b")), "b")
    return materialize_texts(asked.join(left, ["a", "deal"]).select("a", "b", "text_a", "text_b").mapInArrow(_check_pairs, "a long, b long"))


def near_copies(docs: DataFrame) -> DataFrame:
    """(rid, k1, k2, doc_id, root) for each row of docs (doc_id, text): rows with one root are linked through pairs of
    similarity >= 0.8; k1 and k2 are hashes of id and text.

    Texts with one shingle set collapse. Of the texts that have a neighbour in some slice, pairs that sizes and parities do not
    rule out are checked: twice as few as join each slice, then all whose texts are in different components after that.
    """
    keyed = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text"), *content_keys("doc_id", "text"))
    words = [f"w{i}" for i in range(NEAR_WORDS)]
    fields = "rid long, k1 long, k2 long, doc_id long, content long, shingles long, parity binary" + "".join(f", {w} long" for w in words)
    marked = materialize_texts(keyed.withColumn("rid", F.monotonically_increasing_id()).mapInArrow(_sketch, fields))
    same = ["content", "shingles", *words]
    alike = materialize(marked.groupBy(*same).agg(F.min("rid").alias("first")))
    codes = alike.where("shingles > 0").select(F.col("first").alias("id"), F.col("first").alias("label"), *words)
    tables = sampled_tables(codes.count())
    pairs = code_links(codes, tables, NEAR_WORDS, NEAR_RADIUS, FIRST)
    met = materialize(pairs.select(F.col("a").alias("id")).union(pairs.select("b")).distinct())
    asked = materialize(marked.join(met, marked["rid"] == met["id"]).select("id", "k1", "k2", *SETS, *words))
    named = asked.select(F.col("id").alias("rid"), "k1", "k2")
    body = materialize(keyed.select("k1", "k2", "text").join(named, ["k1", "k2"]).dropDuplicates(["k1", "k2", "rid"]).select("rid", "text"))
    tables = sampled_tables(asked.count())
    labelled, links, tried = asked.withColumn("label", F.col("id")), None, None
    for mode in (SURE, SPAN, EVERY):
        pairs = code_links(labelled, tables, NEAR_WORDS, NEAR_RADIUS, mode)
        pairs = pairs if tried is None else materialize(pairs.join(tried, ["a", "b"], "left_anti"))
        found = verified(pairs, body)
        links, tried = (found, pairs) if links is None else (links.union(found), tried.union(pairs))
        roots = materialize(connected_components(links))
        labelled = asked.join(roots.withColumnRenamed("node", "id"), "id", "left").withColumn("label", F.coalesce("root", "id"))
    roots = roots.withColumnRenamed("node", "first")
    discard(body)
    rooted = alike.join(roots, "first", "left").select(*same, F.coalesce("root", "first").alias("root"))
    return marked.join(rooted, same).select("rid", "k1", "k2", "doc_id", "root")


def keep_one(docs: DataFrame) -> DataFrame:
    """One row of each group of near copies, the one with the least id (rows without an id last), with its own columns.

    Texts with equal shingle sets, wordless and null ones among them, are copies; ids decide nothing but which row stays,
    so rows without an id and different texts under one id are kept like any other, and of rows that agree in id and text
    any one. Columns beyond doc_id and text may have any name; an empty table gives no row.
    """

    def work(named: DataFrame) -> DataFrame:
        least = F.min(F.struct(F.col("doc_id").isNull().alias("none"), "doc_id", "k1", "k2")).alias("best")
        best = near_copies(named).groupBy("root").agg(least).select("best.k1", "best.k2").distinct()
        rows = named.select("*", *content_keys("doc_id", "text"))
        return rows.join(best, ["k1", "k2"], "left_semi").dropDuplicates(["k1", "k2"])

    return guarded(docs, work)


def query(spark, sf_dir: str) -> DataFrame:
    return components(spark.read.parquet(f"{sf_dir}/documents.parquet"))
