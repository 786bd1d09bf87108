"""Removal of byte strings that stand earlier in the corpus, by a run-length-compressed suffix index.

Routing. Each 100-byte window is owned by an anchor, its least-hashed 32-gram (leftmost on ties), so equal windows have
equal anchors wherever they stand. Neighbouring windows with one anchor form a segment: about 35 windows in 134 bytes.
Segments meet by anchor hash. Segments of equal content collapse to the earliest, every other copy is removed as a whole;
an anchor with one content only has no more to find.

Matching. Where an anchor has several contents, the segments are indexed block by block: a suffix order of the block is
reduced to a run-length-compressed Burrows-Wheeler transform with sampled run ends and the common prefix at each run
boundary, the suffix order is dropped, and matching statistics (for each position its neighbour in suffix order
and the length they share) are streamed from those samples. Positions that share at least 100 bytes are chained, and
all but the earliest of a chain are marked.

An anchor with very many contents is re-anchored: each of its windows becomes its own segment, which spreads the group.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from floorwalk.llm.runtime import guarded, materialize
from floorwalk.llm.textkit import ANCHOR, HASH_A, HASH_B, as_bytes, mix64

LENGTH, GRAM = 100, 32
PIECE_BYTES, BLOCK_BYTES = 1 << 20, 3 << 19
HOT_CONTENTS = 4096
DUP, FIRST = 0, 1


def sliding_min(x: np.ndarray, width: int) -> np.ndarray:
    size = 1
    while size * 2 <= width:
        x = np.minimum(x[:-size], x[size:])
        size *= 2
    if size < width:
        x = np.minimum(x[: len(x) - (width - size)], x[width - size :])
    return x


def segments(data: np.ndarray, offsets: np.ndarray, length: int, gram: int) -> tuple[np.ndarray, ...]:
    """Anchor hash, content hash, text number, first window and number of windows of every segment."""
    none = (np.zeros(0, np.uint64), np.zeros(0, np.uint64), *(np.zeros(0, np.int64) for _ in range(3)))
    if len(data) < length:
        return none
    width = length - gram + 1
    x = ANCHOR.grams(data, gram)
    low = sliding_min(x, width)
    # A window that would cross the end of its text does not count.
    step = np.zeros(len(data) + 1, dtype=np.int64)
    np.add.at(step, np.maximum(offsets[1:-1] - length + 1, offsets[:-2]), 1)
    np.add.at(step, offsets[1:-1], -1)
    short = np.flatnonzero(np.diff(offsets) < length)
    np.add.at(step, offsets[short], 1)
    np.add.at(step, offsets[short + 1], -1)
    valid = (np.cumsum(step)[: len(low)] == 0)
    begin = valid.copy()
    begin[1:] &= ~valid[:-1] | (low[1:] != low[:-1]) | (x[: len(low) - 1] == low[:-1])
    stop = valid.copy()
    stop[:-1] &= ~valid[1:] | begin[1:]
    first, last = np.flatnonzero(begin), np.flatnonzero(stop)
    if not len(first):
        return none
    content = HASH_B.spans(HASH_B.prefix(data), first, last + length)
    doc = np.searchsorted(offsets, first, side="right") - 1
    return low[first], content, doc, first, last - first + 1


def _pieces(column: pa.Array, overlap: int):
    """Groups of (text number, place in the text, bytes), about PIECE_BYTES together; long texts in overlapping parts."""
    data, offsets = as_bytes(column)
    group, size = [], 0
    for i in range(len(offsets) - 1):
        a, b = int(offsets[i]), int(offsets[i + 1])
        at = a
        while at < b:
            end = min(b, at + PIECE_BYTES)
            group.append((i, at - a, data[at:end]))
            size += end - at
            if size >= PIECE_BYTES:
                yield group
                group, size = [], 0
            if end == b:
                break
            at = end - overlap
    if group:
        yield group


def merge_runs(doc: np.ndarray, start: np.ndarray, count: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Joins neighbouring runs of windows of one document."""
    order = np.lexsort((start, doc))
    doc, start, count = doc[order], start[order], count[order]
    if not len(doc):
        return doc, start, count
    new_doc = np.diff(doc, prepend=doc[0] - 1) != 0
    end = start + count
    # Furthest end so far inside the document, by an offset that keeps documents apart.
    shift = (np.cumsum(new_doc) - 1) * (int(end.max()) + 1)
    reach = np.maximum.accumulate(end + shift) - shift
    begin = new_doc.copy()
    begin[1:] |= start[1:] > reach[:-1]
    at = np.flatnonzero(begin)
    stop = reach[np.append(at[1:], len(doc)) - 1]
    return doc[at], start[at], stop - start[at]


def _anchor(length: int, gram: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        """Segments of a batch; copies inside the batch are settled here and leave as removed runs."""
        for batch in batches:
            ids = batch.column("doc_id").to_numpy(zero_copy_only=False)
            found = []
            for group in _pieces(batch.column("text"), length - 1):
                sizes = np.array([len(p[2]) for p in group])
                offsets = np.concatenate([[0], np.cumsum(sizes)])
                a, g, piece, first, count = segments(np.concatenate([p[2] for p in group]), offsets, length, gram)
                number, base = np.array([p[0] for p in group]), np.array([p[1] for p in group])
                found.append((a, g, ids[number[piece]], first - offsets[piece] + base[piece], count))
            if not found:
                continue
            anchor, content, doc, start, count = (np.concatenate(x) for x in zip(*found, strict=True))
            both = mix64(anchor ^ (content * np.uint64(0x9E3779B97F4A7C15)))
            order = np.lexsort((start, doc, both))
            same = np.zeros(len(order), dtype=bool)
            same[1:] = both[order[1:]] == both[order[:-1]]
            kept, copies = order[~same], order[same]
            # A repeated row of the document that stands first is not a copy.
            head = kept[np.cumsum(~same)[same] - 1]
            copies = copies[(doc[copies] != doc[head]) | (start[copies] != start[head])]
            d, s, c = merge_runs(doc[copies], start[copies], count[copies])
            yield pa.RecordBatch.from_pydict({
                "anchor": pa.array(np.concatenate([anchor[kept], mix64(d.astype(np.uint64) + np.uint64(1))]).view(np.int64)),
                "content": pa.array(np.concatenate([content[kept].view(np.int64), np.zeros(len(d), np.int64)])),
                "doc_id": pa.array(np.concatenate([doc[kept], d])), "start": pa.array(np.concatenate([start[kept], s])),
                "windows": pa.array(np.concatenate([count[kept], c])), "settled": pa.array(np.arange(len(kept) + len(d)) >= len(kept)),
            })

    return run


ANCHORED = "anchor long, content long, doc_id long, start long, windows long, settled boolean"
SETTLED = "kind int, anchor long, doc_id long, start long, windows long"


def _settle(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Rows come sorted by anchor, content, document, start. Copies leave as removed runs (DUP); of an anchor with two
    contents or more, the earliest row of each content leaves as FIRST. Holds one row between batches."""
    carry, waiting = None, False
    for batch in batches:
        table = {n: batch.column(n).to_numpy(zero_copy_only=False) for n in ("anchor", "content", "doc_id", "start", "windows", "settled")}
        ready, live = np.flatnonzero(table["settled"]), np.flatnonzero(~table["settled"])
        rows = {n: v[live] for n, v in table.items()}
        out = [(DUP, *(table[n][ready] for n in ("anchor", "doc_id", "start", "windows")))]
        had = carry is not None
        if had:
            rows = {n: np.concatenate([carry[n], v]) for n, v in rows.items()}
        anchor, content = rows["anchor"], rows["content"]
        if len(anchor):
            new_anchor = np.ones(len(anchor), dtype=bool)
            new_anchor[1:] = anchor[1:] != anchor[:-1]
            new_class = new_anchor.copy()
            new_class[1:] |= content[1:] != content[:-1]
            first = np.flatnonzero(new_class)
            owner = first[np.cumsum(new_class) - 1]
            copy = np.flatnonzero((rows["doc_id"] != rows["doc_id"][owner]) | (rows["start"] != rows["start"][owner]))
            out.append((DUP, *(rows[n][copy] for n in ("anchor", "doc_id", "start", "windows"))))
            group = np.cumsum(new_anchor)[first] - 1
            classes = np.bincount(group)
            several = classes[group] > 1
            if had and not waiting:  # this anchor's contents are on their way already; only the carried row is out
                several[group == 0] = True
                several[0] = False
            chosen = first[several]
            out.append((FIRST, *(rows[n][chosen] for n in ("anchor", "doc_id", "start", "windows"))))
            last_group_old = had and not waiting and group[-1] == 0
            waiting = classes[-1] == 1 and not last_group_old
            carry = {n: v[first[-1] : first[-1] + 1] for n, v in rows.items()}
        kind = np.concatenate([np.full(len(x[1]), x[0], dtype=np.int32) for x in out])
        if len(kind):
            columns = [np.concatenate([x[i] for x in out]) for i in range(1, 5)]
            yield pa.RecordBatch.from_arrays([pa.array(kind), *map(pa.array, columns)], names=["kind", "anchor", "doc_id", "start", "windows"])


def settle(anchored: DataFrame) -> DataFrame:
    return anchored.repartition("anchor").sortWithinPartitions("anchor", "content", "doc_id", "start").mapInArrow(_settle, SETTLED)


class RunLengthIndex:
    """Run-compressed Burrows-Wheeler transform of a collection of byte strings, with samples at the ends of its runs.

    Of the suffix order only this stays: for each run its symbol and length, the text position at its first and last row,
    and the length of the prefix that its first suffix shares with the suffix before it. That is enough to walk from any
    text position to its neighbour in suffix order and to know how much the two share.
    """

    def __init__(self, strings: list[bytes]) -> None:
        sizes = np.array([len(s) for s in strings], dtype=np.int64)
        self.first = np.concatenate([[0], np.cumsum(sizes + 1)[:-1]])
        self.n = int((sizes + 1).sum())
        number = np.repeat(np.arange(len(strings)), sizes + 1)
        end = np.repeat(self.first + sizes, sizes + 1)
        symbol = np.frombuffer(b"\0".join(strings) + b"\0", dtype=np.uint8).astype(np.int64) + 1
        symbol[self.first + sizes] = 0
        order = self._suffix_order(symbol, end, number)
        before = np.where(order == self.first[number[order]], -1 - number[order], symbol[order - 1])
        head = np.ones(self.n, dtype=bool)
        head[1:] = before[1:] != before[:-1]
        start = np.flatnonzero(head)
        self.run_symbol = before[start]
        self.run_length = np.diff(np.append(start, self.n))
        self.run_first = order[start]
        self.run_last = order[start + self.run_length - 1]
        self.shared = np.zeros(len(start), dtype=np.int64)
        self.shared[1:] = self._common(symbol, end, self.run_first[1:], self.run_last[:-1])

    @staticmethod
    def _suffix_order(symbol: np.ndarray, end: np.ndarray, number: np.ndarray) -> np.ndarray:
        """Order of all suffixes by prefix doubling; a string's end sorts first, ends by string number."""
        n, place = len(symbol), np.arange(len(symbol))
        key, size = np.zeros(n, dtype=np.uint64), 7
        for j in range(size):
            at = np.minimum(place + j, n - 1)
            key = (key << np.uint64(9)) | np.where(place + j < end, symbol[at], 0).astype(np.uint64)
        strings = int(number[-1]) + 1
        while True:
            order = np.argsort(key)
            fresh = np.zeros(n, dtype=np.int64)
            fresh[1:] = key[order[1:]] != key[order[:-1]]
            rank = np.empty(n, dtype=np.int64)
            rank[order] = np.cumsum(fresh)
            if rank[order[-1]] == n - 1:
                return order
            far = place + size
            second = np.where(far < end, rank[np.minimum(far, n - 1)] + strings, number)
            key = (rank.astype(np.uint64) * np.uint64(n + strings)) + second.astype(np.uint64)
            size *= 2

    @staticmethod
    def _common(symbol: np.ndarray, end: np.ndarray, a: np.ndarray, b: np.ndarray) -> np.ndarray:
        """Length of the prefix that the suffixes at a and b share; ends never match."""
        length, live, limit = np.zeros(len(a), dtype=np.int64), np.arange(len(a)), np.minimum(end[a] - a, end[b] - b)
        while len(live):
            at = length[live]
            go = at < limit[live]
            live, at = live[go], at[go]
            live = live[symbol[a[live] + at] == symbol[b[live] + at]]
            length[live] += 1
        return length

    def matching_statistics(self) -> tuple[np.ndarray, np.ndarray]:
        """For every text position: its predecessor in suffix order and the length they share, from the run samples.

        Going right by one position inside a run keeps the neighbour and shortens the match by one, so each position
        reads the nearest sample at or before it.
        """
        order = np.argsort(self.run_first)
        sample = self.run_first[order]
        previous = np.concatenate([[-1], self.run_last[:-1]])[order]
        at = np.searchsorted(sample, np.arange(self.n), side="right") - 1
        gone = np.arange(self.n) - sample[at]
        length = np.where(previous[at] < 0, 0, self.shared[order][at] - gone)
        return previous[at] + gone, np.maximum(length, 0)

    def later_copies(self, length: int) -> np.ndarray:
        """Flags positions whose next length bytes also start at an earlier position of the collection."""
        neighbour, shared = self.matching_statistics()
        place = np.arange(self.n)
        head = np.where(shared >= length, neighbour, place)
        while True:
            far = head[head]
            if np.array_equal(far, head):
                break
            head = far
        earliest = np.full(self.n, self.n, dtype=np.int64)
        np.minimum.at(earliest, head, place)
        return earliest[head] < place


def _match(length: int):
    def block(rows: list[tuple]) -> pa.RecordBatch | None:
        index = RunLengthIndex([r[3] for r in rows])
        flag = index.later_copies(length)
        edge = np.diff(flag.astype(np.int8), prepend=0, append=0)
        begin, stop = np.flatnonzero(edge == 1), np.flatnonzero(edge == -1)
        owner = np.searchsorted(index.first, begin, side="right") - 1
        if not len(begin):
            return None
        doc, start = np.array([r[1] for r in rows], dtype=np.int64), np.array([r[2] for r in rows], dtype=np.int64)
        return pa.RecordBatch.from_pydict({"doc_id": pa.array(doc[owner]), "start": pa.array(start[owner] + begin - index.first[owner]), "windows": pa.array((stop - begin).astype(np.int64))})

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        """Segments sorted by anchor, document, start: whole anchors go to an index of about BLOCK_BYTES."""
        rows, size = [], 0
        for batch in batches:
            for row in zip(*(batch.column(n).to_pylist() for n in ("anchor", "doc_id", "start", "segment")), strict=True):
                if size >= BLOCK_BYTES and row[0] != rows[-1][0]:
                    if (out := block(rows)) is not None:
                        yield out
                    rows, size = [], 0
                rows.append(row)
                size += len(row[3])
        if rows and (out := block(rows)) is not None:
            yield out

    return run


def _cut_segments(length: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            data, offsets = as_bytes(batch.column("text"))
            rows = []
            for i, (doc, parts) in enumerate(zip(batch.column("doc_id").to_pylist(), batch.column("parts").to_pylist(), strict=True)):
                for p in parts:
                    a = int(offsets[i]) + p["start"]
                    rows.append((p["anchor"], doc, p["start"], data[a : a + p["windows"] + length - 1].tobytes()))
            yield pa.RecordBatch.from_arrays([pa.array([r[k] for r in rows], type=t) for k, t in enumerate((pa.int64(), pa.int64(), pa.int64(), pa.binary()))], names=["anchor", "doc_id", "start", "segment"])

    return run


def _cut_windows(length: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        """Every window of the given segments as a segment of its own."""
        for batch in batches:
            data, offsets = as_bytes(batch.column("text"))
            for i, (doc, parts) in enumerate(zip(batch.column("doc_id").to_pylist(), batch.column("parts").to_pylist(), strict=True)):
                text = data[offsets[i] : offsets[i + 1]]
                start = np.concatenate([np.arange(p["start"], p["start"] + p["windows"]) for p in parts])
                n = len(start)
                yield pa.RecordBatch.from_pydict({
                    "anchor": pa.array(HASH_A.spans(HASH_A.prefix(text), start, start + length).view(np.int64)),
                    "content": pa.array(HASH_B.spans(HASH_B.prefix(text), start, start + length).view(np.int64)),
                    "doc_id": pa.array(np.full(n, doc, dtype=np.int64)), "start": pa.array(start.astype(np.int64)),
                    "windows": pa.array(np.ones(n, dtype=np.int64)), "settled": pa.array(np.zeros(n, dtype=bool)),
                })

    return run


def removed_runs(docs: DataFrame, length: int = LENGTH, gram: int = GRAM) -> DataFrame:
    """(doc_id, start, windows): runs of window starts whose windows all start earlier in the corpus, too."""
    texts = docs.where("doc_id is not null and text is not null").select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text"))
    first = materialize(settle(texts.mapInArrow(_anchor(length, gram), ANCHORED)))
    open_rows = first.where(F.col("kind") == FIRST)
    hot = open_rows.groupBy("anchor").agg(F.count("*").alias("contents")).where(F.col("contents") > HOT_CONTENTS)
    hot = materialize(hot.select("anchor"))

    def with_texts(rows: DataFrame) -> DataFrame:
        asked = rows.groupBy("doc_id").agg(F.collect_list(F.struct("anchor", "start", "windows")).alias("parts"))
        return texts.join(asked.hint("shuffle_hash"), "doc_id")

    cut = with_texts(open_rows.join(hot, "anchor", "left_anti")).mapInArrow(_cut_segments(length), "anchor long, doc_id long, start long, segment binary")
    matched = cut.repartition("anchor").sortWithinPartitions("anchor", "doc_id", "start").mapInArrow(_match(length), "doc_id long, start long, windows long")
    windows = with_texts(open_rows.join(hot, "anchor", "left_semi")).mapInArrow(_cut_windows(length), ANCHORED)
    spread = settle(windows).where(F.col("kind") == DUP)
    runs = [x.select("doc_id", "start", "windows") for x in (first.where(F.col("kind") == DUP), matched, spread)]
    return runs[0].union(runs[1]).union(runs[2])


def _apply(length: int, keep_text: bool):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            data, offsets = as_bytes(batch.column("text"))
            out = []
            for i, runs in enumerate(batch.column("runs").to_pylist()):
                text = data[offsets[i] : offsets[i + 1]]
                keep, spans = np.ones(len(text), dtype=bool), 0
                if runs:
                    start = np.array([r["start"] for r in runs], dtype=np.int64)
                    stop = start + np.array([r["windows"] for r in runs], dtype=np.int64) + length - 1
                    depth = np.zeros(len(text) + 1, dtype=np.int64)
                    np.add.at(depth, np.minimum(start, len(text)), 1)
                    np.add.at(depth, np.minimum(stop, len(text)), -1)
                    keep = np.cumsum(depth)[:-1] == 0
                    spans = int(((~keep) & np.concatenate([[True], keep[:-1]])).sum()) if len(text) else 0
                left = text[keep].tobytes()
                row = [len(text), len(text) - len(left), spans, hashlib.sha256(left).hexdigest()]
                out.append([*row, left.decode("utf-8", "ignore")] if keep_text else row)
            kinds = (pa.int64(), pa.int64(), pa.int64(), pa.string(), pa.string())
            names = ("n_bytes", "n_removed", "n_spans", "kept_sha256", "kept_text")
            columns = [pa.array([r[k] for r in out], type=kinds[k]) for k in range(5 if keep_text else 4)]
            rest = batch.drop_columns(["runs"] if keep_text else ["runs", "text"])
            yield pa.RecordBatch.from_arrays([*rest.columns, *columns], names=[*rest.schema.names, *names[: len(columns)]])

    return run


def deduplicate(docs: DataFrame, length: int = LENGTH, gram: int = GRAM, keep_text: bool = False) -> DataFrame:
    """doc_id (keep_text: all columns of docs) with n_bytes, n_removed, n_spans, kept_sha256 [, kept_text].

    A null text is empty; texts shorter than the length keep everything; a document without an id is kept whole and
    counts as no one's source; rows that repeat an id are one document and get the same marks; an empty table gives no
    row. kept_text drops what is left of a character that a removed run cuts.
    """
    runs = removed_runs(docs, length, gram).groupBy("doc_id").agg(F.collect_list(F.struct("start", "windows")).alias("runs"))
    rows = docs if keep_text else docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text"))
    joined = rows.alias("d").join(runs.alias("r").hint("shuffle_hash"), F.col("d.doc_id") == F.col("r.doc_id"), "left").select("d.*", "r.runs")
    inherited = [f for f in joined.schema.fields if f.name != "runs" and (keep_text or f.name != "text")]
    extra = "n_bytes long, n_removed long, n_spans long, kept_sha256 string" + (", kept_text string" if keep_text else "")
    schema = ", ".join([*[f"`{f.name}` {f.dataType.simpleString()}" for f in inherited], extra])
    return joined.mapInArrow(_apply(length, keep_text), schema)


def clean(docs: DataFrame, **options) -> DataFrame:
    """The documents with repeated passages cut out of their texts (n_chars follows); their own columns, of any name."""

    def work(named: DataFrame) -> DataFrame:
        out = deduplicate(named, keep_text=True, **options).withColumn("text", F.col("kept_text"))
        if "n_chars" in named.columns:
            out = out.withColumn("n_chars", F.length("text").cast(named.schema["n_chars"].dataType))
        return out

    return guarded(docs, work)


def query(spark, sf_dir: str) -> DataFrame:
    return deduplicate(spark.read.parquet(f"{sf_dir}/documents.parquet"))
