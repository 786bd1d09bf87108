"""Bounded-space online packing of tokenised documents into fixed windows.

Each partition keeps at most OPEN windows open. A document's full windows leave at once; its rest goes into the open
window that it fills best; when none has room and all places are taken, the fullest is emitted. What is still open at the
end of the partitions is merged: the leftover pieces are dealt into groups of bounded size and packed best-fit-decreasing.
"""

from __future__ import annotations

import zlib
from bisect import bisect_left, insort
from collections.abc import Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from floorwalk.llm.runtime import materialize
from floorwalk.llm.textkit import HASH_A, HASH_B, TO_LOWER, Chunk, chunks

WINDOW, OPEN, END_ID = 4096, 64, 2
LEFTOVER_GROUP = 8192
CACHE_UNITS, LINE_WORDS, CHUNK = 400_000, 256, 1 << 20
MARKS = (".", ",")
IS_LETTER = np.zeros(256, dtype=bool)
IS_LETTER[65:91] = IS_LETTER[97:123] = True
_workers: dict[str, "WordCache"] = {}


def vocabulary() -> str:
    """Path of the public vocabulary file of the contract."""
    import public_tokenizers

    return public_tokenizers.path("word_bpe_49k.json")


class WordCache:
    """Token ids of texts by way of their white-space-separated words, all look-ups vectorised.

    The tokenizer drops white space and never looks across it, so a text's ids are its words' ids in order. A word of Latin
    letters, perhaps with one mark at its end, folds to a lower-case stem (and a mark) of one pre-token each, so such words
    share their stem's ids; any other word is a unit as it stands. Units are known by a 64-bit hash in sorted order; their
    ids stand end to end in one array. At CACHE_UNITS units the cache keeps those that at least two chunks asked for.
    """

    def __init__(self, path: str) -> None:
        from tokenizers import Tokenizer

        self.tokenizer = Tokenizer.from_file(path)
        vocab = self.tokenizer.get_vocab()
        self.ends = np.zeros(max(vocab.values()) + 1, dtype=bool)
        self.ends[[i for t, i in vocab.items() if t.endswith("</w>")]] = True
        self.marks = [np.array(self.tokenizer.encode(m, add_special_tokens=False).ids, dtype="<u4") for m in MARKS]
        self._clear()

    def _clear(self) -> None:
        self.key = np.zeros(0, dtype=np.uint64)
        self.at, self.length, self.used = (np.zeros(0, dtype=np.int64) for _ in range(3))
        self.ids = np.concatenate([np.zeros(0, dtype="<u4"), *self.marks])

    def _add(self, key: np.ndarray, ids: np.ndarray, length: np.ndarray) -> None:
        order = np.argsort(key)
        at = len(self.ids) + np.cumsum(length) - length
        place = np.searchsorted(self.key, key[order])
        new = ((self.key, key), (self.at, at), (self.length, length), (self.used, np.zeros(len(key), dtype=np.int64)))
        self.key, self.at, self.length, self.used = (np.insert(old, place, values[order]) for old, values in new)
        self.ids = np.concatenate([self.ids, ids])

    def _evict(self) -> None:
        keep = np.flatnonzero(self.used > 1)
        if len(keep) > CACHE_UNITS // 2:
            keep = np.sort(keep[np.argsort(-self.used[keep], kind="stable")[: CACHE_UNITS // 2]])
        key, at, length, ids = self.key[keep], self.at[keep], self.length[keep], self.ids
        self._clear()
        before = np.cumsum(length) - length
        self._add(key, ids[np.repeat(at - before, length) + np.arange(int(length.sum()))], length)

    def _learn(self, raw: bytes, folded: bytes, key: np.ndarray, start: np.ndarray, end: np.ndarray, stem: np.ndarray) -> None:
        pick = np.flatnonzero(stem)
        if len(pick):
            stems = [folded[a:b] for a, b in zip(start[pick].tolist(), end[pick].tolist(), strict=True)]
            lines = [b" ".join(stems[i : i + LINE_WORDS]).decode() for i in range(0, len(stems), LINE_WORDS)]
            ids = np.array([i for e in self.tokenizer.encode_batch_fast(lines, add_special_tokens=False) for i in e.ids], dtype="<u4")
            cut = np.flatnonzero(self.ends[ids]) + 1
            if len(cut) != len(stems):
                raise ValueError("a stem is not one pre-token of this vocabulary")
            self._add(key[pick], ids, np.diff(cut, prepend=0))
        pick = np.flatnonzero(~stem)
        if len(pick):
            words = [raw[a:b].decode("utf-8", "replace") for a, b in zip(start[pick].tolist(), end[pick].tolist(), strict=True)]
            found = [e.ids for e in self.tokenizer.encode_batch_fast(words, add_special_tokens=False)]
            self._add(key[pick], np.array([i for f in found for i in f], dtype="<u4"), np.array([len(f) for f in found], dtype=np.int64))

    def encode(self, chunk: Chunk) -> tuple[np.ndarray, np.ndarray]:
        """The ids of the chunk's texts end to end, and how many each text has."""
        data = chunk.data
        start, end, doc = chunk.words()
        if not len(start):
            return np.zeros(0, dtype="<u4"), np.zeros(chunk.n_docs, dtype=np.int64)
        folded, letter = fold_letters(data)
        other = np.concatenate([[0], np.cumsum(~letter)])
        last = data[end - 1]
        mark = np.where(last == ord(MARKS[0]), 1, np.where(last == ord(MARKS[1]), 2, 0))
        mark[(other[end - 1] != other[start]) | (end - start < 2)] = 0
        stem = (mark > 0) | (other[end] == other[start])
        stop = end - (mark > 0)
        key = np.where(stem, HASH_A.spans(HASH_A.prefix(folded), start, stop), HASH_B.spans(HASH_B.prefix(data), start, stop))
        units, first, unit = np.unique(key, return_index=True, return_inverse=True)
        if len(self.key) + len(units) > CACHE_UNITS:
            self._evict()
        place = np.minimum(np.searchsorted(self.key, units), max(len(self.key) - 1, 0))
        new = np.flatnonzero(self.key[place] != units) if len(self.key) else np.arange(len(units))
        if len(new):
            one = first[new]
            self._learn(data.tobytes(), folded.tobytes(), units[new], start[one], stop[one], stem[one])
            place = np.searchsorted(self.key, units)
        self.used[place] += 1
        at = np.stack([self.at[place][unit], np.array([0, 0, len(self.marks[0])])[mark]], axis=1).ravel()
        length = np.stack([self.length[place][unit], np.array([0, *map(len, self.marks)])[mark]], axis=1).ravel()
        before = np.cumsum(length) - length
        ids = self.ids[np.repeat(at - before, length) + np.arange(int(length.sum()))]
        return ids, chunk.per_doc(doc, length[0::2] + length[1::2])


def fold_letters(data: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Lower-cased bytes, and which bytes belong to ASCII letters or to composed Latin-1 letters in UTF-8."""
    folded, letter = TO_LOWER[data], IS_LETTER[data]
    if len(data) > 1:
        second = np.flatnonzero((data[:-1] == 0xC3) & (data[1:] >= 0x80) & (data[1:] <= 0xBF) & (data[1:] != 0x97) & (data[1:] != 0xB7)) + 1
        letter[second] = letter[second - 1] = True
        folded[second] += ((data[second] <= 0x9E) * 32).astype(np.uint8)
    return folded, letter


def word_cache(path: str) -> WordCache:
    if path not in _workers:
        _workers[path] = WordCache(path)
    return _workers[path]


class OpenWindows:
    """At most `limit` open windows, best fit; closes the fullest when none fits."""

    def __init__(self, size: int, limit: int) -> None:
        self.size, self.limit = size, limit
        self.room = np.zeros(0, dtype=np.int64)
        self.number: list[int] = []
        self.next = 0

    def place(self, length: int) -> tuple[int, int, int | None]:
        """Window number and offset for a piece, and the number of the window that was emitted for it, if any."""
        fits = np.where(self.room >= length, self.room, self.size + 1)
        at = int(fits.argmin()) if len(fits) else -1
        closed = None
        if at < 0 or self.room[at] < length:
            if len(self.room) < self.limit:
                at = len(self.room)
                self.room = np.append(self.room, self.size)
                self.number.append(self.next)
            else:
                at = int(self.room.argmin())
                closed = self.number[at]
                self.room[at], self.number[at] = self.size, self.next
            self.next += 1
        offset = self.size - int(self.room[at])
        self.room[at] -= length
        return self.number[at], offset, closed


PIECES = "doc_id long, start long, length long, ids_crc32 long, doc_tokens long, sequence_id long, offset long, is_open boolean"


def _pack(path: str, window: int, limit: int, keep_ids: bool):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        cache, windows = word_cache(path), OpenWindows(window, limit)
        base = (TaskContext.get().partitionId() + 1) << 32
        number = 0  # of full windows, counted apart from shared ones
        closed: set[int] = set()
        held: list[list] = []  # pieces of windows that are still open
        end = np.array([END_ID], dtype="<u4").tobytes()

        def table(rows: list[list], is_open: bool) -> pa.RecordBatch:
            columns = [pa.array([r[k] for r in rows], type=pa.int64()) for k in range(7)]
            columns.append(pa.array([is_open] * len(rows)))
            names = [c.split()[0] for c in PIECES.split(", ")]
            if keep_ids:
                columns.append(pa.array([r[7] for r in rows], type=pa.binary()))
                names.append("ids")
            return pa.RecordBatch.from_arrays(columns, names=names)

        for batch in batches:
            docs = batch.column("doc_id").to_pylist()
            for chunk in chunks(batch.column("text"), CHUNK):
                ready: list[list] = []
                ids, count = cache.encode(chunk)
                raw, at = ids.tobytes(), 0
                for doc, n in zip(docs[chunk.first : chunk.first + chunk.n_docs], count.tolist(), strict=True):
                    data = raw[at : at + 4 * n] + end
                    at += 4 * n
                    total = n + 1
                    for start in range(0, total, window):
                        piece = data[4 * start : 4 * (start + window)]
                        length = len(piece) // 4
                        row = [doc, start, length, zlib.crc32(piece), total, 0, 0, piece if keep_ids else None]
                        if length == window:
                            row[5] = base + 2 * number
                            number += 1
                            ready.append(row)
                            continue
                        place, row[6], emitted = windows.place(length)
                        row[5] = base + 2 * place + 1
                        if emitted is not None:
                            closed.add(base + 2 * emitted + 1)
                        held.append(row)
                if closed:
                    ready += [r for r in held if r[5] in closed]
                    held = [r for r in held if r[5] not in closed]
                    closed.clear()
                if ready:
                    yield table(ready, False)
        if held:
            yield table(held, True)

    return run


def best_fit_decreasing(lengths: np.ndarray, size: int) -> tuple[np.ndarray, np.ndarray]:
    """Window number and offset for each piece."""
    number, offset = np.zeros(len(lengths), dtype=np.int64), np.zeros(len(lengths), dtype=np.int64)
    rooms: list[tuple[int, int]] = []
    count = 0
    for i in np.argsort(-lengths, kind="stable"):
        at = bisect_left(rooms, (int(lengths[i]), -1))
        room, window = rooms.pop(at) if at < len(rooms) else (size, count)
        count += window == count
        number[i], offset[i] = window, size - room
        insort(rooms, (room - int(lengths[i]), window))
    return number, offset


def pack(docs: DataFrame, path: str | None = None, window: int = WINDOW, open_windows: int = OPEN, keep_ids: bool = False) -> DataFrame:
    """A row per piece: doc_id, start, length, ids_crc32, doc_tokens, sequence_id, offset [, ids: little-endian u32].

    A null text is empty and packs as its end id alone; a longer document than a window is cut; repeated rows and null ids
    are packed like any other; an empty table gives no row; other columns are not read.
    """
    path = path or vocabulary()
    rows = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text"))
    schema = PIECES + (", ids binary" if keep_ids else "")
    placed = materialize(rows.mapInArrow(_pack(path, window, open_windows, keep_ids), schema))
    left = placed.where("is_open")
    groups = max(1, -(-left.count() // LEFTOVER_GROUP))
    columns = [c for c in placed.columns if c != "is_open"]

    def merge(part: pd.DataFrame) -> pd.DataFrame:
        part = part.sort_values(["doc_id", "start", "ids_crc32"], na_position="last", kind="stable")
        number, part["offset"] = best_fit_decreasing(part["length"].to_numpy(), window)
        part["sequence_id"] = (1 << 61) + part["group"].astype("int64") * (1 << 24) + number
        return part[columns]

    dealt = left.withColumn("group", F.pmod(F.xxhash64("doc_id", "start", "ids_crc32", "sequence_id"), F.lit(groups)))
    merged = dealt.groupBy("group").applyInPandas(merge, placed.select(*columns).schema)
    return placed.where(~F.col("is_open")).select(*columns).unionByName(merged)


def query(spark, sf_dir: str) -> DataFrame:
    return pack(spark.read.parquet(f"{sf_dir}/documents.parquet"))
