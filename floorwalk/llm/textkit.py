"""Vectorised text primitives shared by the operators: words, lines and rolling hashes over Arrow string columns.

Everything works on *chunks*: consecutive texts of one Arrow column, concatenated as UTF-8 bytes, about two megabytes
at a time (a longer text is its own chunk), so that memory stays small whatever the batch holds.
"""

from __future__ import annotations

import contextlib
import ctypes
from collections.abc import Iterator

import numpy as np
import pyarrow as pa

CHUNK_BYTES = 1 << 19
NEWLINE = 10

# Workers live through many stages. Arrow shares the C library's allocator here, and that gives large arrays back at once
# instead of keeping the largest sizes seen so far (-3: M_MMAP_THRESHOLD, -1: M_TRIM_THRESHOLD, -8: M_ARENA_MAX).
pa.set_memory_pool(pa.system_memory_pool())
_libc = None
with contextlib.suppress(OSError, AttributeError):
    _libc = ctypes.CDLL(None)
    _libc.mallopt(-3, 16 << 20)
    _libc.mallopt(-1, 64 << 20)
    _libc.mallopt(-8, 1)


def release() -> None:
    """Gives free memory back to the system; called where a task has dropped what it held."""
    if _libc is not None and hasattr(_libc, "malloc_trim"):
        _libc.malloc_trim(0)


# The white space of the word pattern [^\x20\x09-\x0D]+ as a byte table.
IS_SPACE = np.zeros(256, dtype=bool)
IS_SPACE[[9, 10, 11, 12, 13, 32]] = True
# Lower-casing of A-Z only; other bytes stay.
TO_LOWER = np.arange(256, dtype=np.uint8)
TO_LOWER[65:91] += 32
# First bytes of code points: everything but UTF-8 continuation bytes.
IS_LEAD = (np.arange(256) & 0xC0) != 0x80


def mix64(x: np.ndarray) -> np.ndarray:
    """Finaliser of a 64-bit hash: every input bit reaches every output bit."""
    x = x.astype(np.uint64, copy=True)
    x ^= x >> np.uint64(30)
    x *= np.uint64(0xBF58476D1CE4E5B9)
    x ^= x >> np.uint64(27)
    x *= np.uint64(0x94D049BB133111EB)
    x ^= x >> np.uint64(31)
    return x


class AnchorHash:
    """Polynomial hash modulo 2**64: cheap, and only for choosing places (equal strings get equal values).

    Different strings may share a value, so nothing is decided by it; identity is decided by RollingHash.
    """

    STEP = 1 << 16

    def __init__(self, seed: int) -> None:
        ids = np.arange(1, 257, dtype=np.uint64)
        self.table = mix64(ids * np.uint64(0x9E3779B97F4A7C15) + np.uint64(seed))
        self.base = (0x9E3779B97F4A7C15 ^ (seed * 0x2545F4914F6CDD1D)) & 0xFFFFFFFFFFFFFFFF | 5

    def grams(self, data: np.ndarray, gram: int) -> np.ndarray:
        """The hash of every window of `gram` bytes, by doubling the width that is summed up."""
        x = self.table[data]
        out, width, at = None, 1, 0
        while True:
            if gram & width:
                part = x[at : at + len(data) - gram + 1]
                out = part.copy() if out is None else out + part * np.uint64(pow(self.base, at, 1 << 64))
                at += width
            if width * 2 > gram:
                return mix64(out)
            x = x[:-width] + x[width:] * np.uint64(pow(self.base, width, 1 << 64))
            width *= 2


MERSENNE = np.uint64((1 << 31) - 1)
_BITS = np.uint64(31)


def fold(x: np.ndarray) -> np.ndarray:
    """One step towards x modulo 2**31 - 1: below 2**33 for x below 2**64, below 2**31 + 4 for x below 2**33."""
    return (x & MERSENNE) + (x >> _BITS)


def reduced(x: np.ndarray) -> np.ndarray:
    """x modulo 2**31 - 1."""
    x = fold(fold(x))
    return np.where(x >= MERSENNE, x - MERSENNE, x)


class RollingHash:
    """Polynomial hash of byte strings modulo the prime 2**31 - 1, twice: two random bases, two random byte tables.

    Both residues make up the 62 bits of a hash: two different strings of n bytes share it for at most (n / 2**31) ** 2 of
    the bases, whatever the strings are. Sums run inside blocks, unreduced: 19 bits of a byte's value, 31 of a power and
    12 of the block fit into 64. Powers come from short tables, so nothing that is kept grows with the texts.
    """

    LOW = 12
    MASK = (1 << LOW) - 1

    def __init__(self, seed: int) -> None:
        prime, self.parts = int(MERSENNE), []
        for number in range(2):
            rng = np.random.default_rng(seed * 2 + number)
            table = (rng.permutation((1 << 19) - 1)[:256] + 1).astype(np.uint64)
            base = int(rng.integers(1 << 20, prime - 1))
            self.parts.append((table, self._powers(base), self._powers(pow(base, -1, prime))))

    def _powers(self, base: int) -> tuple[np.ndarray, int]:
        return self._grown(base, 1 << self.LOW), pow(base, 1 << self.LOW, int(MERSENNE))

    @staticmethod
    def _grown(base: int, n: int) -> np.ndarray:
        """The first n powers of a base."""
        out, size = np.ones(n, dtype=np.uint64), 1
        while size < n:
            more = out[size : 2 * size]
            more[:] = reduced(out[: len(more)] * np.uint64(pow(base, size, int(MERSENNE))))
            size *= 2
        return out

    def prefix(self, symbols: np.ndarray) -> list[tuple[np.ndarray, np.ndarray]]:
        """Per base: running sums inside blocks and the sum before each block, of byte symbols (uint8) or 64-bit values."""
        n, step, out = len(symbols), 1 << self.LOW, []
        blocks = (n >> self.LOW) + 1
        for table, (low, stride), _ in self.parts:
            inside = np.zeros(blocks * step, dtype=np.uint64)
            for i in range(0, n, step * 4):
                part = symbols[i : i + step * 4]
                values = inside[i : i + len(part)]
                values[:] = table[part] if part.dtype == np.uint8 else reduced(mix64(part ^ table[0]))
                whole = inside[i : min(i + step * 4, len(inside))].reshape(-1, step)
                whole *= low
                if part.dtype != np.uint8:
                    whole[:] = fold(whole)
                np.cumsum(whole, axis=1, out=whole)
            far = self._grown(stride, blocks)
            before = np.zeros(blocks, dtype=np.uint64)
            before[1:] = reduced(np.cumsum(reduced(reduced(inside[step - 1 :: step]) * far))[:-1])
            out.append((inside, before))
        return out

    def _at(self, sums: tuple[np.ndarray, np.ndarray], far: np.ndarray, place: np.ndarray) -> np.ndarray:
        """The prefix sum before each place, below 2**33."""
        inside, before = sums
        block = place >> self.LOW
        local = fold(fold(inside[place - 1]))
        local[(place & self.MASK) == 0] = 0
        return before[block] + fold(local * far[block])

    def spans(self, prefix: list[tuple[np.ndarray, np.ndarray]], start: np.ndarray, end: np.ndarray) -> np.ndarray:
        """Hash of [start, end): equal for equal content and length wherever it stands."""
        out, lift = [], np.uint64(int(MERSENNE) << 3)
        for sums, (_, (_, stride), (low, down)) in zip(prefix, self.parts, strict=True):
            far = self._grown(stride, len(sums[1]))
            value = fold(self._at(sums, far, end) + lift - self._at(sums, far, start))
            value = fold(value * low[start & self.MASK])
            out.append(reduced(fold(value) * self._grown(down, len(sums[1]))[start >> self.LOW]))
        return mix64((out[0] << np.uint64(32) | out[1]) ^ mix64((end - start).astype(np.uint64)))


HASH_A = RollingHash(17)
HASH_B = RollingHash(91)
ANCHOR = AnchorHash(17)


class Chunk:
    """Texts first..last of a batch: their bytes end to end, and where each begins."""

    def __init__(self, first: int, data: np.ndarray, offsets: np.ndarray) -> None:
        self.first, self.data, self.offsets = first, data, offsets
        self.n_docs = len(offsets) - 1

    def words(self) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """Start, end and text number of every word."""
        word = ~IS_SPACE[self.data]
        n = len(word)
        if not n:
            empty = np.zeros(0, dtype=np.int64)
            return empty, empty, empty
        edge = np.zeros(n + 1, dtype=bool)
        edge[self.offsets] = True
        before = np.empty(n, dtype=bool)
        before[0] = False
        before[1:] = word[:-1]
        start = np.flatnonzero(word & (~before | edge[:-1]))
        after = np.empty(n, dtype=bool)
        after[-1] = False
        after[:-1] = word[1:]
        end = np.flatnonzero(word & (~after | edge[1:])) + 1
        doc = np.searchsorted(self.offsets, start, side="right") - 1
        return start, end, doc

    def per_doc(self, doc: np.ndarray, weights: np.ndarray | None = None) -> np.ndarray:
        counted = np.bincount(doc, weights=weights, minlength=self.n_docs)
        return counted.astype(np.int64) if weights is None or weights.dtype.kind in "iub" else counted

    def count_bytes(self, flags: np.ndarray) -> np.ndarray:
        """Number of set flags in each text."""
        total = np.zeros(len(flags) + 1, dtype=np.int64)
        np.cumsum(flags, out=total[1:])
        return total[self.offsets[1:]] - total[self.offsets[:-1]]


def as_bytes(column: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """The bytes of a string column and the n + 1 places where its texts begin; null counts as empty."""
    if isinstance(column, pa.ChunkedArray):
        column = column.combine_chunks()
    if column.null_count:
        column = column.fill_null("" if not pa.types.is_binary(column.type) else b"")
    wide = pa.types.is_large_string(column.type) or pa.types.is_large_binary(column.type)
    _, offsets, data = column.buffers()
    if not len(column):
        return np.zeros(0, dtype=np.uint8), np.zeros(1, dtype=np.int64)
    places = np.frombuffer(offsets, dtype=np.int64 if wide else np.int32)[column.offset : column.offset + len(column) + 1].astype(np.int64)
    raw = np.frombuffer(data, dtype=np.uint8)[places[0] : places[-1]] if data is not None else np.zeros(0, dtype=np.uint8)
    return raw, places - places[0]


def chunks(column: pa.Array, limit: int = CHUNK_BYTES) -> Iterator[Chunk]:
    data, offsets = as_bytes(column)
    first = 0
    while first < len(offsets) - 1:
        last = max(first + 1, int(np.searchsorted(offsets, offsets[first] + limit, side="right")) - 1)
        yield Chunk(first, data[offsets[first] : offsets[last]], offsets[first : last + 1] - offsets[first])
        first = last


def repeats(keys: np.ndarray) -> np.ndarray:
    """True where a key occurs more than once."""
    if len(keys) < 2:
        return np.zeros(len(keys), dtype=bool)
    ordered = np.sort(keys)
    twice = np.unique(ordered[1:][ordered[1:] == ordered[:-1]])
    if not len(twice):
        return np.zeros(len(keys), dtype=bool)
    at = np.minimum(np.searchsorted(twice, keys), len(twice) - 1)
    return twice[at] == keys


def local_roots(left: np.ndarray, right: np.ndarray, root: np.ndarray) -> np.ndarray:
    """Least reachable number under links, continuing from root."""
    while True:
        low = np.minimum(root[left], root[right])
        new = root.copy()
        np.minimum.at(new, root[left], low)
        np.minimum.at(new, root[right], low)
        new = new[new]
        if np.array_equal(new, root):
            return root
        root = new
