"""Vectorised text kernel shared by the operators of this subpackage.

A ``Slab`` holds the UTF-8 bytes of some whole documents end to end. Words, lines and any other
substrings are position ranges in it, and every substring has a 64-bit hash that depends on its
bytes alone (not on its place), computed from one running polynomial sum. Null text is empty text.
"""

from __future__ import annotations

import ctypes
import functools
import inspect
from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc

SLAB_BYTES = 1 << 20
_MASK = (1 << 64) - 1
_BASE = 0x9E3779B97F4A7C15 | 1
_BASE_INV = pow(_BASE, -1, 1 << 64)
_rng = np.random.Generator(np.random.PCG64(20240229))
_BYTE_CODE = _rng.integers(1, 1 << 63, 256, dtype=np.uint64) * np.uint64(2) + np.uint64(1)

#: separators of words: space and the bytes 0x09-0x0D
WORD_BYTE = np.ones(256, bool)
WORD_BYTE[[0x20, 9, 10, 11, 12, 13]] = False
#: bytes that begin a code point
LEAD_BYTE = np.ones(256, bool)
LEAD_BYTE[0x80:0xC0] = False
LOWER = np.arange(256, dtype=np.uint8)
LOWER[65:91] += 32

_LOW_BITS = 12


def _geometric(base: int, n: int) -> np.ndarray:
    out = np.ones(n, np.uint64)
    done = 1
    while done < n:
        out[done : 2 * done] = out[: min(done, n - done)] * np.uint64(pow(base, done, 1 << 64))
        done *= 2
    return out


class _Powers:
    """base^i for places i, as a product of two small tables."""

    def __init__(self, base: int):
        self.step = pow(base, 1 << _LOW_BITS, 1 << 64)
        self.low = _geometric(base, 1 << _LOW_BITS)
        self.high = _geometric(self.step, 1024)

    def _reach(self, top: int) -> None:
        if top >> _LOW_BITS >= len(self.high):
            self.high = _geometric(self.step, 2 * (top >> _LOW_BITS) + 2)

    def at(self, i: np.ndarray) -> np.ndarray:
        if not len(i):
            return np.empty(0, np.uint64)
        self._reach(int(i.max()))
        return self.high[i >> _LOW_BITS] * self.low[i & ((1 << _LOW_BITS) - 1)]

    def span(self, first: int, n: int) -> np.ndarray:
        """Powers of first, first + 1, ...; first is a multiple of the small table's length."""
        self._reach(first + n)
        rows = self.high[first >> _LOW_BITS : (first + n + len(self.low) - 1) >> _LOW_BITS]
        return (rows[:, None] * self.low[None, :]).ravel()[:n]


_FORWARD, _INVERSE = _Powers(_BASE), _Powers(_BASE_INV)
_CHUNK = 1 << 17


def mix(h: np.ndarray) -> np.ndarray:
    """Bijective scramble of 64-bit integers."""
    h = h ^ (h >> np.uint64(31))
    h = h * np.uint64(0xBF58476D1CE4E5B9)
    h = h ^ (h >> np.uint64(29))
    h = h * np.uint64(0x94D049BB133111EB)
    return h ^ (h >> np.uint64(32))


def mix_one(x: int) -> int:
    return int(mix(np.array([x & _MASK], np.uint64))[0])


def trim() -> None:
    """Give freed memory back to the system: workers outlive their tasks, and the next task may be another operator's."""
    pa.default_memory_pool().release_unused()
    try:
        ctypes.CDLL("libc.so.6").malloc_trim(0)
    except (OSError, AttributeError):  # another C library
        pass


def tidy(run: Callable) -> Callable:
    """A function over batches, or of a table, that trims memory when it is done."""
    if inspect.isgeneratorfunction(run):

        @functools.wraps(run)
        def batches(rows):
            try:
                yield from run(rows)
            finally:
                trim()

        return batches

    @functools.wraps(run)
    def whole(table, *more):
        try:
            return run(table, *more)
        finally:
            trim()

    return whole


class Slab:
    """Bytes of documents ``0..n-1`` end to end; ``off`` has n+1 offsets."""

    def __init__(self, data: np.ndarray, off: np.ndarray, lower: bool = False):
        self.data, self.off, self.n = data, off, len(off) - 1
        self._hashed = LOWER[data] if lower else data
        self._sums: np.ndarray | None = None
        self._words: tuple[np.ndarray, np.ndarray] | None = None

    @property
    def sums(self) -> np.ndarray:
        if self._sums is None:
            n = len(self.data)
            s = np.empty(n + 1, np.uint64)
            s[0] = 0
            for i in range(0, n, _CHUNK):  # in pieces, so that no long temporary array is made
                j = min(n, i + _CHUNK)
                part = _BYTE_CODE[self._hashed[i:j]] * _FORWARD.span(i, j - i)
                part[:1] += s[i : i + 1]
                np.cumsum(part, out=s[i + 1 : j + 1])
            self._sums = s
        return self._sums

    def forget(self) -> None:
        """Let the running sum go; it is made again if it is asked for."""
        self._sums = None

    def hash(self, start: np.ndarray, end: np.ndarray) -> np.ndarray:
        """64-bit hashes of the substrings [start, end)."""
        return mix((self.sums[end] - self.sums[start]) * _INVERSE.at(start) + (end - start).astype(np.uint64))

    def gram_hashes(self, k: int) -> np.ndarray:
        """``hash`` of the k-byte substring at every place."""
        n = max(0, len(self.data) - k + 1)
        out = np.empty(n, np.uint64)
        for i in range(0, n, _CHUNK):
            j = min(n, i + _CHUNK)
            out[i:j] = mix((self.sums[k + i : k + j] - self.sums[i:j]) * _INVERSE.span(i, j - i) + np.uint64(k))
        return out

    def runs(self, member: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Maximal runs of bytes whose entry of the 256-row table is true; no run crosses documents."""
        m = member[self.data]
        if not len(m):
            return np.empty(0, np.int64), np.empty(0, np.int64)
        filled = self.off[:-1][self.off[:-1] < self.off[1:]]
        begin = m.copy()
        begin[1:] &= ~m[:-1]
        begin[filled] = m[filled]
        end = m.copy()
        end[:-1] &= ~m[1:]
        last = self.off[1:][self.off[:-1] < self.off[1:]] - 1
        end[last] = m[last]
        return np.flatnonzero(begin), np.flatnonzero(end) + 1

    def words(self) -> tuple[np.ndarray, np.ndarray]:
        if self._words is None:
            self._words = self.runs(WORD_BYTE)
        return self._words

    def doc_of(self, position: np.ndarray) -> np.ndarray:
        return np.searchsorted(self.off, position, side="right") - 1

    def text(self, i: int) -> str:
        return self.data[self.off[i] : self.off[i + 1]].tobytes().decode("utf-8", "replace")

    def per_doc(self, position: np.ndarray) -> np.ndarray:
        """Offsets by document of sorted positions: n+1 cuts."""
        return np.searchsorted(position, self.off)

    def sums_by_doc(self, flag: np.ndarray) -> np.ndarray:
        """For each document the sum of a per-byte flag."""
        c = np.zeros(len(self.data) + 1, np.int64)
        np.cumsum(flag, out=c[1:])
        return c[self.off[1:]] - c[self.off[:-1]]


def slabs(column: pa.Array | pa.ChunkedArray, lower: bool = False, limit: int = SLAB_BYTES) -> Iterator[tuple[int, int, Slab]]:
    """Cut a string column into slabs of whole documents: (first row, row after the last, slab)."""
    if isinstance(column, pa.ChunkedArray):
        column = column.combine_chunks()
    if column.null_count:
        column = column.fill_null("")
    n = len(column)
    if not n:
        return
    wide = pa.types.is_large_string(column.type) or pa.types.is_large_binary(column.type)
    kind = np.int64 if wide else np.int32
    _, offsets, values = column.buffers()
    off = np.frombuffer(offsets, kind, count=n + 1, offset=column.offset * kind().itemsize).astype(np.int64)
    data = np.frombuffer(values, np.uint8) if values is not None and values.size else np.empty(0, np.uint8)
    i = 0
    while i < n:
        j = max(i + 1, int(np.searchsorted(off, off[i] + limit, side="right")) - 1)
        yield i, j, Slab(data[off[i] : off[j]], off[i : j + 1] - off[i], lower)
        i = j


def blocks(batches: Iterator[pa.RecordBatch], text: int, limit: int) -> Iterator[pa.RecordBatch]:
    """The rows of batches, dealt anew: each batch has texts of about ``limit`` bytes, however the rows came."""
    held: list[pa.RecordBatch] = []
    size = 0
    for b in batches:
        at = 0
        lengths = pc.fill_null(pc.binary_length(b.column(text)), 0).to_numpy().astype(np.int64)
        total = np.cumsum(lengths)
        while at < b.num_rows:
            before = int(total[at - 1]) if at else 0
            to = max(at + 1, int(np.searchsorted(total, before + limit - size, side="right")))
            held.append(b.slice(at, to - at))
            size += int(total[to - 1]) - before
            at = to
            if size >= limit or (at < b.num_rows and size + lengths[at] > limit):
                yield _joined(held)
                held, size = [], 0
    if held:
        yield _joined(held)


def _joined(parts: list[pa.RecordBatch]) -> pa.RecordBatch:
    if len(parts) == 1:
        return parts[0]
    return pa.Table.from_batches(parts).combine_chunks().to_batches(max_chunksize=None)[0]


def rolling(h: np.ndarray, k: int) -> np.ndarray:
    """Hashes of the k-long windows of a sequence of 64-bit codes; len(h)-k+1 of them."""
    n = len(h) - k + 1
    if n <= 0:
        return np.empty(0, np.uint64)
    out = np.zeros(n, np.uint64)
    for j in range(k):
        out = out * np.uint64(0xD6E8FEB86659FD93) + h[j : j + n]
    return mix(out)


def windows(cuts: np.ndarray, k: int) -> tuple[np.ndarray, np.ndarray]:
    """Of per-document word cuts: (first word, document) of each k-word window inside one document."""
    sizes = np.maximum(np.diff(cuts) - k + 1, 0)
    doc = np.repeat(np.arange(len(sizes)), sizes)
    first = np.arange(int(sizes.sum())) - np.repeat(np.cumsum(sizes) - sizes, sizes) + np.repeat(cuts[:-1], sizes)
    return first, doc


def code_points(slab: Slab) -> np.ndarray:
    """Prefix counts of code points: c[i] = code points that begin before byte i."""
    c = np.zeros(len(slab.data) + 1, np.int64)
    np.cumsum(LEAD_BYTE[slab.data], out=c[1:])
    return c
