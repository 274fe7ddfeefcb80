"""Suffix arrays of dictionaries and searches in them.

Places are 0-based. A suffix that ends is smaller than any that goes on and never matches a further byte.
"""

from __future__ import annotations

import tempfile
from bisect import bisect_left, bisect_right
from collections.abc import Iterator
from functools import cached_property

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..session import cut


#: Suffixes that are sorted at once, and entries from which on an array is a file without a name, mapped.
SORTED, MAPPED = 1 << 20, 1 << 22


def _entries(n: int, kind) -> np.ndarray:
    return np.zeros(n, kind) if n < MAPPED else np.memmap(tempfile.TemporaryFile(), kind, "w+", shape=(n,))


def suffix_array(d) -> np.ndarray:
    """uint32 array of suffix starts in order: dealt by two bytes, sorted by seven, then groups of equals by prefix doubling.

    Parts of about ``SORTED`` suffixes are sorted one after another (a larger group of equals is one part), so little memory is held beside the order, the ranks
    and a mark for each suffix, which are mapped from files where they are large.
    """
    a = np.frombuffer(d, np.uint8)
    n = len(a)
    if not n:
        return np.empty(0, np.uint32)
    sa, rank, tied = _entries(n, np.uint32), _entries(n, np.uint32), _entries(n + 1, np.bool_)
    two = lambda i: a[i : i + SORTED].astype(np.uint16) << np.uint16(8) | np.append(a[i + 1 : i + 1 + SORTED], np.zeros(max(0, i + 1 + SORTED - n), np.uint8))[: n - i]
    count = np.zeros(1 << 16, np.int64)
    for i in range(0, n, SORTED):
        count += np.bincount(two(i), minlength=1 << 16)
    ends = np.cumsum(count)
    free = ends - count
    for i in range(0, n, SORTED):
        code = two(i)
        order = np.argsort(code, kind="stable")
        code = code[order]
        here = np.bincount(code, minlength=1 << 16)
        sa[free[code] + np.arange(len(code)) - (np.cumsum(here) - here)[code]] = order + i
        free += here
    low = 0
    while low < n:
        high = int(ends[max(np.searchsorted(ends, low + SORTED, side="right") - 1, np.searchsorted(ends, low, side="right"))])
        at = sa[low:high].astype(np.int64)
        # seven bytes of nine bits: 0 is the end, so shorter suffixes sort first
        key = np.zeros(len(at), np.uint64)
        for k in range(7):
            inside = at + k < n
            key = key << np.uint64(9) | np.where(inside, a[np.minimum(at + k, n - 1)].astype(np.uint64) + np.uint64(1), np.uint64(0))
        _place(sa, rank, tied, np.arange(low, high), at, key)
        low = high
    depth = 7
    while _double(sa, rank, tied, depth):
        depth *= 2
    return sa


def _place(sa: np.ndarray, rank: np.ndarray, tied: np.ndarray, slot: np.ndarray, at: np.ndarray, key: np.ndarray) -> None:
    """Suffixes into their slots by key. A rank is the first slot of a group of equals; tied: as the suffix in the slot before."""
    order = np.argsort(key)
    key, at = key[order], at[order]
    same = np.zeros(len(key), bool)
    same[1:] = key[1:] == key[:-1]
    sa[slot], tied[slot] = at, same
    rank[at] = np.maximum.accumulate(np.where(same, 0, slot))


def _double(sa: np.ndarray, rank: np.ndarray, tied: np.ndarray, depth: int) -> bool:
    """Every group of suffixes that share ``depth`` bytes, by the rank of what follows these; False if there was none.

    Ranks never contradict the order, so they may change while others are still looked up.
    """
    n, low, found = len(sa), 0, False
    while low < n:
        high = min(low + SORTED, n)
        while high < n and tied[high]:  # up to the end of a group
            more = np.flatnonzero(~tied[high : high + SORTED])
            high = high + int(more[0]) if len(more) else min(high + SORTED, n)
        slot = low + np.flatnonzero(tied[low:high] | tied[low + 1 : high + 1])
        if len(slot):
            found = True
            at = sa[slot].astype(np.int64)
            after = at + depth
            key = np.where(after < n, rank[np.minimum(after, n - 1)].astype(np.uint64) + np.uint64(1), np.uint64(0))
            _place(sa, rank, tied, slot, at, rank[at].astype(np.uint64) << np.uint64(32) | key)
        low = high
    return found


def rank_array(sa: np.ndarray) -> np.ndarray:
    """The inverse: the rank of the suffix at each place."""
    out = np.empty(len(sa), np.int64)
    out[sa] = np.arange(len(sa))
    return out


def suffix_array_df(spark: SparkSession, d: bytes, partitions: int | None = None) -> DataFrame:
    """(rank, pos), by prefix doubling on DataFrames: each round ranks pairs of ranks and stops when all differ.

    Ranks come from counts of equal keys summed over key ranges, so no step has a window over everything.
    """
    sent = spark.sparkContext.broadcast(d)

    def first(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            at = b.column(0).to_pylist()
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array([sent.value[i : i + 8].hex() for i in at], pa.string())], names=["pos", "key"])

    keys = spark.range(0, len(d), 1, partitions).mapInArrow(first, "pos long, key string")
    depth, ranked = 8, _ranked(keys.select("pos", F.struct("key").alias("key")))
    while ranked.groupBy("rank").count().where("count > 1").limit(1).count():
        other = ranked.select((F.col("pos") - depth).alias("pos"), F.col("rank").alias("next"))
        both = ranked.join(other, "pos", "left").select("pos", F.struct("rank", F.coalesce("next", F.lit(-1).cast("long")).alias("next")).alias("key"))
        ranked, depth = _ranked(both), 2 * depth
    return ranked.select("rank", "pos")


def _ranked(keyed: DataFrame) -> DataFrame:
    """pos, rank: how many rows have a smaller key."""
    counts = keyed.groupBy("key").agg(F.count("*").alias("n"))
    ranged = cut(counts.repartitionByRange("key").withColumn("part", F.spark_partition_id()))
    before, total = {}, 0
    for r in ranged.groupBy("part").agg(F.sum("n").alias("n")).orderBy("part").collect():  # one row a partition
        before[r["part"]] = total
        total += r["n"]
    if not before:
        return keyed.select("pos", F.lit(0).cast("long").alias("rank"))
    base = F.create_map(*(F.lit(x) for kv in before.items() for x in kv))[F.col("part")]
    w = Window.partitionBy("part").orderBy("key").rowsBetween(Window.unboundedPreceding, -1)
    ranks = ranged.select("key", (base + F.coalesce(F.sum("n").over(w), F.lit(0))).cast("long").alias("rank"))
    return cut(keyed.join(ranks, "key").select("pos", "rank"))


def suffix_keys(view: np.ndarray, sa: np.ndarray) -> np.ndarray:
    """The first eight bytes of each suffix, in order, as integers."""
    out = np.empty(len(sa), np.uint64)
    for i in range(0, len(sa), 1 << 20):
        out[i : i + (1 << 20)] = view[sa[i : i + (1 << 20)]]
    return out


#: Ranks of a block of which the least place is kept.
LEAST = 32


class Searcher:
    """A dictionary with its suffix array: intervals, occurrences and longest matches."""

    def __init__(self, d, sa: np.ndarray, wide: np.ndarray | None = None, keys: np.ndarray | None = None):
        """d: bytes, or a mapping of them. wide (the bytes and sixteen zeros) and keys (the first eight bytes of each suffix) are made when needed if not given."""
        self.d, self.m, self.ranks, self._wide, self._keys = d, len(d), sa, wide, keys
        self.sa = memoryview(np.ascontiguousarray(sa, np.uint32)).cast("B").cast("I") if len(sa) else memoryview(b"")

    @cached_property
    def has_zero(self) -> bool:
        return self.d.find(b"\0") >= 0

    @cached_property
    def view(self) -> np.ndarray:
        """At each place the next eight bytes as a big-endian integer, without a copy for each place."""
        wide = np.frombuffer(bytes(self.d) + bytes(16), np.uint8) if self._wide is None else self._wide
        return np.ndarray((self.m + 9,), ">u8", wide, strides=(1,))

    @cached_property
    def keys(self) -> np.ndarray:
        return suffix_keys(self.view, self.ranks) if self._keys is None else self._keys

    @cached_property
    def least_places(self) -> list[np.ndarray]:
        """The least place of 1, 2, 4, ... whole blocks of ``LEAST`` ranks, from each block on."""
        n = self.m // LEAST
        out = [np.asarray(self.ranks[: n * LEAST]).reshape(n, LEAST).min(1)] if n else []
        while out and len(out[-1]) > (1 << (len(out) - 1)):
            half, step = out[-1], 1 << (len(out) - 1)
            out.append(np.minimum(half[:-step], half[step:]))
        return out

    def leftmost(self, pattern: bytes) -> int:
        """The least place of a string that is there."""
        low, high = self.interval(pattern)
        return int(np.min(self.ranks[low:high]))

    @cached_property
    def _bounds(self) -> list[int]:
        """Ranks where the suffixes of each first byte and second byte (or end) begin."""
        count = np.zeros(256 * 257 + 1, np.int64)
        for i in range(0, self.m, 1 << 22):
            a = np.frombuffer(self.d[i : i + (1 << 22) + 1], np.uint8).astype(np.int64)
            if i + (1 << 22) >= self.m:
                count[1 + a[-1] * 257] += 1
            count += np.bincount(a[:-1] * 257 + a[1:] + 2, minlength=len(count))
        return np.cumsum(count).tolist()

    def refine(self, low: int, high: int, depth: int, byte: int) -> tuple[int, int] | None:
        """Of the ranks low..high (inclusive), whose suffixes share ``depth`` bytes, those that go on with ``byte``."""
        at = lambda p: self.d[p + depth] if p + depth < self.m else -1
        lo = bisect_left(self.sa, byte, low, high + 1, key=at)
        hi = bisect_right(self.sa, byte, lo, high + 1, key=at)
        return (lo, hi - 1) if lo < hi else None

    def trace(self, x: bytes, i: int = 0) -> list[tuple[int, tuple[int, int] | None]]:
        """The intervals of growing prefixes of x[i:], up to the first that is not there."""
        low, high, out = 0, self.m - 1, []
        for j in range(i, len(x)):
            got = self.refine(low, high, j - i, x[j])
            out.append((j, got))
            if got is None:
                break
            low, high = got
        return out

    def interval(self, pattern: bytes) -> tuple[int, int]:
        """Ranks [low, high) of suffixes that begin with the pattern."""
        k = len(pattern)
        cut_ = lambda p: self.d[p : p + k]
        low = bisect_left(self.sa, pattern, key=cut_)
        return low, bisect_right(self.sa, pattern, low, key=cut_)

    def occurrences(self, pattern: bytes) -> int:
        low, high = self.interval(pattern)
        return high - low

    def longest_match(self, x: bytes, i: int, end: int | None = None, within: tuple[int, int] | None = None) -> tuple[int, int]:
        """(place, length) of the longest string of the dictionary that x[i:end] begins with; of its places, the one of the least suffix. Length 0: none.

        within: ranks [low, high) of all suffixes that share some first bytes with it, where they are known.
        """
        d, sa, n = self.d, self.sa, len(x) if end is None else end
        if within:
            return self._longest(x, i, n, *within, 256)
        first = x[i]
        low, high = self._bounds[first * 257], self._bounds[(first + 1) * 257]
        if low == high:
            return 0, 0
        if i + 1 == n:
            return sa[low], 1
        lo2, hi2 = self._bounds[first * 257 + 1 + x[i + 1]], self._bounds[first * 257 + 2 + x[i + 1]]
        if lo2 == hi2:
            return sa[low], 1
        return self._longest(x, i, n, lo2, hi2, 24)

    def _longest(self, x: bytes, i: int, n: int, low: int, high: int, width: int) -> tuple[int, int]:
        """The same among the ranks [low, high), whose suffixes share two bytes or more with it, by windows of ``width`` bytes and more."""
        d, sa = self.d, self.sa
        while True:
            want = x[i : min(i + width, n)]
            k = len(want)
            r = bisect_left(sa, want, low, high, key=lambda p: d[p : p + k])
            best = 2
            if r < high:
                best = max(best, _common(want, d[sa[r] : sa[r] + k]))
            if best < k and r > low:
                best = max(best, _common(want, d[sa[r - 1] : sa[r - 1] + k]))
            if best == k and i + k < n:
                # all of the window matches: only suffixes with it can match longer
                low, high = r, bisect_right(sa, want, r, high, key=lambda p: d[p : p + k])
                width *= 4
                continue
            head = x[i : i + best]
            r = bisect_left(sa, head, low, high, key=lambda p: d[p : p + best])
            return sa[r], best


def _common(a: bytes, b: bytes) -> int:
    """Length of the common prefix."""
    n = min(len(a), len(b))
    if a[:n] == b[:n]:
        return n
    low, high = 0, n
    while high - low > 1:
        mid = (low + high) // 2
        if a[low:mid] == b[low:mid]:
            low = mid
        else:
            high = mid
    return low


def longest_match_naive(d: bytes, x: bytes, i: int) -> tuple[int, int]:
    """By definition, growing the string one byte at a time; of its places the one whose suffix is least."""
    k = 0
    while i + k < len(x) and x[i : i + k + 1] in d:
        k += 1
    if not k:
        return 0, 0
    places = [p for p in range(len(d) - k + 1) if d[p : p + k] == x[i : i + k]]
    return min(places, key=lambda p: d[p:]), k


class GramIndex:
    """Places of all q-byte strings of a small dictionary; matches shorter than q are left to the caller."""

    def __init__(self, d: bytes, q: int = 4):
        self.d, self.q = d, q
        self.places: dict[bytes, list[int]] = {}
        for p in range(len(d) - q + 1):
            self.places.setdefault(d[p : p + q], []).append(p)

    def longest_match(self, x: bytes, i: int) -> tuple[int, int]:
        best = (0, 0)
        for p in self.places.get(x[i : i + self.q], ()):
            k = self.q
            while i + k < len(x) and p + k < len(self.d) and x[i + k] == self.d[p + k]:
                k += 1
            if k > best[1] or (k == best[1] and self.d[p:] < self.d[best[0] :]):
                best = (p, k)
        return best


def gram_index_df(spark: SparkSession, d: bytes, q: int = 4) -> DataFrame:
    """(gram, places) as a table."""
    rows = spark.createDataFrame([(bytearray(d),)], "d binary")
    grams = rows.select(F.posexplode(F.transform(F.sequence(F.lit(1), F.greatest(F.octet_length("d") - q + 1, F.lit(1))), lambda i: F.substring("d", i, F.lit(q)))).alias("p", "g"))
    return grams.where(F.octet_length("g") == q).groupBy(F.hex("g").alias("gram")).agg(F.array_sort(F.collect_list("p")).alias("places"))
