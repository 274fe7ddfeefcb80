"""Dictionaries: how they are sampled, held, shipped to tasks, extended and pruned."""

from __future__ import annotations

import atexit
import hashlib
import mmap
import os
import shutil
import uuid
from dataclasses import dataclass, field
from urllib.parse import urlparse

import numpy as np
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..session import shared_folder, small_batches
from . import suffix
from .collection import prefix, total_bytes

#: Largest dictionary that is sent as a broadcast; larger ones are mapped from files in the shared folder.
BROADCAST_BYTES = 16 << 20
#: The same where the shared folder is a mounted file system: a sent one costs each worker 14 times its size, a mapped one nothing.
SENT_BYTES = 1 << 20


def _is_sent(spark: SparkSession, size: int) -> bool:
    mounted = urlparse(shared_folder(spark)).scheme in ("", "file")
    return size <= (min(SENT_BYTES, BROADCAST_BYTES) if mounted else BROADCAST_BYTES)


@dataclass(frozen=True)
class DictSpec:
    """Size in bytes or in % of the collection, sample size, and kind: even, documents, head."""

    m_bytes: int | None = None
    pct: float | None = None
    s: int = 1024
    kind: str = "even"
    seed: int = 0

    def size(self, n: int) -> int:
        m = self.m_bytes if self.m_bytes is not None else int(n * self.pct / 100)
        return min(m, n)


def even_samples(placed: DataFrame, m: int, s: int, n: int | None = None) -> DataFrame:
    """k, start, bytes: c = floor(m / s) samples of s bytes, the k-th from floor(k n / c).

    A document works out from its place which samples it overlaps and cuts its pieces; pieces of a sample are put together by place. Only m bytes are
    shuffled. Samples may span documents. If they would cover everything there is one sample, the whole.
    """
    n = total_bytes(placed) if n is None else n
    c = m // s
    if m < n and c == 0:
        raise ValueError(f"a dictionary of {m} bytes has no room for a sample of {s}")
    if c * s >= n or m >= n:
        c, s = 1, n
    big = lambda x: x.cast("decimal(38,0)")  # noqa: E731  places times samples pass 64 bits on large collections
    ceil_div = lambda a: F.ceil(a / F.lit(n)).cast("long")
    b, e = F.col("start_off"), F.col("start_off") + F.col("n_bytes")
    low = F.greatest(F.lit(0).cast("long"), ceil_div(big((b - s + 1)) * c))
    high = F.least(F.lit(c - 1).cast("long"), ceil_div(big(e) * c) - 1)
    rows = placed.where("n_bytes > 0").select("body", b.alias("b"), e.alias("e"), F.explode(F.when(low <= high, F.sequence(low, high)).otherwise(F.array().cast("array<bigint>"))).alias("k"))
    start = F.floor(big(F.col("k")) * n / F.lit(c)).cast("long")
    rows = rows.withColumn("start", start)
    left, right = F.greatest("b", "start"), F.least(F.col("e"), F.col("start") + s)
    rows = rows.where(left < right).select("k", "start", left.alias("at"), F.substring(F.col("body"), (left - F.col("b") + 1).cast("int"), (right - left).cast("int")).alias("piece"))
    parts = F.array_sort(F.collect_list(F.struct("at", "piece")))
    return rows.groupBy("k", "start").agg(parts.alias("p")).select("k", "start", F.expr("aggregate(p, CAST('' AS BINARY), (a, x) -> concat(a, x.piece))").alias("bytes"))


def random_documents(coll: DataFrame, m: int, seed: int = 0) -> DataFrame:
    """Documents in a meaningless order (the least md5 of seed and id first) until m bytes; the last is cut. k, start, bytes."""
    from .collection import shuffled_key, with_offsets

    placed = with_offsets(coll, [shuffled_key(seed)])
    size = F.least(F.col("n_bytes"), F.lit(m) - F.col("start_off"))
    return placed.where(F.col("start_off") < m).select(F.col("ord").alias("k"), F.col("start_off").alias("start"), F.substring(F.col("body"), F.lit(1), size.cast("int")).alias("bytes"))


def head(placed: DataFrame, m: int) -> DataFrame:
    """The first m bytes, as a control that depends on order."""
    size = F.least(F.col("n_bytes"), F.lit(m) - F.col("start_off"))
    return placed.where(F.col("start_off") < m).select(F.col("ord").alias("k"), F.col("start_off").alias("start"), F.substring(F.col("body"), F.lit(1), size.cast("int")).alias("bytes"))


def assemble(samples: DataFrame, m: int) -> bytes:
    """The samples one after another, at most m bytes - the size that the user set - on the driver."""
    out = bytearray()
    for r in samples.orderBy("k").toLocalIterator():
        out += r["bytes"][: m - len(out)]
        if len(out) >= m:
            break
    return bytes(out)


@dataclass
class Dictionary:
    """Bytes, suffix array, and the sizes of its versions: places under ``sizes[v]`` were there in version v."""

    data: bytes
    sizes: list[int] = field(default_factory=list)
    epoch: int = 0

    def __post_init__(self) -> None:
        self.sizes = self.sizes or [len(self.data)]
        self._sa: np.ndarray | None = None
        self._shipped: tuple | None = None

    @property
    def sa(self) -> np.ndarray:
        if self._sa is None:
            self._sa = suffix.suffix_array(self.data)
        return self._sa

    @property
    def version(self) -> int:
        return len(self.sizes) - 1

    @property
    def md5(self) -> str:
        return hashlib.md5(self.data).hexdigest()

    def extend(self, more: bytes) -> Dictionary:
        """A further version; earlier places keep their meaning."""
        return Dictionary(self.data[:] + more, [*self.sizes, len(self.data) + len(more)], self.epoch)

    def save(self, path: str) -> None:
        """Each file appears under its name when whole, the sizes last."""
        os.makedirs(path, exist_ok=True)
        for name, b in (("dict.bin", self.data), ("suffixes.bin", self.sa), ("sizes.txt", " ".join(map(str, [self.epoch, *self.sizes])).encode())):
            with open(os.path.join(path, name + ".part"), "wb") as f:
                f.write(b)
            os.replace(os.path.join(path, name + ".part"), os.path.join(path, name))

    @classmethod
    def load(cls, path: str) -> Dictionary:
        read = lambda name: open(os.path.join(path, name), "rb").read()  # noqa: E731, SIM115
        epoch, *sizes = map(int, read("sizes.txt").split())
        out = cls(read("dict.bin"), sizes, epoch)
        out._sa = np.frombuffer(read("suffixes.bin"), np.uint32)
        return out


def build(placed: DataFrame, spec: DictSpec) -> Dictionary:
    n = total_bytes(placed)
    m = spec.size(n)
    if spec.kind == "even":
        samples = even_samples(placed, m, spec.s, n)
    elif spec.kind == "documents":
        samples = random_documents(placed.select("doc_id", "body", "n_bytes"), m, spec.seed)
    else:
        samples = head(placed, m)
    return Dictionary(assemble(samples, m))


def from_prefix(placed: DataFrame, pct: float, spec: DictSpec) -> Dictionary:
    """A dictionary of the size for the whole collection, sampled from the first pct % of it."""
    m = spec.size(total_bytes(placed))
    part = prefix(placed, pct)
    return build(part, DictSpec(m_bytes=m, s=spec.s, kind=spec.kind, seed=spec.seed))


def extend(dictionary: Dictionary, placed_new: DataFrame, m_extra: int, s: int) -> Dictionary:
    """The next version: samples of new documents after the old bytes."""
    n = total_bytes(placed_new)
    return dictionary.extend(assemble(even_samples(placed_new, min(m_extra, n), min(s, m_extra, n), n), m_extra)) if n else dictionary


class Shipped:
    """A dictionary as tasks see it, opened once in each worker.

    A mapped one costs a worker no memory of its own: bytes, suffixes and their first eight bytes are files that all workers of a machine share in the page
    cache. Decoding opens the bytes alone.
    """

    _open: dict[str, suffix.Searcher | bytes | mmap.mmap] = {}

    def __init__(self, spark: SparkSession, dictionary: Dictionary):
        small_batches(spark)
        sc = spark.sparkContext
        if not dictionary._shipped or dictionary._shipped[0] is not sc or (dictionary._shipped[2] is not None) != _is_sent(spark, len(dictionary.data)):
            dictionary._shipped = (sc, uuid.uuid4().hex, *self._ship(spark, dictionary))
        _, self.key, self.sent, self.path = dictionary._shipped

    @staticmethod
    def _ship(spark: SparkSession, dictionary: Dictionary) -> tuple:
        """(broadcast, None), or (None, folder)."""
        if _is_sent(spark, len(dictionary.data)):
            return spark.sparkContext.broadcast((dictionary.data[:], dictionary.sa.tobytes())), None
        u = urlparse(shared_folder(spark))
        if u.scheme not in ("", "file"):
            raise ValueError(f"a dictionary over {BROADCAST_BYTES} bytes is mapped from spark.checkpoint.dir, which has to be a mounted file system")
        path = os.path.join(u.path, f"dictionary-{uuid.uuid4().hex}")
        dictionary.save(path)
        atexit.register(shutil.rmtree, path, True)
        with open(os.path.join(path, "wide.bin"), "wb") as f:
            f.write(dictionary.data)
            f.write(bytes(16))
        search = suffix.Searcher(dictionary.data, dictionary.sa, np.memmap(os.path.join(path, "wide.bin"), np.uint8, "r"))
        with open(os.path.join(path, "keys.bin"), "wb") as f:
            for i in range(0, len(dictionary.sa), 1 << 20):
                f.write(suffix.suffix_keys(search.view, dictionary.sa[i : i + (1 << 20)]))
        # from here on the driver too has them in these files alone
        with open(os.path.join(path, "dict.bin"), "rb") as f:
            dictionary.data = mmap.mmap(f.fileno(), 0, access=mmap.ACCESS_READ)
        dictionary._sa = np.memmap(os.path.join(path, "suffixes.bin"), np.uint32, "r")
        return None, path

    def _file(self, name: str) -> str:
        return os.path.join(self.path, name)

    def _bytes(self) -> bytes | mmap.mmap:
        if not self.path:
            return self.sent.value[0]
        with open(self._file("dict.bin"), "rb") as f:
            return mmap.mmap(f.fileno(), 0, access=mmap.ACCESS_READ)

    def _once(self, kind: str, make):
        if self.key + kind not in Shipped._open:
            Shipped._open.clear()  # one dictionary at a time in a worker
            Shipped._open[self.key + kind] = make()
        return Shipped._open[self.key + kind]

    def searcher(self) -> suffix.Searcher:
        def make() -> suffix.Searcher:
            if not self.path:
                return suffix.Searcher(self._bytes(), np.frombuffer(self.sent.value[1], np.uint32))
            return suffix.Searcher(self._bytes(), *(np.memmap(self._file(n), t, "r") for n, t in (("suffixes.bin", np.uint32), ("wide.bin", np.uint8), ("keys.bin", np.uint64))))

        return self._once("s", make)

    def data(self) -> bytes | mmap.mmap:
        """The bytes alone; slices of them are bytes."""
        return self._once("d", self._bytes)


def prune_and_refill(placed: DataFrame, dictionary: Dictionary, passes: int, s: int, min_run: int = 16) -> list[tuple[int, Dictionary, float]]:
    """Several passes: keep the runs of the dictionary that factors use, fill the room with fresh even samples. (pass, dictionary, unused %)."""
    from . import factorize, measures

    m, n, out = len(dictionary.data), total_bytes(placed), []
    for k in range(passes + 1):
        factors = factorize.factorize(placed, dictionary)
        runs = measures.used_runs(factors).collect()  # runs of one dictionary, which is on the driver anyway
        used = sum(r["stop"] - r["start"] for r in runs)
        out.append((k, dictionary, 100.0 * (m - used) / m))
        if k == passes:
            break
        kept = b"".join(dictionary.data[r["start"] : r["stop"]] for r in sorted(runs, key=lambda r: r["start"]) if r["stop"] - r["start"] >= min_run)[:m]
        room = m - len(kept)
        if room < s:
            break
        # new places: the stride is shifted by the pass, by sampling from a rotated origin
        shift = (k + 1) * n // (2 * (passes + 1))
        turned = placed.withColumn("start_off", F.pmod(F.col("start_off") - shift, F.lit(n)))
        dictionary = Dictionary(kept + assemble(even_samples(turned, room, s, n), room))
    return out
