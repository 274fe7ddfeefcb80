"""Stores to compare with: raw, blocks under a general compressor, two passes over host clusters, and one compressor primed with the dictionary."""

from __future__ import annotations

import bz2
import lzma
import zlib
from collections.abc import Callable, Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..session import tasks_for

#: block sizes of the experiments in bytes; 0 is one document a block
BLOCK_SIZES = (0, 100_000, 200_000, 500_000, 1_000_000)
#: requests that travel with one copy of their block where each opens it by itself
TOGETHER = 64


def _raw_deflate(level: int, wbits: int) -> Callable[[bytes], bytes]:
    def run(b: bytes) -> bytes:
        c = zlib.compressobj(level, zlib.DEFLATED, wbits)
        return c.compress(b) + c.flush()

    return run


def _lzma_window(size: int):
    filters = [{"id": lzma.FILTER_LZMA2, "preset": 6, "dict_size": size}]
    return lambda b: lzma.compress(b, format=lzma.FORMAT_XZ, filters=filters)


def codec(name: str) -> tuple[Callable[[bytes], bytes], Callable[[bytes, int], bytes]]:
    """(compress, decompress up to a size): raw, zlib, gzip, deflate<window bits>, lzma, lzma-<MB of window>, bz2."""

    def inflate(wbits: int):
        return lambda b, n: zlib.decompressobj(wbits).decompress(b, n) if n else b""

    def unlzma(b: bytes, n: int) -> bytes:
        return lzma.LZMADecompressor().decompress(b, n) if n else b""

    if name == "raw":
        return (lambda b: b), (lambda b, n: b[:n])
    if name == "zlib":
        return (lambda b: zlib.compress(b, 9)), inflate(15)
    if name == "gzip":
        return _raw_deflate(9, 31), inflate(31)
    if name.startswith("deflate"):
        bits = int(name[7:] or 15)
        return _raw_deflate(9, -bits), inflate(-bits)
    if name == "lzma":
        return (lambda b: lzma.compress(b)), unlzma
    if name.startswith("lzma-"):
        return _lzma_window(int(name[5:]) << 20), unlzma
    if name == "bz2":
        return (lambda b: bz2.compress(b, 9)), (lambda b, n: bz2.BZ2Decompressor().decompress(b, n) if n else b"")
    raise ValueError(name)


def block_number(block_bytes: int):
    """Documents are never split: a document belongs to the block its first byte falls into; size 0 gives each its own."""
    return F.floor(F.col("start_off") / block_bytes).cast("long") if block_bytes else F.col("ord").cast("long")


def blocked_store(placed: DataFrame, name: str | tuple[str, ...], block_bytes: int) -> DataFrame:
    """block_id, first_ord, n_docs, raw_bytes, members, payload. A task holds one block: its size and one document at most.

    Of several compressors each gives a row for each block, named in a column codec at the end; blocks are brought together once.
    """
    names = (name,) if isinstance(name, str) else tuple(name)
    squeezed, named = {c: codec(c)[0] for c in names}, [] if isinstance(name, str) else ["codec"]
    schema = "block_id long, first_ord long, n_docs long, raw_bytes long, members array<struct<doc_id:long,off:long,len:long>>, payload binary" + ", codec string" * len(named)

    if not block_bytes:  # nothing to bring together
        rows = placed.select(F.col("ord").alias("block_id"), F.col("ord").alias("first_ord"), F.lit(1).cast("long").alias("n_docs"), F.col("n_bytes").alias("raw_bytes"), F.array(F.struct(F.col("doc_id"), F.lit(0).cast("long").alias("off"), F.col("n_bytes").alias("len"))).alias("members"), "body")

        def each(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            for b in batches:
                for c, squeeze in squeezed.items():
                    payload = pa.array([squeeze(x) for x in b.column(5).to_pylist()], pa.binary())
                    yield pa.RecordBatch.from_arrays([*b.columns[:5], payload, *(pa.array([c] * b.num_rows, pa.string()) for _ in named)], names=[*b.schema.names[:5], "payload", *named])

        return rows.mapInArrow(each, schema)

    def pack(t: pa.Table) -> pa.Table:
        t = t.sort_by("ord")
        bodies, ids = t["body"].to_pylist(), t["doc_id"].to_pylist()
        off = np.concatenate([[0], np.cumsum([len(x) for x in bodies])])
        members = [{"doc_id": i, "off": int(o), "len": len(x)} for i, o, x in zip(ids, off, bodies, strict=False)]
        whole = b"".join(bodies)
        n = len(names)
        return pa.table(
            {
                "block_id": pa.array([t["block_id"][0].as_py()] * n),
                "first_ord": pa.array([t["ord"][0].as_py()] * n),
                "n_docs": pa.array([len(ids)] * n),
                "raw_bytes": pa.array([len(whole)] * n),
                "members": pa.array([members] * n, pa.list_(pa.struct([("doc_id", pa.int64()), ("off", pa.int64()), ("len", pa.int64())]))),
                "payload": pa.array([squeeze(whole) for squeeze in squeezed.values()], pa.binary()),
            }
            | {k: pa.array(names, pa.string()) for k in named}
        )

    rows = placed.select(block_number(block_bytes).alias("block_id"), "ord", "doc_id", "body")
    # a number of tasks, since a few that hold what is little to move are long to squeeze
    return rows.repartition(tasks_for(placed), "block_id").groupBy("block_id").applyInArrow(pack, schema)


def blocked_ratio(blocks: DataFrame, codecs: tuple[str, ...] = ()) -> DataFrame:
    """n_docs, raw_bytes, enc_bytes, enc_pct. ``codecs``: a row for each of them, also where it has no block."""
    s = blocks.groupBy(*(["codec"] if codecs else [])).agg(F.sum("n_docs").alias("n_docs"), F.sum("raw_bytes").alias("raw_bytes"), F.sum(F.octet_length("payload")).alias("enc_bytes"))
    if codecs:
        s = blocks.sparkSession.createDataFrame([(c,) for c in codecs], "codec string").join(s, "codec", "left")
    return s.withColumn("enc_pct", 100.0 * F.col("enc_bytes") / F.col("raw_bytes"))


def _members(blocks: DataFrame) -> DataFrame:
    return blocks.select("block_id", F.explode("members").alias("m")).select("block_id", F.col("m.doc_id").alias("doc_id"), F.col("m.off").alias("off"), F.col("m.len").alias("len"))


def read_blocked(blocks: DataFrame, name: str, requests: DataFrame) -> DataFrame:
    """req_no, doc_id, body, decoded_bytes. Each wanted block is opened once, up to the end of its last wanted document.

    Members are narrowed by the wanted ids inside the scan, as the store's rows are; payloads do not move. A member list is at most a block's documents.
    """
    from ..sources.store import BROADCAST_IDS, delivered

    _, open_ = codec(name)
    wanted = requests.select("doc_id").distinct()
    if wanted.limit(BROADCAST_IDS + 1).count() <= BROADCAST_IDS:
        wanted = F.broadcast(wanted)
        send = F.broadcast  # no more blocks than ids
    else:
        send = lambda rows: rows
    hits = _members(blocks).join(wanted, "doc_id", "left_semi").groupBy("block_id").agg(F.collect_list(F.struct("doc_id", "off", "len")).alias("want"))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            ids, bodies, cost = [], [], []
            for payload, want in zip(b.column(0).to_pylist(), b.column(1).to_pylist(), strict=True):
                raw = open_(payload, max(w["off"] + w["len"] for w in want))
                for w in want:
                    ids.append(w["doc_id"])
                    bodies.append(raw[w["off"] : w["off"] + w["len"]])
                    cost.append(w["off"] + w["len"])
            yield pa.RecordBatch.from_arrays([pa.array(ids, pa.int64()), pa.array(bodies, pa.binary()), pa.array(cost, pa.int64())], names=["doc_id", "body", "decoded_bytes"])

    opened = blocks.join(send(hits), "block_id").select("payload", "want").mapInArrow(run, "doc_id long, body binary, decoded_bytes long")
    return delivered(requests, opened, "body", "decoded_bytes")


def read_blocked_each(blocks: DataFrame, name: str, requests: DataFrame) -> DataFrame:
    """The same, but every request opens its block by itself, from the block's start to the document's end, as a server without a cache answers them.

    A block that is asked for often goes to several tasks, about ``TOGETHER`` requests at a time.
    """
    from ..sources.store import delivered

    _, open_ = codec(name)
    placed = delivered(requests, _members(blocks), "block_id", "off", "len").where("block_id is not null")
    shares = placed.groupBy("block_id").agg(F.ceil(F.count("*") / TOGETHER).alias("shares"))
    dealt = placed.join(shares, "block_id").groupBy("block_id", F.pmod(F.xxhash64("req_no"), F.col("shares")).alias("share"))
    rows = dealt.agg(F.collect_list(F.struct("req_no", "doc_id", "off", "len")).alias("want")).join(blocks.select("block_id", "payload"), "block_id")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for payload, want in zip(b.column(0).to_pylist(), b.column(1).to_pylist(), strict=True):
                ends = [w["off"] + w["len"] for w in want]
                bodies = [open_(payload, e)[w["off"] : e] for w, e in zip(want, ends, strict=True)]
                yield pa.RecordBatch.from_arrays([pa.array([w["req_no"] for w in want], pa.int64()), pa.array([w["doc_id"] for w in want], pa.int64()), pa.array(bodies, pa.binary()), pa.array(ends, pa.int64())], names=["req_no", "doc_id", "body", "decoded_bytes"])

    return rows.select("payload", "want").mapInArrow(run, "req_no long, doc_id long, body binary, decoded_bytes long")


def read_all_blocked(blocks: DataFrame, name: str) -> DataFrame:
    """doc_id, body of every document."""
    _, open_ = codec(name)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for payload, size, members in zip(*(b.column(i).to_pylist() for i in range(3)), strict=True):
                raw = open_(payload, size)
                yield pa.RecordBatch.from_arrays([pa.array([m["doc_id"] for m in members], pa.int64()), pa.array([raw[m["off"] : m["off"] + m["len"]] for m in members], pa.binary())], names=["doc_id", "body"])

    return blocks.select("payload", "raw_bytes", "members").mapInArrow(run, "doc_id long, body binary")


def primed(coll: DataFrame, dictionary: bytes) -> DataFrame:
    """Control: deflate of each document primed with the last 32 KB of the dictionary. doc_id, n_bytes, payload."""
    seed = dictionary[-32768:]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            out = []
            for x in b.column(1).to_pylist():
                c = zlib.compressobj(9, zlib.DEFLATED, -15, zdict=seed)
                out.append(c.compress(x) + c.flush())
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array([len(x) for x in b.column(1).to_pylist()], pa.int64()), pa.array(out, pa.binary())], names=["doc_id", "n_bytes", "payload"])

    return coll.select("doc_id", "body").mapInArrow(run, "doc_id long, n_bytes long, payload binary")


def open_primed(store: DataFrame, dictionary: bytes) -> DataFrame:
    seed = dictionary[-32768:]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array([zlib.decompressobj(-15, zdict=seed).decompress(x) for x in b.column(1).to_pylist()], pa.binary())], names=["doc_id", "body"])

    return store.select("doc_id", "payload").mapInArrow(run, "doc_id long, body binary")


# -- two passes: long repeats inside a cluster of pages, then a small window


def long_repeats(x: bytes, block: int = 32) -> list[tuple[int, int, bytes]]:
    """First pass as (distance, length, literal bytes before): repeats of ``block`` bytes or more, found by hashes of aligned blocks and extended."""
    seen: dict[bytes, int] = {}
    out, i, lit, n = [], 0, 0, len(x)
    stored = 0
    while i + block <= n:
        while stored + block <= i:
            seen.setdefault(x[stored : stored + block], stored)
            stored += block
        p = seen.get(x[i : i + block])
        if p is None:
            i += 1
            continue
        k = block
        while i + k < n and x[p + k] == x[i + k]:
            k += 1
        back = 0
        while i - back > lit and p - back > 0 and x[p - back - 1] == x[i - back - 1]:
            back += 1
        out.append((i - p, k + back, x[lit : i - back]))
        i += k
        lit = i
    out.append((0, 0, x[lit:]))
    return out


def two_pass(x: bytes, block: int = 32, window_bits: int = 14) -> bytes:
    from .codecs import enc_v

    repeats = long_repeats(x, block)
    head = enc_v(np.array([v for d, k, lit in repeats for v in (d, k, len(lit))], np.int64))
    body = len(head).to_bytes(4, "little") + head + b"".join(lit for _, _, lit in repeats)
    return _raw_deflate(9, -window_bits)(body)


def undo_two_pass(b: bytes) -> bytes:
    from .codecs import dec_v

    raw = zlib.decompress(b, -15)
    size = int.from_bytes(raw[:4], "little")
    numbers, at, out = dec_v(raw[4 : 4 + size]).tolist(), 4 + size, bytearray()
    for d, k, lit in zip(numbers[::3], numbers[1::3], numbers[2::3], strict=True):
        out += raw[at : at + lit]
        at += lit
        start = len(out) - d
        for i in range(0, k, d or 1):
            out += out[start + i : start + i + min(d, k - i)]
    return bytes(out)


def two_pass_store(pages: DataFrame, salt_docs: int = 200) -> DataFrame:
    """pages: page_id, url, html. Pages of a host (and, for large hosts, of a part of it: at most about ``salt_docs`` pages) are packed together.

    cluster, n_docs, raw_bytes, members, payload.
    """
    host = F.coalesce(F.expr("try_parse_url(url, 'HOST')"), F.lit(""))
    rows = pages.select(F.col("page_id").cast("long").alias("doc_id"), "url", F.encode(F.coalesce("html", F.lit("")), "UTF-8").alias("body"), host.alias("host"))
    size = rows.groupBy("host").agg(F.ceil(F.count("*") / salt_docs).alias("parts"))
    rows = rows.join(size, "host").withColumn("cluster", F.concat_ws("#", "host", F.pmod(F.xxhash64("url"), F.col("parts")).cast("string")))

    def pack(t: pa.Table) -> pa.Table:
        t = t.sort_by([("url", "ascending"), ("doc_id", "ascending")])
        bodies, ids = t["body"].to_pylist(), t["doc_id"].to_pylist()
        off = np.concatenate([[0], np.cumsum([len(x) for x in bodies])])
        whole = b"".join(bodies)
        members = [{"doc_id": i, "off": int(o), "len": len(x)} for i, o, x in zip(ids, off, bodies, strict=False)]
        return pa.table({"cluster": [t["cluster"][0].as_py()], "n_docs": [len(ids)], "raw_bytes": [len(whole)], "members": pa.array([members], pa.list_(pa.struct([("doc_id", pa.int64()), ("off", pa.int64()), ("len", pa.int64())]))), "payload": pa.array([two_pass(whole)], pa.binary())})

    return rows.select("cluster", "url", "doc_id", "body").groupBy("cluster").applyInArrow(pack, "cluster string, n_docs long, raw_bytes long, members array<struct<doc_id:long,off:long,len:long>>, payload binary")


def open_two_pass(store: DataFrame) -> DataFrame:
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for payload, members in zip(b.column(0).to_pylist(), b.column(1).to_pylist(), strict=True):
                raw = undo_two_pass(payload)
                yield pa.RecordBatch.from_arrays([pa.array([m["doc_id"] for m in members], pa.int64()), pa.array([raw[m["off"] : m["off"] + m["len"]] for m in members], pa.binary())], names=["doc_id", "body"])

    return store.select("payload", "members").mapInArrow(run, "doc_id long, body binary")


def zlib_size_agg():
    """An aggregate function: the size of the zlib stream over all values of a group, as 32-bit integers. Made when a session exists."""

    @F.pandas_udf("long")
    def size(v: pd.Series) -> int:
        return len(zlib.compress(np.asarray(v, "<u4").tobytes(), 9))

    return size
