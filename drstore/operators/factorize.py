"""Dictionary-relative factors of documents, and back.

A factor is (pos, len); len 0 marks a literal byte, held in pos. From each place the longest string of the dictionary is taken, never beyond the
document's end; of its places in the dictionary the one whose suffix is least (``tie='first_rank'``) or the leftmost.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from . import codecs
from .dictionary import Dictionary, Shipped
from .suffix import Searcher

_FACTOR = pa.list_(pa.struct([("pos", pa.int64()), ("len", pa.int32())]))


def factor_document(x: bytes, search: Searcher, tie: str = "first_rank") -> tuple[list[int], list[int]]:
    pos, length, i, n = [], [], 0, len(x)
    find = search.longest_match
    while i < n:
        p, k = find(x, i)
        if k and tie == "leftmost":
            p = search.d.find(x[i : i + k])
        pos.append(p if k else x[i])
        length.append(k)
        i += k or 1
    return pos, length


def decode_document(pos, length, d: bytes) -> bytes:
    return b"".join([d[p : p + k] if k else bytes((p,)) for p, k in zip(pos, length, strict=True)])


def decode_range(pos: np.ndarray, length: np.ndarray, d: bytes, start: int, size: int) -> bytes:
    """Bytes start .. start+size of a document: only the factors that cover them are opened."""
    step = np.maximum(length, 1)
    end = np.cumsum(step)
    a = int(np.searchsorted(end, start, side="right"))
    b = int(np.searchsorted(end, start + size, side="left")) + 1
    skip = start - (int(end[a - 1]) if a else 0)
    return decode_document(pos[a:b].tolist(), length[a:b].tolist(), d)[skip : skip + size]


def factor_batch(bodies: list[bytes], search: Searcher, tie: str = "first_rank") -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(pos, len, cuts) of the factors of many documents."""
    from .bulk import Bulk

    return Bulk(search, tie).factors(bodies)


def factor_lists(pos: np.ndarray, length: np.ndarray, cuts: np.ndarray) -> pa.Array:
    flat = pa.StructArray.from_arrays([pa.array(pos, pa.int64()), pa.array(length.astype(np.int32))], names=["pos", "len"])
    return pa.ListArray.from_arrays(pa.array(cuts.astype(np.int32)), flat)


def flat_factors(lists: pa.Array) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(pos, len, cuts), the other way round."""
    cuts = lists.offsets.to_numpy() - lists.offsets[0].as_py() if len(lists) else np.zeros(1, np.int64)
    flat = lists.flatten()
    return flat.field("pos").to_numpy(), flat.field("len").to_numpy(), cuts


#: Bytes of text that are factored at once.
SLICE = 8 << 20


def _sliced(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """The batches (doc_id, body) in slices of about ``SLICE`` bytes, one row at least."""
    for b in batches:
        off = np.concatenate([[0], np.cumsum(pc.fill_null(pc.binary_length(b.column(1)), 0).to_numpy(zero_copy_only=False).astype(np.int64))])
        i = 0
        while i < b.num_rows:
            j = max(i + 1, int(np.searchsorted(off, off[i] + SLICE, side="right")) - 1)
            yield b.slice(i, j - i)
            i = j


def _carried(df: DataFrame, carry: tuple[str, ...]) -> str:
    """The carried columns at the end of a schema."""
    return "".join(f", `{f.name}` {f.dataType.simpleString()}" for f in df.select(*carry).schema)


def factorize(coll: DataFrame, dictionary: Dictionary, tie: str = "first_rank", carry: tuple[str, ...] = ()) -> DataFrame:
    """doc_id, factors (and carried columns). Narrow: no shuffle."""
    ship = Shipped(coll.sparkSession, dictionary)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        search = ship.searcher()
        for b in _sliced(batches):
            yield pa.RecordBatch.from_arrays([b.column(0), factor_lists(*factor_batch(b.column(1).to_pylist(), search, tie)), *b.columns[2:]], names=["doc_id", "factors", *carry])

    return coll.select("doc_id", "body", *carry).mapInArrow(run, "doc_id long, factors array<struct<pos:long,len:int>>" + _carried(coll, carry))


def factorize_stream(placed: DataFrame, dictionary: Dictionary) -> DataFrame:
    """Ablation: documents of a partition as one string, factored without regard to their ends, then cut at them. doc_id, factors."""
    ship = Shipped(placed.sparkSession, dictionary)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        search = ship.searcher()
        for b in batches:
            bodies = b.column(1).to_pylist()
            pos, length = factor_document(b"".join(bodies), search)
            i, out_p, out_k = 0, [], []
            for x in bodies:
                room, ps, ks = len(x), [], []
                while room:
                    p, k = pos[i], length[i]
                    take = min(k or 1, room)
                    ps.append(p)
                    ks.append(take if k else 0)
                    room -= take
                    if k and take < k:
                        pos[i], length[i] = p + take, k - take
                    else:
                        i += 1
                out_p.append(ps)
                out_k.append(ks)
            cuts = np.concatenate([[0], np.cumsum([len(p) for p in out_p])])
            yield pa.RecordBatch.from_arrays([b.column(0), factor_lists(np.array([v for p in out_p for v in p], np.int64), np.array([v for k in out_k for v in k], np.int64), cuts)], names=["doc_id", "factors"])

    return placed.select("doc_id", "body").mapInArrow(run, "doc_id long, factors array<struct<pos:long,len:int>>")


def factors_long(factors: DataFrame) -> DataFrame:
    """doc_id, seq, doc_off, pos, len, is_literal."""
    rows = factors.select("doc_id", F.posexplode("factors").alias("seq", "f")).select("doc_id", "seq", F.col("f.pos").alias("pos"), F.col("f.len").alias("len"))
    w = Window.partitionBy("doc_id").orderBy("seq").rowsBetween(Window.unboundedPreceding, -1)
    return rows.select("doc_id", "seq", F.coalesce(F.sum(F.greatest(F.col("len"), F.lit(1))).over(w), F.lit(0)).cast("long").alias("doc_off"), "pos", "len", (F.col("len") == 0).alias("is_literal"))


def decode(factors: DataFrame, dictionary: Dictionary) -> DataFrame:
    """doc_id, body."""
    ship = Shipped(factors.sparkSession, dictionary)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        d = ship.data()
        for b in batches:
            pos, length, cuts = flat_factors(b.column(1))
            out = [decode_document(pos[i:j].tolist(), length[i:j].tolist(), d) for i, j in zip(cuts[:-1], cuts[1:], strict=True)]
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array(out, pa.binary())], names=["doc_id", "body"])

    return factors.select("doc_id", "factors").mapInArrow(run, "doc_id long, body binary")


def decode_sql(factors: DataFrame, dictionary: Dictionary) -> DataFrame:
    """doc_id, body, in built-in functions; for dictionaries small enough to be a literal."""
    if len(dictionary.data) > 1 << 16:
        raise ValueError("a literal dictionary has at most 64 KB")
    rows = factors.withColumn("__d", F.lit(dictionary.data))
    one = "unhex(lpad(hex(f.pos), 2, '0'))"
    body = F.expr(f"aggregate(factors, CAST('' AS BINARY), (a, f) -> concat(a, CASE WHEN f.len = 0 THEN {one} ELSE substring(__d, CAST(f.pos + 1 AS INT), f.len) END))")
    return rows.select("doc_id", body.alias("body"))


def encode(coll: DataFrame, dictionary: Dictionary, codec: str, tie: str = "first_rank", z_form: str = "u32") -> DataFrame:
    """Factors and codes in one pass: doc_id, dict_version, codec, n_bytes, n_factors, pos_stream, len_stream."""
    ship, version = Shipped(coll.sparkSession, dictionary), dictionary.version

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        search = ship.searcher()
        for b in _sliced(batches):
            ps, ks, n = [], [], b.num_rows
            bodies = b.column(1).to_pylist()
            pos, length, cuts = factor_batch(bodies, search, tie)
            for i, j in zip(cuts[:-1].tolist(), cuts[1:].tolist(), strict=True):
                p, k = codecs.encode_pairs(pos[i:j], length[i:j], codec, z_form)
                ps.append(p)
                ks.append(k)
            sizes, counts = [len(x) for x in bodies], np.diff(cuts)
            yield pa.RecordBatch.from_arrays(
                [b.column(0), pa.array([version] * n, pa.int32()), pa.array([codec] * n), pa.array(sizes, pa.int64()), pa.array(counts, pa.int64()), pa.array(ps, pa.binary()), pa.array(ks, pa.binary())],
                names=["doc_id", "dict_version", "codec", "n_bytes", "n_factors", "pos_stream", "len_stream"],
            )

    return coll.select("doc_id", "body").mapInArrow(run, "doc_id long, dict_version int, codec string, n_bytes long, n_factors long, pos_stream binary, len_stream binary")


def recode(factors: DataFrame, codec: str | tuple[str, ...], z_form: str = "u32", carry: tuple[str, ...] = ()) -> DataFrame:
    """Factors under another codec, without factoring again: doc_id, codec, n_factors, pos_stream, len_stream (and carried columns).

    Of several codecs each gives a row for each document; a stream that they share is coded once.
    """
    names = (codec,) if isinstance(codec, str) else tuple(codec)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            pos, length, cuts = flat_factors(b.column(1))
            spans, counts, made = list(zip(cuts[:-1].tolist(), cuts[1:].tolist(), strict=True)), pa.array(np.diff(cuts).astype(np.int64)), {}
            for c in names:
                if c == "Zi":
                    both = [codecs.encode_pairs(pos[i:j], length[i:j], c, z_form) for i, j in spans]
                    streams = [pa.array(x, pa.binary()) for x in ([p for p, _ in both], [k for _, k in both])]
                else:
                    for side, v in zip(enumerate(c), (pos, length), strict=True):
                        if side not in made:
                            made[side] = pa.array([codecs.encode_stream(v[i:j], side[1], z_form) for i, j in spans], pa.binary())
                    streams = [made[side] for side in enumerate(c)]
                yield pa.RecordBatch.from_arrays([b.column(0), pa.array([c] * b.num_rows, pa.string()), counts, *streams, *b.columns[2:]], names=["doc_id", "codec", "n_factors", "pos_stream", "len_stream", *carry])

    return factors.select("doc_id", "factors", *carry).mapInArrow(run, "doc_id long, codec string, n_factors long, pos_stream binary, len_stream binary" + _carried(factors, carry))


def decode_encoded(enc: DataFrame, dictionary: Dictionary, z_form: str = "u32", carry: tuple[str, ...] = ()) -> DataFrame:
    """doc_id, body (and carried columns) of encoded documents."""
    ship, k = Shipped(enc.sparkSession, dictionary), len(carry)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        d = ship.data()
        for b in batches:
            out = []
            for codec, p, q in zip(*(b.column(k + i).to_pylist() for i in (1, 2, 3)), strict=True):
                pos, length = codecs.decode_pairs(p, q, codec, z_form)
                out.append(decode_document(pos.tolist(), length.tolist(), d))
            yield pa.RecordBatch.from_arrays([*b.columns[: k + 1], pa.array(out, pa.binary())], names=[*b.schema.names[: k + 1], "body"])

    src = enc.select(*carry, "doc_id", "codec", "pos_stream", "len_stream")
    schema = ", ".join(f"`{f.name}` {f.dataType.simpleString()}" for f in src.schema[: k + 1]) + ", body binary"
    return src.mapInArrow(run, schema)


def decode_slices(enc: DataFrame, dictionary: Dictionary, z_form: str = "u32") -> DataFrame:
    """doc_id, part: bytes [start, start + size) of encoded documents; enc also has start and size."""
    ship = Shipped(enc.sparkSession, dictionary)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        d = ship.data()
        for b in batches:
            out = []
            for codec, p, q, start, size in zip(*(b.column(i).to_pylist() for i in range(1, 6)), strict=True):
                pos, length = codecs.decode_pairs(p, q, codec, z_form)
                out.append(decode_range(np.asarray(pos), np.asarray(length), d, start, size))
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array(out, pa.binary())], names=["doc_id", "part"])

    return enc.select("doc_id", "codec", "pos_stream", "len_stream", F.col("start").cast("long"), F.col("size").cast("long")).mapInArrow(run, "doc_id long, part binary")


def mergeable(factors: DataFrame) -> DataFrame:
    """Adjacent factors that lie next to each other in the dictionary; greedy factors have none unless a longer match crosses no document end."""
    rows = factors_long(factors).where(~F.col("is_literal"))
    w = Window.partitionBy("doc_id").orderBy("seq")
    return rows.withColumn("p", F.lag("pos").over(w)).withColumn("k", F.lag("len").over(w)).withColumn("s", F.lag("seq").over(w)).where("s = seq - 1 and p + k = pos").select("doc_id", "seq")
