"""Encoded stores on disk: Parquet sorted by doc_id, segment files with a document map, and reading by id, list, place and scan."""

from __future__ import annotations

import os
import uuid
from collections.abc import Iterator
from urllib.parse import urlparse

import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..operators.dictionary import Dictionary
from ..operators.factorize import decode_encoded
from ..session import tasks_for

#: Lists of requests up to this many distinct ids are sent to the store's tasks; longer ones are joined by id.
BROADCAST_IDS = 200_000
#: Requests of one id that one task serves.
HOT_REQUESTS = 20_000


def write_store(enc: DataFrame, path: str, mode: str = "errorifexists", codec: str = "uncompressed") -> None:
    """Sorted by doc_id in each file, one folder for each dictionary version.

    Nothing moves, so documents are encoded once, in the tasks that write them. Encode what ``with_offsets`` gave in the order of ids and files hold ranges of
    doc_id; otherwise the bloom filters alone narrow a read. Streams are coded already, so files are not compressed again unless asked.
    """
    (
        enc.sortWithinPartitions("dict_version", "doc_id")
        .write.mode(mode)
        .option("compression", codec)
        .option("parquet.block.size", 4 << 20)
        .option("parquet.bloom.filter.enabled#doc_id", "true")
        .partitionBy("dict_version")
        .parquet(path)
    )


def read_store(spark: SparkSession, path: str) -> DataFrame:
    return spark.read.parquet(path)


def write_bucketed(enc: DataFrame, table: str, buckets: int) -> None:
    """As a table in buckets of doc_id: later joins on doc_id with the same buckets need no exchange."""
    enc.write.mode("overwrite").bucketBy(buckets, "doc_id").sortBy("doc_id").saveAsTable(table)


def get(store: DataFrame, dictionary: Dictionary, doc_id: int) -> bytes | None:
    """One document; the filter reaches the scan (min/max and bloom filter of row groups)."""
    rows = decode_encoded(store.where(F.col("doc_id") == doc_id), dictionary).take(1)
    return bytes(rows[0]["body"]) if rows else None


def narrowed(rows: DataFrame, requests: DataFrame) -> DataFrame:
    """The rows that some request asks for: ids are sent to the scan up to a checked number, else met by id."""
    wanted = requests.select("doc_id").distinct()
    few = wanted.limit(BROADCAST_IDS + 1).count() <= BROADCAST_IDS
    return rows.join(F.broadcast(wanted) if few else wanted, "doc_id", "left_semi")


def delivered(requests: DataFrame, bodies: DataFrame, *columns: str) -> DataFrame:
    """req_no, doc_id and columns of bodies for each request. An id that is asked for more than ``HOT_REQUESTS`` times is dealt to several tasks, its body with it."""
    total = requests.count()
    counts = requests.groupBy("doc_id").agg(F.count("*").alias("n"))
    hot = counts.where(F.col("n") > HOT_REQUESTS).select("doc_id", F.ceil(F.col("n") / HOT_REQUESTS).cast("int").alias("shares"))
    asked = requests.select("req_no", "doc_id")
    if total > HOT_REQUESTS:  # so many are hot at most: total / HOT_REQUESTS
        hot = F.broadcast(hot) if total // HOT_REQUESTS <= BROADCAST_IDS else hot
        asked = asked.join(hot, "doc_id", "left").withColumn("share", F.pmod(F.xxhash64("req_no"), F.coalesce("shares", F.lit(1))).cast("int")).drop("shares")
        bodies = bodies.join(hot, "doc_id", "left").withColumn("share", F.explode(F.sequence(F.lit(0), F.coalesce("shares", F.lit(1)) - 1))).drop("shares")
        return asked.join(bodies, ["doc_id", "share"], "left").select("req_no", "doc_id", *columns)
    return asked.join(bodies, "doc_id", "left").select("req_no", "doc_id", *columns)


def retrieve(store: DataFrame, dictionary: Dictionary, requests: DataFrame) -> DataFrame:
    """req_no, doc_id, body for each request; absent ids have a null body. Each document is decoded once, however often it is asked for."""
    return delivered(requests, decode_encoded(narrowed(store, requests), dictionary), "body")


def retrieve_each(store: DataFrame, dictionary: Dictionary, requests: DataFrame) -> DataFrame:
    """The same, but every request is decoded by itself, as a server without a cache answers them."""
    return decode_encoded(delivered(requests, narrowed(store, requests), "codec", "pos_stream", "len_stream").where("codec is not null"), dictionary, carry=("req_no",))


def decode_all(store: DataFrame, dictionary: Dictionary) -> DataFrame:
    return decode_encoded(store, dictionary)


def _local(path: str) -> str:
    u = urlparse(path)
    if u.scheme not in ("", "file"):
        raise ValueError("segment files are written to a file system that all executors mount")
    return u.path


def write_segments(enc: DataFrame, path: str, raw: bool = False) -> DataFrame:
    """Concatenated payloads, one file a partition, and the document map (doc_id, segment, byte_off, byte_len).

    Nothing moves, so documents are encoded once; a segment holds what a task of ``enc`` holds. A payload is the two streams behind their sizes, or with ``raw``
    the body as it is. Files appear under their final name only when whole, and the map that
    is returned comes from the attempts that succeeded.
    """
    root = _local(path)
    names = ["doc_id", "body"] if raw else ["doc_id", "codec", "pos_stream", "len_stream"]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        from pyspark import TaskContext

        segment = TaskContext.get().partitionId()
        os.makedirs(root, exist_ok=True)
        part, at = os.path.join(root, f"{uuid.uuid4().hex}.part"), 0
        rows: list[tuple[int, int, int]] = []
        with open(part, "wb") as f:
            for b in batches:
                for row in zip(*(c.to_pylist() for c in b.columns), strict=True):
                    if raw:
                        body = row[1]
                    else:
                        _, codec, p, k = row
                        body = len(codec).to_bytes(1, "little") + codec.encode() + len(p).to_bytes(4, "little") + p + k
                    f.write(body)
                    rows.append((row[0], at, len(body)))
                    at += len(body)
        os.replace(part, os.path.join(root, f"segment-{segment:06d}"))
        if rows:
            ids, off, size = zip(*rows, strict=True)
            yield pa.RecordBatch.from_arrays([pa.array(ids, pa.int64()), pa.array([segment] * len(ids), pa.int32()), pa.array(off, pa.int64()), pa.array(size, pa.int64())], names=["doc_id", "segment", "byte_off", "byte_len"])

    where = os.path.join(root, "map")
    enc.select(*names).sortWithinPartitions("doc_id").mapInArrow(run, "doc_id long, segment int, byte_off long, byte_len long").write.mode("overwrite").parquet(where)
    return enc.sparkSession.read.parquet(where)


def build_docmap(sizes: DataFrame) -> DataFrame:
    """doc_id, segment, byte_off, byte_len from (doc_id, segment, byte_len): places inside segments by running sums, in parallel."""
    w = Window.partitionBy("segment").orderBy("doc_id").rowsBetween(Window.unboundedPreceding, -1)
    return sizes.select("doc_id", "segment", F.coalesce(F.sum("byte_len").over(w), F.lit(0)).cast("long").alias("byte_off"), "byte_len")


def audit_docmap(docmap: DataFrame) -> DataFrame:
    """Faults of a map: gaps or overlaps inside a segment, and ids that come twice."""
    w = Window.partitionBy("segment").orderBy("byte_off", "byte_len")
    holes = docmap.withColumn("want", F.coalesce(F.lag(F.col("byte_off") + F.col("byte_len")).over(w), F.lit(0))).where("byte_off <> want").select("doc_id", F.lit("place").alias("fault"))
    twice = docmap.groupBy("doc_id").count().where("count > 1").select("doc_id", F.lit("twice").alias("fault"))
    return holes.unionByName(twice)


def retrieve_by_offset(path: str, docmap: DataFrame, requests: DataFrame, dictionary: Dictionary | None) -> DataFrame:
    """req_no, doc_id, body by seeking in segment files: requests meet the map, and each segment is read in order of place. Without a dictionary: raw bodies."""
    root = _local(path)
    from ..operators import codecs
    from ..operators.dictionary import Shipped
    from ..operators.factorize import decode_document

    ship = Shipped(requests.sparkSession, dictionary) if dictionary else None
    wanted = narrowed(docmap, requests)
    wanted = wanted.repartition(tasks_for(docmap), "segment").sortWithinPartitions("segment", "byte_off")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        d = ship.data() if ship else b""
        opened, f = None, None
        for b in batches:
            out = []
            for segment, off, size in zip(*(b.column(i).to_pylist() for i in (1, 2, 3)), strict=True):
                if segment != opened:
                    if f:
                        f.close()
                    opened, f = segment, open(os.path.join(root, f"segment-{segment:06d}"), "rb")  # noqa: SIM115
                f.seek(off)
                raw = f.read(size)
                if ship:
                    n = raw[0]
                    codec, at = raw[1 : 1 + n].decode(), 1 + n
                    k = int.from_bytes(raw[at : at + 4], "little")
                    pos, length = codecs.decode_pairs(raw[at + 4 : at + 4 + k], raw[at + 4 + k :], codec)
                    raw = decode_document(pos.tolist(), length.tolist(), d)
                out.append(raw)
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array(out, pa.binary())], names=["doc_id", "body"])
        if f:
            f.close()

    bodies = wanted.select("doc_id", "segment", "byte_off", "byte_len").mapInArrow(run, "doc_id long, body binary")
    return delivered(requests, bodies, "body")


def snippet(docs: DataFrame, term: str, width: int, body: str = "body") -> DataFrame:
    """doc_id, at, snippet: ``width`` characters on both sides of the term's first occurrence, without regard to case."""
    text = F.decode(F.col(body), "UTF-8")
    at = F.instr(F.lower(text), term.lower())
    start = F.greatest(F.lit(1), at - width)
    return docs.where(at > 0).select("doc_id", at.alias("at"), F.substring(text, start, at - start + len(term) + width).alias("snippet"))
