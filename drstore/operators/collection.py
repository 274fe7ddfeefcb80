"""Collections: documents as bytes in an order, with places as if they were one string.

A collection has doc_id, body BINARY, n_bytes; ordered ones also ord and start_off (0-based). Null bodies are empty.
"""

from __future__ import annotations

import json
from math import isqrt

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..session import cut, tasks_for


def as_collection(df: DataFrame, id_col: str, body_col: str, keep: tuple[str, ...] = ()) -> DataFrame:
    kind = dict(df.dtypes)[body_col]
    body = F.col(body_col) if kind == "binary" else F.encode(F.col(body_col).cast("string"), "UTF-8")
    body = F.coalesce(body, F.lit(b"").cast("binary"))
    return df.select(F.col(id_col).cast("long").alias("doc_id"), body.alias("body"), F.octet_length(body).cast("long").alias("n_bytes"), *keep)


def with_offsets(coll: DataFrame, order_by: list[Column] | None = None) -> DataFrame:
    """Adds ord and start_off. Order: ``order_by``, then doc_id (null first), then a hash of the body; equal rows are interchangeable.

    Two passes. Keys and sizes alone are dealt by ranges of the order and give one row a range to the driver: its least key, its rows and bytes. In the second
    pass a document finds its range by comparing its key with these, moves there with its body - the only time that it moves - and gets its place by running
    sums inside the range. So rows are never matched by doc_id, ranges follow the order, and their number follows the input.
    """
    named = coll.withColumns({f"__k{i}": c for i, c in enumerate(order_by or [])} | {"__tie": F.xxhash64("body")})
    by = [c for c in named.columns if c.startswith("__k")] + ["doc_id", "__tie"]
    up = [F.col(c).asc_nulls_first() for c in by]
    ranges = tasks_for(coll)
    # the ranges are fixed before they are looked at
    dealt = cut(named.select(*by, "n_bytes").repartitionByRange(ranges, *up).withColumn("__part", F.spark_partition_id()))
    sums = dealt.groupBy("__part").agg(F.min(F.struct(*by)).alias("least"), F.count("*").alias("n"), F.sum("n_bytes").alias("b")).orderBy("__part").collect()
    if not sums:
        return coll.withColumn("ord", F.lit(0).cast("long")).withColumn("start_off", F.lit(0).cast("long"))
    before, rows, size = [], 0, 0
    for r in sums:
        before.append((rows, size))
        rows, size = rows + r["n"], size + (r["b"] or 0)
    step = isqrt(len(sums)) + 1
    groups = [[r["least"] for r in sums[i : i + step]] for i in range(0, len(sums), step)]
    key = dealt.select(F.struct(*by).alias("k")).schema["k"].dataType.simpleString()
    # constants, which the optimizer folds: some ranges' least keys, all of them in groups, and what comes before each range
    constant = lambda v, kind: F.from_json(F.lit(json.dumps(v)), kind)
    row = lambda r: dict(zip(by, r, strict=True))
    some, every = constant([row(g[0]) for g in groups], f"array<{key}>"), constant([[row(r) for r in g] for g in groups], f"array<array<{key}>>")
    base = constant([{"n": n, "b": b} for n, b in before], "array<struct<n:long,b:long>>")
    own = F.struct(*by)
    reached = lambda least: F.size(F.filter(least, lambda x: x <= own))
    group = F.greatest(reached(some), F.lit(1)) - 1
    placed = named.withColumn("__group", group).withColumn("__part", F.greatest(F.lit(0), F.col("__group") * step + reached(F.get(every, F.col("__group"))) - 1))
    w = Window.partitionBy("__part").orderBy(*up)
    start = F.get(base, F.col("__part"))
    out = placed.drop("__group").repartitionById(len(sums), "__part")
    out = out.withColumn("ord", (start["n"] + F.row_number().over(w) - 1).cast("long"))
    out = out.withColumn("start_off", (start["b"] + F.sum("n_bytes").over(w.rowsBetween(Window.unboundedPreceding, 0)) - F.col("n_bytes")).cast("long"))
    return out.select(*coll.columns, "ord", "start_off")


def total_bytes(coll: DataFrame) -> int:
    return int(coll.agg(F.sum("n_bytes")).first()[0] or 0)


def host_key(url: str = "url", mode: str = "raw") -> Column:
    """Order of pages by address: as it is, or with the host's labels reversed so that a domain's hosts stand together."""
    if mode == "raw":
        return F.col(url)
    host = F.coalesce(F.expr(f"try_parse_url({url}, 'HOST')"), F.lit(""))
    return F.concat_ws("/", F.array_join(F.reverse(F.split(host, r"\.")), "."), F.coalesce(F.expr(f"try_parse_url({url}, 'FILE')"), F.lit("")))


def shuffled_key(seed: int = 0) -> Column:
    """An order without meaning, the same on each run."""
    return F.md5(F.concat_ws(":", F.lit(str(seed)), F.col("doc_id").cast("string")))


def prefix(placed: DataFrame, pct: float) -> DataFrame:
    """The documents of the first pct % of bytes; the last one is cut."""
    n = total_bytes(placed)
    limit = int(n * pct / 100)
    part = placed.where(F.col("start_off") < limit)
    size = F.least(F.col("n_bytes"), F.lit(limit) - F.col("start_off"))
    return part.withColumn("body", F.substring(F.col("body"), F.lit(1), size.cast("int"))).withColumn("n_bytes", size)


def fold(turns: DataFrame, key: str, order: str, text: str) -> DataFrame:
    """One document for each key: its texts in order, joined by newlines."""
    rows = turns.groupBy(F.col(key).cast("long").alias("doc_id")).agg(F.array_sort(F.collect_list(F.struct(F.col(order), F.coalesce(F.col(text), F.lit("")).alias("t")))).alias("x"))
    return as_collection(rows.select("doc_id", F.array_join(F.transform("x", lambda s: s["t"]), "\n").alias("t")), "doc_id", "t")


def record_docs(orders: DataFrame, lineitem: DataFrame) -> DataFrame:
    """One JSON document for each order with its lines."""
    lines = lineitem.groupBy("l_orderkey").agg(F.array_sort(F.collect_list(F.struct("l_linenumber", "l_partkey", "l_suppkey", "l_quantity", "l_extendedprice"))).alias("lines"))
    rows = orders.join(lines, orders["o_orderkey"] == lines["l_orderkey"], "left")
    body = F.to_json(F.struct(F.col("o_orderkey").alias("key"), F.col("o_orderstatus").alias("status"), F.col("o_orderpriority").alias("priority"), F.coalesce("lines", F.array()).alias("lines")))
    return as_collection(rows.select("o_orderkey", body.alias("body")), "o_orderkey", "body")
