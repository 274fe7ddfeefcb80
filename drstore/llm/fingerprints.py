"""Document fingerprints by one-permutation MinHash, in built-in functions only.

Every ``SHINGLE``-word shingle is hashed once (a text of fewer words is one shingle). The upper bits choose one of
``BINS`` bins, each bin keeps its least hash, and an empty bin takes the value of the bin that comes first in an order
of its own (a hash of both bin numbers), which is optimal densification without a bound on tries. The fingerprint packs the low ``BITS`` bits of
each bin as hexadecimal; likeness is the share of equal bins, corrected for chance equality (2^-BITS).

Null text is empty text. A text without a word has the empty fingerprint, which is alike (1) to itself and unlike (0) to any other. Equal texts have equal
fingerprints. An empty table gives an empty result; columns other than doc_id and text are not used.

``with_edits`` also needs each document's successor by doc_id (null first, ties by text hash; repeated rows follow each other as documents of their own;
the last is followed by the first). Rows are dealt by ranges of doc_id, whose bounds are quantiles, and sorted inside a
range; only the first document of each range crosses to the range before. So there is one exchange of texts and no global window.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

BINS, BITS, SHINGLE = 128, 8, 5
_BIN_SHIFT = 64 - (BINS.bit_length() - 1)
_LOW = (1 << BITS) - 1
_SPLIT = r"[\\x20\\x09-\\x0D]+"


def signature(df: DataFrame, text: str, out: str) -> DataFrame:
    """Adds ``out``: array of the low bits of the bins; empty for a text without a word."""
    w, h, s, o, m, b = (f"__{out}_{x}" for x in "whsomb")
    window = ", ".join(f"{h}[i + {k}]" for k in range(SHINGLE))
    return (
        df.withColumn(h, F.expr(f"transform(array_remove(split(coalesce({text}, ''), '{_SPLIT}'), ''), x -> xxhash64(x))"))
        .withColumn(s, F.expr(f"CASE WHEN size({h}) = 0 THEN slice({h}, 1, 0) WHEN size({h}) < {SHINGLE} THEN array(xxhash64({h})) ELSE transform(sequence(0, size({h}) - {SHINGLE}), i -> xxhash64({window})) END"))
        .withColumn(o, F.expr(f"sort_array({s})"))
        .withColumn(m, F.expr(f"filter(zip_with({o}, concat(array(CAST(null AS BIGINT)), {o}), (x, y) -> CASE WHEN y IS NULL OR shiftright(x, {_BIN_SHIFT}) <> shiftright(y, {_BIN_SHIFT}) THEN x END), x -> x IS NOT NULL)"))
        .withColumn(b, F.expr(f"transform({m}, x -> CAST(shiftright(x, {_BIN_SHIFT}) AS INT) + {BINS // 2})"))
        .withColumn(
            out,
            F.expr(
                f"CASE WHEN size({m}) = 0 THEN CAST(array() AS ARRAY<TINYINT>) ELSE transform(sequence(0, {BINS - 1}), k -> CAST((element_at({m}, CAST(coalesce(nullif(array_position({b}, k), 0),"
                f" (array_min(transform({b}, (j, i) -> (shiftleft(shiftright(xxhash64(k, j), 8), 8) | i))) & {BINS - 1}) + 1) AS INT)) & {_LOW}) - {(_LOW + 1) // 2} AS TINYINT)) END"
            ),
        )
        .drop(w, h, s, o, m, b)
    )


def packed(bits: str) -> Column:
    """The fingerprint as text."""
    return F.expr(f"array_join(transform({bits}, v -> lpad(hex(v + {(_LOW + 1) // 2}), {BITS // 4}, '0')), '')")


def likeness(a: str, b: str) -> Column:
    """Estimated Jaccard similarity of two signatures, corrected for chance."""
    chance = 1.0 / (1 << BITS)
    same = f"aggregate(zip_with({a}, {b}, (x, y) -> IF(x = y, 1, 0)), 0, (s, x) -> s + x) / {float(BINS)}D"
    return F.expr(f"CASE WHEN size({a}) = 0 OR size({b}) = 0 THEN IF(size({a}) = size({b}), 1.0D, 0.0D) ELSE greatest(0.0D, ({same} - {chance}D) / {1 - chance}D) END")


def fingerprint(docs: DataFrame, text: str = "text") -> DataFrame:
    """doc_id, n_chars, fingerprint."""
    rows = docs.select(docs["doc_id"].cast("long").alias("doc_id"), F.coalesce(docs[text].cast("string"), F.lit("")).alias("text"))
    return signature(rows, "text", "sig").select("doc_id", F.length("text").cast("long").alias("n_chars"), packed("sig").alias("fingerprint"))


def _ranges(rows: DataFrame, per_partition: int = 4) -> Column:
    """Number of the range of doc_id that a row belongs to; null doc_id is in range 0."""
    n = per_partition * int(rows.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    bounds = rows.select(F.percentile_approx("doc_id", [i / n for i in range(1, n)], 20 * n).alias("b")).first()["b"] or []
    bounds = sorted(set(bounds))
    if not bounds:
        return F.lit(0)
    return F.coalesce(F.size(F.filter(F.lit(bounds), lambda x: x <= F.col("doc_id"))), F.lit(0))


def with_edits(docs: DataFrame, text: str = "text") -> DataFrame:
    """Fingerprints of each text, of its edited text and likeness to the edited and the next one.

    The edited text has its last floor(n_chars / 4) code points replaced by the first as many (or all) of the next document.
    """
    rows = docs.select(docs["doc_id"].cast("long").alias("doc_id"), F.coalesce(docs[text].cast("string"), F.lit("")).alias("text"))
    rows = rows.withColumn("__range", _ranges(rows)).withColumn("__pos", F.coalesce("doc_id", F.lit(-(1 << 63))))
    # the first document of each range: one row a range, so it can be broadcast
    least = rows.groupBy("__range").agg(F.min("__pos").alias("__pos"))
    firsts = rows.join(F.broadcast(least), ["__range", "__pos"]).groupBy("__range").agg(F.min(F.struct(F.xxhash64("text").alias("tie"), F.col("text"))).alias("f"))
    ring = Window.orderBy("__range")
    loop = Window.orderBy("__range").rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing)
    beyond = firsts.select("__range", F.coalesce(F.lead("f").over(ring), F.first("f").over(loop))["text"].alias("text"))
    beyond = beyond.select(F.lit(None).cast("long").alias("doc_id"), "text", "__range", F.lit(0).cast("long").alias("__pos"), F.lit(1).alias("__after"))

    rows = signature(rows.withColumn("__after", F.lit(0)).unionByName(beyond), "text", "__sig")
    w = Window.partitionBy("__range").orderBy("__after", "__pos", F.xxhash64("text"))
    rows = rows.withColumn("__next", F.lead(F.struct(F.col("text").alias("t"), F.col("__sig").alias("s"))).over(w)).where("__after = 0")
    n = F.length("text")
    edited = F.expr("concat(substring(text, 1, length(text) - CAST(floor(length(text) / 4) AS INT)), substring(__next.t, 1, CAST(floor(length(text) / 4) AS INT)))")
    rows = rows.select("doc_id", n.cast("long").alias("n_chars"), edited.alias("__edited"), "__sig", F.col("__next.s").alias("__next_sig"))
    rows = signature(rows, "__edited", "__edited_sig")
    return rows.select("doc_id", "n_chars", F.sha2(F.col("__edited").cast("binary"), 256).alias("edited_sha256"), packed("__sig").alias("fingerprint"), packed("__edited_sig").alias("edited_fingerprint"), likeness("__sig", "__edited_sig").alias("near_edited"), likeness("__sig", "__next_sig").alias("near_next"))
