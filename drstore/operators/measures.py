"""Sizes, lengths, coverage, histograms and read costs."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F


def vbyte_size(v: Column) -> Column:
    """Bytes of V for a value, in closed form."""
    return sum((F.when(v >= F.lit(1 << (7 * k)), 1).otherwise(0) for k in range(1, 5)), F.lit(1))


def u_size(v: Column) -> Column:
    return F.lit(4)


def ratio(enc: DataFrame, dictionary_bytes: int, map_bytes: int = 24, codecs: tuple[str, ...] = ()) -> DataFrame:
    """n_docs, raw_bytes, enc_bytes, enc_pct (payload), enc_pct_with_map, enc_pct_total (and the dictionary). ``codecs``: a row for each of them, also where it has no document."""
    size = F.octet_length("pos_stream") + F.octet_length("len_stream")
    s = enc.groupBy(*(["codec"] if codecs else [])).agg(F.count("*").alias("n_docs"), F.sum("n_bytes").alias("raw_bytes"), F.sum(size).alias("enc_bytes"))
    if codecs:
        named = enc.sparkSession.createDataFrame([(c,) for c in codecs], "codec string")
        s = named.join(s, "codec", "left").withColumn("n_docs", F.coalesce("n_docs", F.lit(0).cast("long")))
    pct = lambda x: 100.0 * x / F.col("raw_bytes")
    with_map = F.col("enc_bytes") + map_bytes * F.col("n_docs")
    return s.select("*", pct(F.col("enc_bytes")).alias("enc_pct"), pct(with_map).alias("enc_pct_with_map"), pct(with_map + dictionary_bytes).alias("enc_pct_total"))


def lengths(factors: DataFrame) -> DataFrame:
    """One row for each factor: pos, len."""
    return factors.select("doc_id", F.explode("factors").alias("f")).select("doc_id", F.col("f.pos").alias("pos"), F.col("f.len").alias("len"))


def length_stats(factors: DataFrame, s: int) -> DataFrame:
    """Counts and means of factors: a literal covers one byte, and literals are the byte values that the dictionary lacks. Shares of matches under 100, up to the sample size, and in one V byte."""
    match = F.col("len") > 0
    return lengths(factors).agg(
        F.count("*").alias("n_factors"),
        (F.sum(F.greatest("len", F.lit(1))) / F.count("*")).alias("avg_factor_len"),
        F.avg(F.when(match, F.col("len"))).alias("avg_match_len"),
        F.avg((~match).cast("double")).alias("literal_share"),
        F.count_distinct(F.when(~match, F.col("pos"))).alias("absent_bytes"),
        F.avg((F.col("len") < 100).cast("double")).alias("under_100"),
        F.avg((F.col("len") <= s).cast("double")).alias("up_to_sample"),
        F.avg((F.col("len") < 128).cast("double")).alias("one_byte"),
    )


def histogram(factors: DataFrame, fine: int = 100, coarse: int = 10) -> DataFrame:
    """bin, cnt: single lengths below ``fine``, steps of ``coarse`` above."""
    b = F.when(F.col("len") < fine, F.col("len")).otherwise(F.floor(F.col("len") / coarse) * coarse)
    return lengths(factors).groupBy(b.cast("long").alias("bin")).agg(F.count("*").alias("cnt"))


STRIPE = 1 << 16


def used_runs(factors: DataFrame) -> DataFrame:
    """start, stop of the maximal runs of dictionary bytes that factors cover.

    Equal factors are combined first; runs are merged inside stripes of the dictionary, in parallel, and end at stripe borders.
    """
    f = lengths(factors).where("len > 0").groupBy("pos").agg(F.max("len").alias("len"))
    pieces = f.select("pos", (F.col("pos") + F.col("len")).alias("stop")).select(F.explode(F.sequence(F.floor(F.col("pos") / STRIPE), F.floor((F.col("stop") - 1) / STRIPE))).alias("stripe"), "pos", "stop")
    pieces = pieces.select("stripe", F.greatest("pos", F.col("stripe") * STRIPE).alias("start"), F.least("stop", (F.col("stripe") + 1) * STRIPE).alias("stop"))
    return _merge(pieces, "stripe")


def _merge(pieces: DataFrame, by: str) -> DataFrame:
    w = Window.partitionBy(by).orderBy("start", "stop")
    reach = F.max("stop").over(w.rowsBetween(Window.unboundedPreceding, -1))
    marked = pieces.withColumn("fresh", (reach.isNull() | (F.col("start") > reach)).cast("int"))
    grouped = marked.withColumn("run", F.sum("fresh").over(w))
    return grouped.groupBy(by, "run").agg(F.min("start").alias("start"), F.max("stop").alias("stop")).select("start", "stop")


def unused_pct(factors: DataFrame, m: int) -> DataFrame:
    """m, used_bytes, unused_pct."""
    used = F.coalesce(F.sum(F.col("stop") - F.col("start")), F.lit(0))
    return used_runs(factors).agg(used.alias("used_bytes")).select(F.lit(m).cast("long").alias("m"), "used_bytes", (100.0 * (m - F.col("used_bytes")) / m).alias("unused_pct"))


def unused_pct_bitmap(factors: DataFrame, m: int) -> DataFrame:
    """The same by bitmaps of dictionary bytes."""
    f = lengths(factors).where("len > 0").groupBy("pos").agg(F.max("len").alias("len"))
    bytes_ = f.select(F.explode(F.sequence(F.col("pos"), F.col("pos") + F.col("len") - 1)).alias("b"))
    maps = bytes_.groupBy(F.bitmap_bucket_number("b").alias("bucket")).agg(F.bitmap_construct_agg(F.bitmap_bit_position("b")).alias("bits"))
    return maps.agg(F.coalesce(F.sum(F.bitmap_count("bits")), F.lit(0)).alias("used_bytes")).select(F.lit(m).cast("long").alias("m"), "used_bytes", (100.0 * (m - F.col("used_bytes")) / m).alias("unused_pct"))


def position_skew(factors: DataFrame) -> DataFrame:
    """How concentrated positions are inside documents and in the whole: distinct shares and repeated pairs."""
    f = lengths(factors).where("len > 0")
    by_doc = f.groupBy("doc_id").agg(F.count("*").alias("n"), F.count_distinct("pos").alias("d"), F.count_distinct("pos", "len").alias("p"))
    inside = by_doc.agg(F.sum("n").alias("n_matches"), (F.sum("d") / F.sum("n")).alias("distinct_in_documents"), (1 - F.sum("p") / F.sum("n")).alias("repeated_pairs_in_documents"))
    whole = f.agg((F.count_distinct("pos") / F.count("*")).alias("distinct_overall"))
    return inside.crossJoin(whole)


def foreign_bytes(factors: DataFrame, placed: DataFrame, s: int, c: int, n: int) -> DataFrame:
    """Of the matched bytes, how many come from samples that lie in the document itself and how many from elsewhere.

    Factors meet their sample by number (an equality), never by comparing ranges of all with all.
    """
    f = lengths(factors).where("len > 0").withColumn("k", F.least(F.floor(F.col("pos") / s), F.lit(c - 1)).cast("long"))
    at = F.floor(F.col("k").cast("decimal(38,0)") * n / F.lit(c)).cast("long") + (F.col("pos") - F.col("k") * s)
    own = placed.select("doc_id", "start_off", (F.col("start_off") + F.col("n_bytes")).alias("end_off"))
    rows = f.withColumn("at", at).join(own, "doc_id")
    inside = (F.col("at") >= F.col("start_off")) & (F.col("at") < F.col("end_off"))
    return rows.agg(F.sum(F.when(inside, F.col("len")).otherwise(0)).alias("own_bytes"), F.sum(F.when(inside, 0).otherwise(F.col("len"))).alias("foreign_bytes"))


def block_cost(blocked: DataFrame) -> DataFrame:
    """Bytes decoded for one request of each document of a blocked store: from the block's start to the document's end."""
    w = Window.partitionBy("block_id")
    return blocked.select("doc_id", "block_id", (F.col("start_off") - F.min("start_off").over(w) + F.col("n_bytes")).alias("decoded_bytes"))


def memory_need(m: int, block: int) -> dict[str, int]:
    """Bytes that stay in memory: to decode and to encode by a dictionary, and to decode a block."""
    return {"dictionary_decode": m, "dictionary_encode": 5 * m, "block_decode": block}


def ratio_spread(enc: DataFrame) -> DataFrame:
    """Percentiles of the ratio of single documents."""
    r = 100.0 * (F.octet_length("pos_stream") + F.octet_length("len_stream")) / F.greatest(F.col("n_bytes"), F.lit(1))
    return enc.where("n_bytes > 0").select(r.alias("r")).agg(*(F.percentile_approx("r", p / 100).alias(f"p{p}") for p in (5, 25, 50, 75, 95)), F.avg("r").alias("mean"))
