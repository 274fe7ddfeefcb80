"""Ranked retrieval and request lists, and timing of reads."""

from __future__ import annotations

import time

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

K1, B = 1.2, 0.75


def strip_html(html: Column) -> Column:
    """Text of a page: scripts, styles, comments, tags and entities become spaces."""
    out = F.regexp_replace(html, r"(?is)<(script|style)\b.*?</\1\s*>", " ")
    out = F.regexp_replace(out, r"(?s)<!--.*?-->", " ")
    out = F.regexp_replace(out, r"(?s)<[^>]*>", " ")
    return F.regexp_replace(out, r"&[#\w]+;", " ")


def tokens(rows: DataFrame, id_col: str, text: Column) -> DataFrame:
    """doc_id, term, tf: runs of letters in lower case."""
    words = F.regexp_extract_all(F.lower(F.coalesce(text, F.lit(""))), F.lit(r"\p{L}+"), F.lit(0))
    return rows.select(F.col(id_col).cast("long").alias("doc_id"), F.explode(words).alias("term")).groupBy("doc_id", "term").agg(F.count("*").alias("tf"))


def index_stats(tf: DataFrame) -> tuple[DataFrame, DataFrame, DataFrame]:
    """(term, df), (doc_id, dl), one row (n, avgdl)."""
    df = tf.groupBy("term").agg(F.count("*").alias("df"))
    dl = tf.groupBy("doc_id").agg(F.sum("tf").alias("dl"))
    return df, dl, dl.agg(F.count("*").alias("n"), F.avg("dl").alias("avgdl"))


def rank(queries: DataFrame, tf: DataFrame, model: str = "bm25") -> DataFrame:
    """query_no, doc_id, score (6 decimals). queries: query_no, term (each term once).

    The query terms cut the postings before anything else is joined.
    """
    df, dl, total = index_stats(tf)
    asked = queries.select("term").distinct()
    post = tf.join(asked, "term", "left_semi").join(df.join(asked, "term", "left_semi"), "term").join(dl, "doc_id").crossJoin(F.broadcast(total))
    if model == "bm25":
        idf = F.log(1 + (F.col("n") - F.col("df") + 0.5) / (F.col("df") + 0.5))
        w = idf * F.col("tf") * (K1 + 1) / (F.col("tf") + K1 * (1 - B + B * F.col("dl") / F.col("avgdl")))
    else:
        w = (1 + F.log("tf")) * F.log(F.col("n") / F.col("df"))
    rows = post.select("doc_id", "term", w.alias("w"))
    hits = queries.join(rows, "term").groupBy("query_no", "doc_id").agg(F.sum("w").alias("s"))
    if model != "bm25":
        every = tf.join(df, "term").crossJoin(F.broadcast(total)).groupBy("doc_id").agg(F.sqrt(F.sum(F.pow((1 + F.log("tf")) * F.log(F.col("n") / F.col("df")), 2))).alias("norm"))
        hits = hits.join(every, "doc_id").withColumn("s", F.col("s") / F.greatest("norm", F.lit(1e-12)))
    return hits.select("query_no", "doc_id", F.round("s", 6).alias("score"))


def top_k(ranked: DataFrame, k: int = 20) -> DataFrame:
    """query_no, rank, doc_id, score; ties by doc_id."""
    w = Window.partitionBy("query_no").orderBy(F.desc("score"), "doc_id")
    return ranked.withColumn("rank", F.row_number().over(w)).where(F.col("rank") <= k)


def request_list(top: DataFrame, cap: int) -> DataFrame:
    """req_no, query_no, rank, doc_id: results query after query, capped - the cap is the experiment's. The list has at most ``cap`` rows, so it is numbered at once."""
    first = top.orderBy("query_no", "rank").limit(cap)
    return first.withColumn("req_no", F.row_number().over(Window.orderBy("query_no", "rank")).cast("long") - 1).select("req_no", "query_no", "rank", "doc_id")


def sequential(placed: DataFrame, count: int, n: int) -> DataFrame:
    """req_no, doc_id: ids in stored order, from the start again after the last."""
    ids = placed.select(F.col("ord").alias("at"), "doc_id")
    wanted = placed.sparkSession.range(count).select(F.col("id").alias("req_no"), (F.col("id") % n).alias("at"))
    return wanted.join(ids, "at").select("req_no", "doc_id")


def timed(df: DataFrame) -> float:
    """Seconds of running a result to the noop sink."""
    t = time.perf_counter()
    df.write.format("noop").mode("overwrite").save()
    return time.perf_counter() - t


def docs_per_second(df: DataFrame, requests: int, runs: int = 3) -> dict[str, float]:
    """The first run is reported apart, then the median of the rest."""
    first, *rest = (timed(df) for _ in range(runs))
    rest = sorted(rest) or [first]
    return {"cold_dps": requests / first, "dps": requests / rest[len(rest) // 2]}
