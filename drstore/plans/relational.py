"""The relational surface around the store, on the star tables and the request stream."""

from __future__ import annotations

from pyspark.sql import Window
from pyspark.sql import functions as F

from ..sources.tables import load, register
from ..streaming import requests as rq
from . import inputs
from .queries import query, scratch

_REQ = "(SELECT event_id, ts, user_id, (event_id * 2654435761) % (SELECT count(*) FROM documents) AS doc_id FROM events)"


def _requests(spark, sf):
    return rq.as_requests(load(spark, sf, "events"), load(spark, sf, "documents").count())


@query("request_windows_tumbling", f"SELECT date_trunc('day', ts) AS window_start, count(*) AS requests, CAST(sum(doc_id) AS BIGINT) AS id_sum FROM {_REQ} GROUP BY 1")
def _tumbling(spark, sf):
    return rq.tumbling(_requests(spark, sf))


@query("request_windows_sliding", f"SELECT window_start, count(*) AS requests FROM (SELECT unnest([date_trunc('day', ts), date_trunc('day', ts) - INTERVAL 1 DAY]) AS window_start FROM {_REQ}) GROUP BY 1")
def _sliding(spark, sf):
    return rq.sliding(_requests(spark, sf))


@query(
    "request_sessions",
    "WITH g AS (SELECT user_id, ts, CASE WHEN ts - lag(ts) OVER (PARTITION BY user_id ORDER BY ts) < INTERVAL 6 HOUR THEN 0 ELSE 1 END AS fresh FROM events), s AS (SELECT *, sum(fresh) OVER (PARTITION BY user_id ORDER BY ts) AS n FROM g) SELECT user_id, min(ts) AS session_start, count(*) AS requests FROM s GROUP BY user_id, n",
)
def _sessions(spark, sf):
    return rq.sessions(_requests(spark, sf))


@query("requests_deduplicated", f"SELECT DISTINCT user_id, doc_id FROM {_REQ}")
def _dedup(spark, sf):
    return rq.deduplicated(_requests(spark, sf), ["user_id", "doc_id"], False).select("user_id", "doc_id")


_VERSIONS = "(SELECT min(ts) + k * INTERVAL 5 DAY AS since, CAST(k AS INT) AS dict_version FROM events, range(0, 6) AS r(k) GROUP BY k)"


@query("version_in_force", f"SELECT event_id, ts, dict_version FROM events ASOF LEFT JOIN {_VERSIONS} v ON events.ts >= v.since")
def _asof(spark, sf):
    e = load(spark, sf, "events")
    v = e.agg(F.min("ts").alias("t")).crossJoin(spark.range(6)).select((F.col("t") + F.expr("make_dt_interval(CAST(id AS INT) * 5)")).alias("since"), F.col("id").cast("int").alias("dict_version"))
    return rq.versions_in_force(_requests(spark, sf), v)


@query("request_load_by_day_and_type", "SELECT CAST(date_trunc('day', ts) AS TIMESTAMP) AS day, event_type, count(*) AS n, round(sum(value), 4) AS value, count(DISTINCT user_id) AS users FROM events GROUP BY ALL")
def _load_by(spark, sf):
    return load(spark, sf, "events").groupBy(F.date_trunc("day", "ts").alias("day"), "event_type").agg(F.count("*").alias("n"), F.round(F.sum("value"), 4).alias("value"), F.count_distinct("user_id").alias("users"))


@query("event_properties", "SELECT event_id, CAST(json_extract_string(props, '$.k') AS INT) AS k FROM events WHERE CAST(json_extract_string(props, '$.k') AS INT) BETWEEN 10 AND 20")
def _props(spark, sf):
    return load(spark, sf, "events").select("event_id", F.from_json("props", "k int")["k"].alias("k")).where(F.col("k").between(10, 20))


def _stream(spark, sf, name: str, files: int = 3):
    """The table as a stream of Parquet files."""
    rows = load(spark, sf, name)
    path = scratch(spark, "stream")
    rows.repartition(files).write.parquet(path)
    return rq.read_stream(spark, path, rows.schema)


def _drain(spark, df, mode: str):
    """The result of a stream run to the end of its input."""
    name = "drstore_sink_" + scratch(spark, "x")[-12:].replace("-", "_")
    q = df.writeStream.format("memory").queryName(name).outputMode(mode).option("checkpointLocation", scratch(spark, "checkpoint")).trigger(availableNow=True).start()
    q.awaitTermination()
    return spark.table(name)


@query("stream_request_windows", f"SELECT date_trunc('day', ts) AS window_start, count(*) AS requests, CAST(sum(doc_id) AS BIGINT) AS id_sum FROM {_REQ} GROUP BY 1")
def _stream_windows(spark, sf):
    n = load(spark, sf, "documents").count()
    return _drain(spark, rq.tumbling(rq.as_requests(_stream(spark, sf, "events"), n)), "complete")


@query("stream_static_join", "SELECT lang, count(*) AS requests FROM (SELECT (event_id * 2654435761) % (SELECT count(*) FROM documents) AS doc_id FROM events) JOIN documents USING (doc_id) GROUP BY 1")
def _stream_static(spark, sf):
    docs = load(spark, sf, "documents").select("doc_id", "lang")
    r = rq.as_requests(_stream(spark, sf, "events"), docs.count())
    return _drain(spark, r.join(docs, "doc_id").groupBy("lang").agg(F.count("*").alias("requests")), "complete")


@query("stream_deduplicated_requests", "SELECT count(DISTINCT event_id) AS requests FROM events")
def _stream_dedup(spark, sf):
    e = _stream(spark, sf, "events").withColumn("ts", F.col("ts").cast("timestamp")).withWatermark("ts", "60 days")
    return _drain(spark, rq.deduplicated(e, ["event_id"], True).groupBy().agg(F.count("*").alias("requests")), "complete")


@query("stream_stream_join", "SELECT event_id, ts, ts + INTERVAL 5 MINUTE AS rts FROM events")
def _stream_stream(spark, sf):
    """A response five minutes after every request, joined within ten minutes."""
    a = _stream(spark, sf, "events", 1).select("event_id", F.col("ts").cast("timestamp").alias("ts"))
    b = _stream(spark, sf, "events", 1).select("event_id", (F.col("ts").cast("timestamp") + F.expr("INTERVAL 5 MINUTES")).alias("rts"))
    return _drain(spark, rq.answered(a, b), "append")


@query("stream_ratio_drift", "SELECT event_type AS grp, count(*) AS n FROM events GROUP BY 1")
def _drift(spark, sf):
    """The smoothed value of each event type as the stream's state ends."""
    from ..streaming.append import ratio_drift

    e = _stream(spark, sf, "events").withColumn("ratio", F.col("value"))
    out = _drain(spark, ratio_drift(e, "event_type"), "update")
    return out.groupBy("grp").agg(F.max("n").alias("n"))


@query("stream_appended_documents", "SELECT doc_id, md5(text) AS digest FROM documents WHERE doc_id % 10 >= 7")
def _stream_append(spark, sf):
    from ..operators import collection as col
    from ..operators import dictionary as dic
    from ..operators import factorize
    from ..streaming.append import Appender

    base = inputs.documents(spark, sf).where("doc_id % 10 < 7")
    a = Appender(spark, scratch(spark, "append"), dic.build(col.with_offsets(base), dic.DictSpec(pct=2.0, s=512)))
    new = _stream(spark, sf, "documents").where("doc_id % 10 >= 7").select("doc_id", "text")
    a.start(new, scratch(spark, "checkpoint")).awaitTermination()
    return factorize.decode_encoded(a.store(), a.dictionary).select("doc_id", F.md5("body").alias("digest"))


# -- joins


@query("join_inner_star", "SELECT r_name, n_name, count(*) AS orders, round(sum(o_totalprice), 2) AS total FROM orders JOIN customer ON o_custkey = c_custkey JOIN nation ON c_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey GROUP BY ALL")
def _star(spark, sf):
    o, c, n, r = (load(spark, sf, x) for x in ("orders", "customer", "nation", "region"))
    small = n.join(r, n["n_regionkey"] == r["r_regionkey"])  # 25 rows: nations are fixed
    j = o.join(c, o["o_custkey"] == c["c_custkey"]).join(F.broadcast(small), F.col("c_nationkey") == F.col("n_nationkey"))
    return j.groupBy("r_name", "n_name").agg(F.count("*").alias("orders"), F.round(F.sum("o_totalprice"), 2).alias("total"))


@query("join_left_semi", "SELECT doc_id, lang FROM documents WHERE doc_id IN (SELECT doc_id FROM labels WHERE toxic = 1)")
def _semi(spark, sf):
    return load(spark, sf, "documents").join(load(spark, sf, "labels").where("toxic = 1"), "doc_id", "left_semi").select("doc_id", "lang")


@query("join_left_anti", "SELECT doc_id FROM documents WHERE doc_id NOT IN (SELECT doc_id FROM labels)")
def _anti(spark, sf):
    return load(spark, sf, "documents").join(load(spark, sf, "labels"), "doc_id", "left_anti").select("doc_id")


@query("join_full_outer", "SELECT coalesce(a.k, b.k) AS k, a.n AS suppliers, b.n AS customers FROM (SELECT s_nationkey AS k, count(*) AS n FROM supplier WHERE s_acctbal > 0 GROUP BY 1) a FULL JOIN (SELECT c_nationkey AS k, count(*) AS n FROM customer WHERE c_acctbal > 9000 GROUP BY 1) b ON a.k = b.k")
def _outer(spark, sf):
    a = load(spark, sf, "supplier").where("s_acctbal > 0").groupBy(F.col("s_nationkey").alias("k")).agg(F.count("*").alias("suppliers"))
    b = load(spark, sf, "customer").where("c_acctbal > 9000").groupBy(F.col("c_nationkey").alias("k")).agg(F.count("*").alias("customers"))
    return a.join(b, "k", "full").select("k", "suppliers", "customers")


@query(
    "join_ranges_by_stripe",
    "WITH p AS (SELECT doc_id, sum(octet_length(encode(text))) OVER (ORDER BY doc_id) - octet_length(encode(text)) AS s, octet_length(encode(text)) AS b FROM documents), w AS (SELECT k, CAST(k * 25000 AS BIGINT) AS ws, CAST(k * 25000 + 700 AS BIGINT) AS we FROM range(0, (SELECT CAST((sum(b) + 24999) // 25000 AS BIGINT) FROM p)) AS r(k)) SELECT k, doc_id FROM w JOIN p ON s < we AND s + b > ws",
)
def _ranges(spark, sf):
    """Windows over the whole line that overlap documents: both sides go to stripes of the line, and the equality on stripes carries the join."""
    stripe = 8192
    p = inputs.placed(spark, sf, "documents").where("n_bytes > 0").select("doc_id", F.col("start_off").alias("s"), (F.col("start_off") + F.col("n_bytes")).alias("e"))
    windows = -(-(p.agg(F.max("e")).first()[0] or 0) // 25000)
    w = spark.range(windows).select(F.col("id").alias("k"), (F.col("id") * 25000).alias("ws"), (F.col("id") * 25000 + 700).alias("we"))
    p = p.withColumn("g", F.explode(F.sequence(F.floor(F.col("s") / stripe), F.floor((F.col("e") - 1) / stripe))))
    w = w.withColumn("g", F.explode(F.sequence(F.floor(F.col("ws") / stripe), F.floor((F.col("we") - 1) / stripe))))
    return w.join(p, (w["g"] == p["g"]) & (F.col("s") < F.col("we")) & (F.col("e") > F.col("ws"))).select("k", "doc_id").distinct()


@query("join_lateral_top", "SELECT n_nationkey, c_custkey FROM nation, LATERAL (SELECT c_custkey FROM customer WHERE c_nationkey = n_nationkey ORDER BY c_acctbal DESC, c_custkey LIMIT 3)")
def _lateral(spark, sf):
    register(spark, sf)
    return spark.sql("SELECT n_nationkey, c_custkey FROM nation, LATERAL (SELECT c_custkey FROM customer WHERE c_nationkey = n_nationkey ORDER BY c_acctbal DESC, c_custkey LIMIT 3)")


@query("join_salted", f"SELECT event_type, lang, count(*) AS n FROM (SELECT event_type, (event_id * 2654435761) % (SELECT count(*) FROM documents) % 7 AS doc_id FROM events) JOIN documents USING (doc_id) GROUP BY ALL")
def _salted(spark, sf):
    """Few hot ids: requests are salted and the documents repeated for each salt."""
    n = load(spark, sf, "documents").count()
    e = load(spark, sf, "events").select("event_type", ((F.col("event_id") * rq.STEP) % n % 7).alias("doc_id"), F.pmod(F.xxhash64("event_id"), F.lit(8)).alias("salt"))
    d = load(spark, sf, "documents").select("doc_id", "lang", F.explode(F.sequence(F.lit(0).cast("long"), F.lit(7).cast("long"))).alias("salt"))
    return e.join(d, ["doc_id", "salt"]).groupBy("event_type", "lang").agg(F.count("*").alias("n"))


# -- aggregates, windows, sets


@query("aggregate_grouping_sets", "SELECT l_returnflag, l_linestatus, count(*) AS n, CAST(sum(l_quantity) AS DOUBLE) AS qty FROM lineitem GROUP BY GROUPING SETS ((l_returnflag, l_linestatus), (l_returnflag), ())")
def _sets(spark, sf):
    g = load(spark, sf, "lineitem").groupingSets([["l_returnflag", "l_linestatus"], ["l_returnflag"], []], "l_returnflag", "l_linestatus")
    return g.agg(F.count("*").alias("n"), F.sum("l_quantity").alias("qty"))


@query("aggregate_pricing_summary", "SELECT l_returnflag, l_linestatus, CAST(sum(l_quantity) AS DOUBLE) AS sum_qty, round(sum(l_extendedprice * (1 - l_discount)), 2) AS sum_disc_price, round(avg(l_discount), 6) AS avg_disc, count(*) AS count_order FROM lineitem WHERE l_shipdate <= TIMESTAMP '1998-09-02' GROUP BY ALL")
def _pricing(spark, sf):
    return load(spark, sf, "lineitem").where("l_shipdate <= timestamp'1998-09-02'").groupBy("l_returnflag", "l_linestatus").agg(F.sum("l_quantity").alias("sum_qty"), F.round(F.sum(F.col("l_extendedprice") * (1 - F.col("l_discount"))), 2).alias("sum_disc_price"), F.round(F.avg("l_discount"), 6).alias("avg_disc"), F.count("*").alias("count_order"))


@query("aggregate_statistics", "SELECT event_type, median(value) AS med, round(stddev_samp(value), 6) AS sd, min_by(event_id, value) AS least, max(value) AS most, count(*) FILTER (value > 50) AS over, bool_and(value > 0) AS positive FROM events GROUP BY 1")
def _stats(spark, sf):
    """Of the events with the least value the one with the least id."""
    place = F.when(F.col("value").isNotNull() & F.col("event_id").isNotNull(), F.struct("value", "event_id"))
    return load(spark, sf, "events").groupBy("event_type").agg(F.median("value").alias("med"), F.round(F.stddev_samp("value"), 6).alias("sd"), F.min_by("event_id", place).alias("least"), F.max("value").alias("most"), F.count_if(F.col("value") > 50).alias("over"), F.bool_and(F.col("value") > 0).alias("positive"))


@query("aggregate_sketches")
def _sketches(spark, sf):
    """Approximate distinct counts and quantiles beside the exact ones."""
    return load(spark, sf, "lineitem").agg(F.approx_count_distinct("l_partkey").alias("approx_parts"), F.count_distinct("l_partkey").alias("parts"), F.percentile_approx("l_extendedprice", 0.5).alias("approx_median"), F.median("l_extendedprice").alias("median"))


@query("aggregate_pivot", "SELECT event_type, count(*) FILTER (dayofweek(ts) = 1) AS monday, count(*) FILTER (dayofweek(ts) = 0) AS sunday FROM events GROUP BY 1")
def _pivot(spark, sf):
    e = load(spark, sf, "events").withColumn("d", F.dayofweek("ts"))
    p = e.groupBy("event_type").pivot("d", [2, 1]).count()
    return p.select("event_type", F.coalesce(F.col("2"), F.lit(0)).alias("monday"), F.coalesce(F.col("1"), F.lit(0)).alias("sunday"))


@query("aggregate_unpivot", "SELECT p_partkey, k, v FROM (UNPIVOT (SELECT p_partkey, CAST(p_size AS DOUBLE) AS p_size, p_retailprice FROM part) ON p_size, p_retailprice INTO NAME k VALUE v)")
def _unpivot(spark, sf):
    p = load(spark, sf, "part").select("p_partkey", F.col("p_size").cast("double").alias("p_size"), "p_retailprice")
    return p.unpivot("p_partkey", ["p_size", "p_retailprice"], "k", "v")


@query("window_analytic", "SELECT c_custkey, rank() OVER w AS r, dense_rank() OVER w AS dr, ntile(4) OVER (PARTITION BY c_nationkey ORDER BY c_acctbal DESC, c_custkey) AS q, lag(c_custkey) OVER (PARTITION BY c_nationkey ORDER BY c_acctbal DESC, c_custkey) AS before FROM customer WINDOW w AS (PARTITION BY c_nationkey ORDER BY c_acctbal DESC)")
def _windows(spark, sf):
    w = Window.partitionBy("c_nationkey").orderBy(F.desc("c_acctbal"))
    v = Window.partitionBy("c_nationkey").orderBy(F.desc("c_acctbal"), "c_custkey")
    return load(spark, sf, "customer").select("c_custkey", F.rank().over(w).alias("r"), F.dense_rank().over(w).alias("dr"), F.ntile(4).over(v).alias("q"), F.lag("c_custkey").over(v).alias("before"))


@query("window_moving", "SELECT event_id, round(avg(value) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS BETWEEN 3 PRECEDING AND CURRENT ROW), 6) AS m FROM events")
def _moving(spark, sf):
    w = Window.partitionBy("user_id").orderBy("ts", "event_id").rowsBetween(-3, 0)
    return load(spark, sf, "events").select("event_id", F.round(F.avg("value").over(w), 6).alias("m"))


@query("top_per_group", "SELECT source, doc_id, n_chars FROM documents QUALIFY row_number() OVER (PARTITION BY source ORDER BY n_chars DESC, doc_id) <= 3")
def _top(spark, sf):
    w = Window.partitionBy("source").orderBy(F.desc("n_chars"), "doc_id")
    return load(spark, sf, "documents").withColumn("r", F.row_number().over(w)).where("r <= 3").select("source", "doc_id", "n_chars")


@query("top_overall", "SELECT o_orderkey, o_totalprice FROM orders ORDER BY o_totalprice DESC, o_orderkey LIMIT 10 OFFSET 5")
def _overall(spark, sf):
    return load(spark, sf, "orders").orderBy(F.desc("o_totalprice"), "o_orderkey").select("o_orderkey", "o_totalprice").offset(5).limit(10)


@query("set_operations", "(SELECT 'both' AS k, o_custkey AS v FROM orders INTERSECT SELECT 'both', c_custkey FROM customer WHERE c_acctbal > 0) UNION ALL (SELECT 'never' AS k, c_custkey FROM customer EXCEPT ALL SELECT 'never', o_custkey FROM orders)")
def _set_ops(spark, sf):
    o, c = load(spark, sf, "orders"), load(spark, sf, "customer")
    both = o.select(F.col("o_custkey").alias("v")).intersect(c.where("c_acctbal > 0").select("c_custkey")).select(F.lit("both").alias("k"), "v")
    never = c.select(F.col("c_custkey").alias("v")).exceptAll(o.select("o_custkey")).select(F.lit("never").alias("k"), "v")
    return both.unionByName(never)


@query("scalar_functions", "SELECT doc_id, md5(text) AS m, sha256(text) AS s, length(text) AS chars, CAST(octet_length(encode(text)) AS INT) AS bytes, upper(lang) AS lang, lpad(CAST(doc_id AS VARCHAR), 8, '0') AS padded FROM documents")
def _scalars(spark, sf):
    return load(spark, sf, "documents").select("doc_id", F.md5("text").alias("m"), F.sha2("text", 256).alias("s"), F.length("text").cast("long").alias("chars"), F.octet_length("text").alias("bytes"), F.upper("lang").alias("lang"), F.lpad(F.col("doc_id").cast("string"), 8, "0").alias("padded"))


@query("null_and_case_logic", "SELECT l_orderkey, l_linenumber, CASE WHEN l_discount > 0.05 THEN 'high' WHEN l_discount > 0 THEN 'low' END AS d, nullif(l_linestatus, 'O') IS NOT DISTINCT FROM NULL AS open FROM lineitem WHERE l_quantity BETWEEN 5 AND 7 AND l_returnflag IN ('A', 'R') AND NOT l_tax > 0.04")
def _nulls(spark, sf):
    rows = load(spark, sf, "lineitem").where("l_quantity between 5 and 7 and l_returnflag in ('A', 'R') and not l_tax > 0.04")
    d = F.when(F.col("l_discount") > 0.05, "high").when(F.col("l_discount") > 0, "low")
    return rows.select("l_orderkey", "l_linenumber", d.alias("d"), F.nullif("l_linestatus", F.lit("O")).eqNullSafe(F.lit(None)).alias("open"))
