"""Requests as a stream of events, each with a batch twin over the whole table."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

STEP = 2654435761


def as_requests(events: DataFrame, n: int) -> DataFrame:
    """event_id, ts, user_id, doc_id: each event asks for one of n documents."""
    return events.select("event_id", "ts", "user_id", ((F.col("event_id") * STEP) % n).alias("doc_id"))


def tumbling(requests: DataFrame, width: str = "1 day") -> DataFrame:
    """window_start, requests, bytes_key: load in windows."""
    w = F.window("ts", width)
    return requests.groupBy(w.alias("w")).agg(F.count("*").alias("requests"), F.sum("doc_id").alias("id_sum")).select(F.col("w.start").alias("window_start"), "requests", "id_sum")


def sliding(requests: DataFrame, width: str = "2 days", step: str = "1 day") -> DataFrame:
    return requests.groupBy(F.window("ts", width, step).alias("w")).agg(F.count("*").alias("requests")).select(F.col("w.start").alias("window_start"), "requests")


def sessions(requests: DataFrame, gap: str = "6 hours") -> DataFrame:
    """user_id, session_start, requests."""
    s = F.session_window("ts", gap)
    return requests.groupBy("user_id", s.alias("w")).agg(F.count("*").alias("requests")).select("user_id", F.col("w.start").alias("session_start"), "requests")


def deduplicated(requests: DataFrame, keys: list[str], streaming: bool) -> DataFrame:
    return requests.dropDuplicatesWithinWatermark(keys) if streaming else requests.dropDuplicates(keys)


def versions_in_force(requests: DataFrame, versions: DataFrame) -> DataFrame:
    """As-of join: event_id, ts, dict_version, the last version whose since is not after the request. versions: since, dict_version - a short list.

    A range join against the sent list, so events are neither sorted nor moved.
    """
    v = versions.select(F.col("since"), F.col("dict_version").cast("int").alias("dict_version"))
    until = v.withColumn("until", F.lead("since").over(Window.orderBy("since")))
    hit = (requests["ts"] >= until["since"]) & (until["until"].isNull() | (requests["ts"] < until["until"]))
    return requests.join(F.broadcast(until), hit, "left").select("event_id", "ts", "dict_version")


def answered(requests: DataFrame, responses: DataFrame, minutes: int = 10) -> DataFrame:
    """Stream-stream join: responses within some minutes after their request."""
    a = requests.withWatermark("ts", "1 hour").alias("a")
    b = responses.withWatermark("rts", "1 hour").alias("b")
    on = F.expr(f"a.event_id = b.event_id AND b.rts BETWEEN a.ts AND a.ts + INTERVAL {minutes} MINUTES")
    return a.join(b, on).select("a.event_id", "a.ts", "b.rts")


def read_stream(spark: SparkSession, path: str, schema) -> DataFrame:
    """A folder of Parquet files as a stream, a file a batch."""
    return spark.readStream.schema(schema).option("maxFilesPerTrigger", 1).parquet(path)
