"""Input tables as DataFrames, and files of other formats as collections."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

TABLES = ("region", "nation", "customer", "supplier", "part", "orders", "lineitem", "events", "documents", "embeddings", "pages", "benchmark", "labels", "conversations")


def load(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def register(spark: SparkSession, sf_dir: str) -> None:
    """Temp views of all tables."""
    for name in TABLES:
        load(spark, sf_dir, name).createOrReplaceTempView(name)


def read_collection(spark: SparkSession, path: str, fmt: str, id_col: str | None = None, body_col: str | None = None) -> DataFrame:
    """doc_id, body of files: one document a file for text and binaryFile, one a row for json, csv, orc and parquet.

    Files without an id are numbered by the hash of their path.
    """
    if fmt == "binaryFile":
        return spark.read.format("binaryFile").load(path).select(F.xxhash64("path").alias("doc_id"), F.col("content").alias("body"))
    if fmt == "text":
        rows = spark.read.option("wholetext", True).text(path).select("_metadata.file_path", "value")
        return rows.select(F.xxhash64("file_path").alias("doc_id"), F.encode("value", "UTF-8").alias("body"))
    reader = spark.read.option("header", True) if fmt == "csv" else spark.read
    rows = reader.format(fmt).load(path)
    return rows.select(F.col(id_col).cast("long").alias("doc_id"), F.encode(F.coalesce(F.col(body_col).cast("string"), F.lit("")), "UTF-8").alias("body"))
