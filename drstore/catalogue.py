"""Registered queries of the store, its baselines and measures."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from .plans import queries, workloads
from .plans import relational as _relational  # noqa: F401  registers its queries
QUERIES = queries.QUERIES
ORACLE_SQL = queries.ORACLE_SQL


def entry(spark: SparkSession, sf_dir: str) -> DataFrame:
    return workloads.entry(spark, sf_dir)
