"""Collections and dictionaries that workloads and queries share."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..operators import collection as col
from ..operators import dictionary as dic
from ..sources.tables import load

#: dictionary sizes in % of the collection: the published ratio classes of both collections, and a wider set
CLASSES = {"pages": {"S": 0.117, "M": 0.235, "L": 0.469}, "documents": {"S": 0.195, "M": 0.391, "L": 0.781}}
WIDE = (1.0, 2.0, 4.0, 8.0)
SAMPLES = (512, 1024, 2048, 5120)


def documents(spark: SparkSession, sf_dir: str) -> DataFrame:
    return col.as_collection(load(spark, sf_dir, "documents"), "doc_id", "text")


def pages(spark: SparkSession, sf_dir: str, *keep: str) -> DataFrame:
    return col.as_collection(load(spark, sf_dir, "pages"), "page_id", "html", keep)


def placed(spark: SparkSession, sf_dir: str, name: str, order: str = "natural") -> DataFrame:
    """documents or pages with places; order: natural, url, host, shuffled."""
    if name == "documents":
        coll = documents(spark, sf_dir)
        return col.with_offsets(coll, [col.shuffled_key()] if order == "shuffled" else None)
    coll = pages(spark, sf_dir, "url")
    keys = {"natural": None, "url": [col.host_key("url")], "host": [col.host_key("url", "host_reversed")], "shuffled": [col.shuffled_key()]}
    return col.with_offsets(coll, keys[order])


def benchmark(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The whole table of benchmark texts, which are short."""
    return col.as_collection(load(spark, sf_dir, "benchmark"), "item_id", "text")


def dictionary(placed_: DataFrame, pct: float = 4.0, s: int = 512, kind: str = "even") -> dic.Dictionary:
    return dic.build(placed_, dic.DictSpec(pct=pct, s=s, kind=kind))


def little_dictionary(spark: SparkSession, sf_dir: str, m: int = 2048, s: int = 256) -> dic.Dictionary:
    """A dictionary of all documents, small enough for SQL to check by definition."""
    return dic.build(placed(spark, sf_dir, "documents"), dic.DictSpec(m_bytes=m, s=s))
