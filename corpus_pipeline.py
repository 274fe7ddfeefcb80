"""A training-corpus pipeline of five stages over ``documents``.

Each stage takes (spark, docs, sf_dir) and returns a DataFrame, which is written as Parquet and read again as the next one's docs. All but
the last keep the columns of documents.

1. quality_rules: documents that the base test or the learned decision list rejects go.
2. near_dedup: of each class of near-duplicates (five-word shingles, similarity 0.8 or more) one document stays.
3. secret_scan: secrets in the texts are replaced by a mark.
4. source_mixing: documents are repeated or left out so that the expected token shares of the quality and toxicity domains meet targets. The
   share wanted of good documents is above theirs, so none of these is left out; no document comes more than twice.
5. byte_bpe: token ids of each text, and the digest of what they decode to.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from drstore.llm import byte_bpe, dart_dedup, quality_rules, secret_scan, shared, source_mixing

#: token shares wanted of source_mixing.DOMAINS: good, poor, good but toxic, poor and toxic
TARGETS = (0.985, 0.005, 0.008, 0.002)


def _quality(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    shared.small_batches(spark)
    return quality_rules.filter_documents(docs, spark.read.parquet(f"{sf_dir}/labels.parquet"))


def _dedup(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return dart_dedup.keep_one(docs)


def _secrets(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return secret_scan.redact(docs)


def _mix(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return source_mixing.resample(docs, spark.read.parquet(f"{sf_dir}/labels.parquet"), TARGETS, most=2.0)


def _encode(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    import public_tokenizers

    return byte_bpe.encode(docs, public_tokenizers.path("byte_bpe_multi_50k.tiktoken"), public_tokenizers.PATTERN, carry=("doc_id", "lang", "source", "n_chars"), check=True)


STAGES = [("quality_rules", _quality), ("near_dedup", _dedup), ("secret_scan", _secrets), ("source_mixing", _mix), ("byte_bpe", _encode)]

#: near-duplicate classes, rules and tokens are not for SQL
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    for name, stage in STAGES[:-1]:
        docs = shared.keep(stage(spark, docs, sf_dir), f"pipeline-{name}")
    return STAGES[-1][1](spark, docs, sf_dir)
