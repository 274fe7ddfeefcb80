"""Cutting lineage, and written tables, through a folder that all executors share."""

from __future__ import annotations

import os
import tempfile

from pyspark.sql import DataFrame, SparkSession


def shared_folder(spark: SparkSession) -> str:
    """URI of ``spark.checkpoint.dir``. Where it is unset a local folder serves a session on one machine, and a cluster is refused."""
    root = spark.conf.get("spark.checkpoint.dir", None)
    if root:
        return root
    if not spark.sparkContext.master.startswith("local"):
        raise ValueError("spark.checkpoint.dir has to name a folder that the driver and all executors share")
    return "file://" + os.path.join(tempfile.gettempdir(), "drstore-checkpoints")


def cut(df: DataFrame) -> DataFrame:
    """df read from a checkpoint in the shared folder."""
    sc = df.sparkSession.sparkContext
    if sc.getCheckpointDir() is None:
        sc.setCheckpointDir(shared_folder(df.sparkSession))
    return df.checkpoint(eager=True)


#: Bytes of input for one task, as the optimizer estimates them, and below which a further task is not worth starting.
TASK_BYTES, LEAST_TASK_BYTES = 64 << 20, 64 << 10


def tasks_for(df: DataFrame, most: int = 20_000) -> int:
    """How many ranges a table is dealt into: enough to keep all cores busy, more where the input is larger."""
    cores = df.sparkSession.sparkContext.defaultParallelism
    size = int(df._jdf.queryExecution().optimizedPlan().stats().sizeInBytes())
    if size >= 1 << 60:  # the optimizer does not know
        return min(most, 2 * cores)
    return max(1, min(most, max(2 * cores, size // TASK_BYTES), 1 + size // LEAST_TASK_BYTES))


#: Rows of an Arrow batch: both sides hold one at once, and documents are large.
BATCH_ROWS = 1000


def small_batches(spark: SparkSession) -> None:
    key = "spark.sql.execution.arrow.maxRecordsPerBatch"
    now = int(spark.conf.get(key, "10000"))
    if now <= 0 or now > BATCH_ROWS:
        spark.conf.set(key, str(BATCH_ROWS))
