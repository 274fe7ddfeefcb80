"""Files that the driver and every executor can see.

The folder is the cluster's ``spark.checkpoint.dir``; only where that is unset (tests on one machine) a
local folder is used. Model files are written by tasks under a temporary name and renamed, so a task
that is run again leaves the same file. A ``file:`` folder is memory-mapped in place; any other file system
is read through Spark's Hadoop client into an unlinked local file, which is then mapped.
"""

from __future__ import annotations

import atexit
import mmap
import os
import re
import shutil
import tempfile
import uuid
import warnings
from urllib.parse import urlparse

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

_own: list[tuple[SparkSession, str]] = []


def folder(spark: SparkSession) -> str:
    """URI of the shared folder; also makes it Spark's checkpoint folder."""
    root = spark.conf.get("spark.checkpoint.dir", None)
    if not root:
        if not spark.sparkContext.master.startswith("local"):
            raise ValueError("spark.checkpoint.dir has to name a folder that the driver and all executors share")
        root = "file://" + os.path.join(tempfile.gettempdir(), "drstore-shared")
    if spark.sparkContext.getCheckpointDir() is None:
        spark.sparkContext.setCheckpointDir(root)
    return root


#: Rows of an Arrow batch; documents are large, and a batch is held by both sides at once.
BATCH_ROWS = 2000


def small_batches(spark: SparkSession) -> None:
    key = "spark.sql.execution.arrow.maxRecordsPerBatch"
    now = int(spark.conf.get(key, "10000"))
    if now <= 0 or now > BATCH_ROWS:
        spark.conf.set(key, str(BATCH_ROWS))


def fresh(spark: SparkSession, what: str) -> str:
    """A new path under the shared folder, removed when the driver ends."""
    path = f"{folder(spark).rstrip('/')}/{what}-{uuid.uuid4().hex}"
    if not _own:
        atexit.register(_clean)
    _own.append((spark, path))
    return path


def _clean() -> None:
    for spark, p in _own:
        if urlparse(p).scheme in ("", "file"):
            shutil.rmtree(urlparse(p).path, ignore_errors=True)
            continue
        try:  # the session may be gone
            path = spark._jvm.org.apache.hadoop.fs.Path(p)
            path.getFileSystem(spark._jsc.hadoopConfiguration()).delete(path, True)
        except Exception:  # noqa: BLE001
            warnings.warn(f"{p} was left behind", RuntimeWarning, stacklevel=1)


#: plan nodes whose rows come in the same order each time a task is run
_FIXED = {"Project", "Filter", "Relation", "LogicalRelation", "LocalRelation", "SubqueryAlias", "Union"}


def settled(docs: DataFrame) -> DataFrame:
    """docs, written first if its rows may come in another order when a lost task is run again.

    Blocks are named by partition and place, so what a task reads has to be the same each time; scans and what is narrow on top of them are.
    """
    names = {re.sub(r"^[\s:|+'-]*", "", line).split(" ")[0].split("[")[0] for line in docs._jdf.queryExecution().optimizedPlan().toString().splitlines()}
    return docs if names <= _FIXED else keep(docs, "settled")


def keep(df: DataFrame, what: str) -> DataFrame:
    """Cut the lineage: write as Parquet to the shared folder and read it again."""
    spark = df.sparkSession
    path = fresh(spark, what)
    key, held = "spark.sql.classic.shuffleDependency.fileCleanup.enabled", None
    try:  # what was shuffled for the table goes when the table is there
        held = spark.conf.get(key)
        spark.conf.set(key, "true")
    except Exception:  # noqa: BLE001  a Spark without the setting keeps the files until they are collected
        held = None
    try:
        df.write.parquet(path)
    finally:
        if held is not None:
            spark.conf.set(key, held)
    return spark.read.schema(df.schema).parquet(path)


#: A key that more than one row in so many has is met by sending its row to every task; there are no more than this many, so the driver may name them.
HOT_SHARE = 2000


def meet(rows: DataFrame, table: DataFrame, key: str, weight: str, total: int, semi: bool = False) -> DataFrame:
    """rows that have their key in table, with its columns; its keys are distinct. ``weight``: how many of the ``total`` rows have the key. ``semi``: rows alone."""
    limit = total // HOT_SHARE
    how = "left_semi" if semi else "inner"
    # keys are told apart by their hash on both sides, so equal hashes go the same way
    hot = [r[0] for r in table.where(F.col(weight) > limit).select(F.xxhash64(key)).distinct().collect()]
    table = table.select(key) if semi else table.drop(weight)
    if not hot:
        return rows.join(table, key, how)
    is_hot = F.xxhash64(key).isin(hot)
    return rows.where(is_hot).join(F.broadcast(table.where(is_hot)), key, how).unionByName(rows.where(~is_hot).join(table.where(~is_hot), key, how))


def free_name(df: DataFrame, name: str) -> str:
    """The name, with underscores before it until df has no such column."""
    taken = {c.lower() for c in df.columns}
    while name.lower() in taken:
        name = "_" + name
    return name


def _remote(path: str):
    from pyarrow import fs

    return fs.FileSystem.from_uri(path)


def put(path: str, content: bytes) -> None:
    u = urlparse(path)
    if u.scheme in ("", "file"):
        os.makedirs(os.path.dirname(u.path), exist_ok=True)
        part = f"{u.path}.{uuid.uuid4().hex}.part"
        with open(part, "wb") as f:
            f.write(content)
        os.replace(part, u.path)
        return
    system, inner = _remote(path)
    system.create_dir(os.path.dirname(inner), recursive=True)
    part = f"{inner}.{uuid.uuid4().hex}.part"
    with system.open_output_stream(part) as f:
        f.write(content)
    system.move(part, inner)


def view(path: str) -> memoryview:
    """Read-only mapping of a file of the shared folder."""
    u = urlparse(path)
    if u.scheme in ("", "file"):
        with open(u.path, "rb") as f:
            return memoryview(mmap.mmap(f.fileno(), 0, access=mmap.ACCESS_READ)) if os.fstat(f.fileno()).st_size else memoryview(b"")
    system, inner = _remote(path)
    with tempfile.TemporaryFile() as local:
        with system.open_input_stream(inner) as f:
            shutil.copyfileobj(f, local)
        local.flush()
        return memoryview(mmap.mmap(local.fileno(), 0, access=mmap.ACCESS_READ)) if local.tell() else memoryview(b"")


def remove(path: str) -> None:
    u = urlparse(path)
    if u.scheme in ("", "file"):
        if os.path.exists(u.path):
            os.unlink(u.path)
        return
    system, inner = _remote(path)
    system.delete_file(inner)
