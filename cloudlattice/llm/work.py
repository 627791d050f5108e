"""Shared helpers: the cluster's work folder, table loading and small column builders."""

from __future__ import annotations

import atexit
import re
import tempfile
import uuid

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

#: White space of the contracts: the space and the control characters from tab to carriage return.
WORD = r"[^\x20\x09-\x0D]+"


BATCH_ROWS, DEFAULT_ROWS = "spark.sql.execution.arrow.maxRecordsPerBatch", "10000"
#: The engine's own setting: shuffle files go when the query that made them has ended.
CLEANUP = "spark.sql.classic.shuffleDependency.fileCleanup.enabled"
#: A work table has at most so many files for each core, and so many tasks in its last stage.
FILES_PER_CORE = 3
#: A task holds one row group while it writes. A local file system starts a process for the permissions of every file,
#: check sum and marker, which costs more than a small file; no other file system reads these settings.
WRITING = {
    "compression": "zstd",
    "parquet.block.size": 32 << 20,
    "mapreduce.fileoutputcommitter.marksuccessfuljobs": "false",
    "fs.file.impl": "org.apache.hadoop.fs.RawLocalFileSystem",
    "fs.file.impl.disable.cache": "true",
}

_own: dict[str, str] = {}


def steady(spark: SparkSession) -> None:
    """Fewer rows in a batch between the engine and Python, as texts make rows large; a value that the user has set stays."""
    if spark.conf.get(BATCH_ROWS) == DEFAULT_ROWS:
        spark.conf.set(BATCH_ROWS, "1000")


def load(spark: SparkSession, sf_dir: str, table: str) -> DataFrame:
    steady(spark)
    return spark.read.parquet(f"{sf_dir}/{table}.parquet")


def work_dir(spark: SparkSession) -> str:
    """The folder in ``spark.checkpoint.dir``; on one machine, where that is unset, a temporary one. A cluster must set it."""
    root = spark.conf.get("spark.checkpoint.dir", None)
    if not root:
        context = spark.sparkContext
        if not re.fullmatch(r"local(\[.*\])?", context.master):
            raise ValueError("spark.checkpoint.dir must name a folder that the driver and all executors share")
        root = _own[context.applicationId] = _own.get(context.applicationId) or tempfile.mkdtemp(prefix="cloudlattice-")
    return root.rstrip("/")


def _remove(spark: SparkSession, path: str) -> None:
    try:
        target = spark._jvm.org.apache.hadoop.fs.Path(path)
        target.getFileSystem(spark._jsc.hadoopConfiguration()).delete(target, True)
    except Exception:  # the session has ended: its folder belongs to the cluster's own clean-up
        return


def written(df: DataFrame, name: str = "step") -> DataFrame:
    """Write ``df`` as a table in the shared work folder and read it back.

    Cuts the lineage, is computed once, and survives lost executors because every
    reader goes to the shared files. Its shuffle files go as soon as it is written; the
    table is removed when the driver ends, or by ``removed``.
    """
    spark = df.sparkSession
    path = f"{work_dir(spark)}/{name}-{uuid.uuid4().hex}"
    steady(spark)
    before = spark.conf.get(CLEANUP, "false")
    spark.conf.set(CLEANUP, "true")
    files = FILES_PER_CORE * max(1, spark.sparkContext.defaultParallelism)
    try:
        df.coalesce(files).write.options(**WRITING).parquet(path)
    finally:
        spark.conf.set(CLEANUP, before)
    atexit.register(_remove, spark, path)
    out = spark.read.schema(df.schema).parquet(path)
    out.work_path = path
    return out


def removed(*tables: DataFrame) -> None:
    """Delete written tables that no later step reads."""
    for table in tables:
        _remove(table.sparkSession, table.work_path)


def word_count(text: Column) -> Column:
    return F.coalesce(F.regexp_count(text, F.lit(WORD)), F.lit(0)).cast("long")


def utf8_bytes(text: Column) -> Column:
    return F.coalesce(F.octet_length(text), F.lit(0)).cast("long")


def partitions_for(spark: SparkSession, least: int = 1) -> int:
    return max(least, int(spark.conf.get("spark.sql.shuffle.partitions")))
