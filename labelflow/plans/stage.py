"""Cutting lineage: a stage is written to the folder that driver and executors share and read back from there."""

from __future__ import annotations

import atexit
import gc
import uuid
from collections.abc import Iterator
from contextlib import contextmanager

from pyspark.sql import DataFrame, SparkSession

CLEANUP_KEY = "spark.sql.classic.shuffleDependency.fileCleanup.enabled"
ARROW_KEY = "spark.sql.execution.arrow.maxRecordsPerBatch"
#: Bytes of written files beyond which a stage is too large for Spark to broadcast by its own estimate.
SMALL_STAGE = 256 * 1024


def shared_dir(spark: SparkSession) -> str:
    """The folder all executors see: spark.checkpoint.dir of the session; one of our own only in local mode."""
    found = spark.conf.get("spark.checkpoint.dir", None) or spark.sparkContext.getConf().get("spark.checkpoint.dir")
    if found:
        return found.rstrip("/")
    if not spark.sparkContext.master.startswith("local"):
        raise ValueError("spark.checkpoint.dir must name a folder that driver and executors share")
    return "file:///tmp/labelflow-checkpoints"


def new_path(spark: SparkSession, label: str) -> str:
    """A fresh, fully qualified path in the shared folder, removed when the driver process ends."""
    where = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(f"{shared_dir(spark)}/labelflow-{label}-{uuid.uuid4().hex}")
    path = where.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).makeQualified(where).toString()
    if path.startswith("file:/") and not path.startswith("file://"):
        path = path.replace("file:/", "file:///", 1)
    atexit.register(_quiet_remove, spark, path)
    return path


def remove_path(spark: SparkSession, path: str) -> None:
    where = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(path)
    where.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(where, True)


def _quiet_remove(spark: SparkSession, path: str) -> None:
    try:
        if spark.sparkContext._jsc is not None:
            remove_path(spark, path)
    except Exception:  # noqa: BLE001  the session may be gone at interpreter exit
        return


def stored_bytes(spark: SparkSession, path: str) -> int:
    where = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(path)
    return where.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).getContentSummary(where).getLength()


@contextmanager
def shuffle_cleanup(spark: SparkSession) -> Iterator[None]:
    """Drops a query's shuffle files once it has been written; for operators that run several jobs."""
    before = spark.conf.get(CLEANUP_KEY, "false")
    spark.conf.set(CLEANUP_KEY, "true")
    try:
        yield
    finally:
        spark.conf.set(CLEANUP_KEY, before)


@contextmanager
def arrow_rows(spark: SparkSession, rows: int) -> Iterator[None]:
    """Sends Python at most `rows` rows at once; for stages of wide rows, whose batches else take hundreds of MB on both sides."""
    before = spark.conf.get(ARROW_KEY)
    spark.conf.set(ARROW_KEY, str(min(rows, int(before)) if int(before) > 0 else rows))
    try:
        yield
    finally:
        spark.conf.set(ARROW_KEY, before)


def materialise(df: DataFrame, label: str = "stage", by: str | None = None) -> DataFrame:
    """Writes a stage and reads it back: lineage ends, and a lost executor loses nothing. `by` names a column (the last) whose
    values get a folder each, so that a filter on it reads only those.

    Spark takes a stage's compressed files for its size, and would send millions of rows of sorted ids through the driver; so a
    stage of over SMALL_STAGE is never broadcast unless a join says so (plans.joins does, by count)."""
    spark = df.sparkSession
    path = new_path(spark, label)
    with shuffle_cleanup(spark):
        (df.write.partitionBy(by) if by else df.write).parquet(path)
    gc.collect()
    out = spark.read.schema(df.schema).parquet(path)
    if stored_bytes(spark, path) > SMALL_STAGE:
        out = out.hint("merge")
    out._labelflow_path = path
    return out


def release(*frames: DataFrame) -> None:
    """Removes the files of materialised stages that nothing reads any more."""
    for df in frames:
        path = getattr(df, "_labelflow_path", None)
        if path:
            remove_path(df.sparkSession, path)
