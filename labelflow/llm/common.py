"""Shared pieces of the training-data operators: table readers, text columns, Arrow helpers."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from labelflow.plans.joins import lookup
from labelflow.plans.stage import arrow_rows, materialise, new_path, release, remove_path, shared_dir, shuffle_cleanup

__all__ = ["arrow_rows", "ascii_lower", "binary_text", "doc_bucket", "id_column", "join_groups", "materialise", "new_path", "partitions_for", "release", "remove_path", "shared_dir", "shuffle_cleanup", "table"]

MASK64 = (1 << 64) - 1


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    """One of the given tables, through Spark's own reader, so that any file system Spark knows will do."""
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def partitions_for(spark: SparkSession, rows: int, rows_each: int, least: int | None = None) -> int:
    """Partitions so that each holds about rows_each rows, and no fewer than the session's shuffle partitions."""
    floor = least if least is not None else int(spark.conf.get("spark.sql.shuffle.partitions"))
    return max(floor, -(-rows // max(1, rows_each)), 1)


def ascii_lower(col: Column) -> Column:
    """Lower-case A-Z and nothing else."""
    return F.translate(col, "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz")


def binary_text(col: str | Column = "text") -> Column:
    """UTF-8 bytes of a text; null counts as empty."""
    col = F.col(col) if isinstance(col, str) else col
    return F.coalesce(col, F.lit("")).cast("binary")


def doc_bucket(col: str | Column, modulus: int) -> Column:
    """crc32 of the decimal id, modulo: the split rule of the labelled operators."""
    col = F.col(col) if isinstance(col, str) else col
    return F.crc32(col.cast("string").cast("binary")) % modulus


def id_column(batch: pa.RecordBatch, name: str = "doc_id") -> np.ndarray:
    """A bigint column as numpy; nulls become the smallest long, which sorts first like Spark's nulls."""
    col = batch.column(batch.schema.get_field_index(name))
    return col.fill_null(np.iinfo(np.int64).min).to_numpy(zero_copy_only=False)


def join_groups(rows: DataFrame, groups: DataFrame, keys: list[str], size: str, by: list[str], most: int = 256) -> DataFrame:
    """Left join of rows to the one row of their group, which has the group's size in column `size`.

    Groups of over `most` rows are looked up first (broadcast behind a count, else over salts). Their rows then go through the
    join with the small groups under random salts, so no task gets a large group and no small group is copied."""
    held = materialise(groups, "groups")
    values = [c for c in groups.columns if c not in keys]
    large = held.filter(F.col(size) > most).select(*keys, *(F.col(c).alias(f"_large_{c}") for c in values))
    found = lookup(rows.withColumn("_by", F.xxhash64(*by)), large, keys, "left", "_by", limit=100_000)
    salted = found.withColumn("_salt", F.when(F.col(f"_large_{size}").isNull(), F.lit(0)).otherwise(F.pmod("_by", F.lit(1 << 20)) + 1).cast("int"))
    both = salted.join(held.filter(F.col(size) <= most).withColumn("_salt", F.lit(0)), [*keys, "_salt"], "left")
    mine = [F.when(F.col(f"_large_{size}").isNull(), F.col(c)).otherwise(F.col(f"_large_{c}")).alias(c) for c in values]
    return both.select(*rows.columns, *mine)
