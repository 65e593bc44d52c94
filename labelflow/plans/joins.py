"""Lookup joins that hold under skew: the small side is broadcast behind a count, else dealt over salts."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

#: Rows of a few longs that may be broadcast: some 30 MB.
BROADCAST_ROWS = 500_000
SALTS = 16
#: Rows of one key beyond which a join is worth salting, and the hash buckets by which rows of a key are bounded.
HUB_ROWS = 1_000_000
HUB_BUCKETS = 65_536


def salts_for(rows: DataFrame, *columns: str) -> int:
    """Salts that joins of rows on each of the columns need: one where no value has over HUB_ROWS rows. Rows are counted by hash bucket, at
    most HUB_BUCKETS counts a task, and a bucket bounds each of its values."""
    for c in columns:
        sizes = rows.groupBy(F.pmod(F.xxhash64(c), F.lit(HUB_BUCKETS)).alias("bucket")).agg(F.count("*").alias("n"))
        if (sizes.agg(F.max("n")).first()[0] or 0) > HUB_ROWS:
            return SALTS
    return 1


def lookup(left: DataFrame, right: DataFrame, keys: list[str], how: str = "left", salt_by: str | None = None, limit: int = BROADCAST_ROWS, salts: int = SALTS) -> DataFrame:
    """Joins left rows to the one right row of their key. `right` should be cheap to count (a written stage).

    Up to `limit` right rows are broadcast. Beyond that each right row is repeated for every salt and left rows pick theirs by
    the hash of `salt_by`, so that a key with a third of all left rows is spread over `salts` tasks. One salt is a plain
    join, for keys that the caller knows to be even.
    """
    if how not in ("left", "inner"):
        raise ValueError("lookup joins are left or inner")
    if right.count() <= limit:
        return left.join(F.broadcast(right), keys, how)
    right = right.hint("merge")  # else Spark may broadcast it by the size of compressed files
    if salts == 1:
        return left.join(right, keys, how)
    by = F.xxhash64(salt_by) if salt_by else F.xxhash64(*[c for c in left.columns])
    salted = left.withColumn("_salt", F.pmod(by, F.lit(salts)).cast("int"))
    spread = right.withColumn("_salt", F.explode(F.sequence(F.lit(0), F.lit(salts - 1))))
    return salted.join(spread, [*keys, "_salt"], how).drop("_salt")


def without(left: DataFrame, right: DataFrame, keys: list[str], limit: int = BROADCAST_ROWS) -> DataFrame:
    """Left rows whose key is not in `right` (distinct keys, cheap to count); broadcast behind the same count."""
    small = right.count() <= limit
    return left.join(F.broadcast(right) if small else right.hint("merge"), keys, "left_anti")
