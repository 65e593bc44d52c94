"""Deterministic randomness by modular arithmetic, the same in Spark and in plain SQL."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

#: Modulus and multipliers of the mix: fixed values that seeds, batches and random graphs depend on.
P = 2147483647
A1, B1, C1 = 48271, 40692, 13
A2, B2, C2 = 69621, 16807, 7


def _fifth(x: Column) -> Column:
    square = (x * x) % P
    return ((square * square) % P * x) % P


def mixed(ident: Column, salt: int) -> Column:
    """A permuted residue below P. Linear hashes would give the two ends of a random edge a constant difference."""
    x = _fifth(((ident + 1) * A1 + salt * B1 + C1) % P)
    return _fifth((x * A2 + salt * B2 + C2) % P)


def with_hash(df: DataFrame, name: str, ident: str, salt: int) -> DataFrame:
    """Adds the hash a step at a time, which keeps the expression small."""
    x = df.withColumn("_x", ((F.col(ident).cast("long") + 1) * A1 + salt * B1 + C1) % P)
    x = x.withColumn("_s", (F.col("_x") * F.col("_x")) % P).withColumn("_x", ((F.col("_s") * F.col("_s")) % P * F.col("_x")) % P)
    x = x.withColumn("_x", (F.col("_x") * A2 + salt * B2 + C2) % P)
    x = x.withColumn("_s", (F.col("_x") * F.col("_x")) % P)
    return x.withColumn(name, ((F.col("_s") * F.col("_s")) % P * F.col("_x")) % P).drop("_x", "_s")


def hash_sql(source: str, ident: str, salt: int, name: str = "h") -> str:
    """A subquery with the same hash as a column."""
    a = f"SELECT *, ((CAST({ident} AS BIGINT) + 1) * {A1} + {salt * B1 + C1}) % {P} AS x0 FROM {source}"
    b = f"SELECT * EXCLUDE (x0), (x0 * x0) % {P} AS s1, x0 AS x1 FROM ({a})"
    c = f"SELECT * EXCLUDE (s1, x1), (((s1 * s1) % {P} * x1) % {P} * {A2} + {salt * B2 + C2}) % {P} AS x2 FROM ({b})"
    d = f"SELECT * EXCLUDE (x2), (x2 * x2) % {P} AS s2, x2 AS x3 FROM ({c})"
    return f"(SELECT * EXCLUDE (s2, x3), ((s2 * s2) % {P} * x3) % {P} AS {name} FROM ({d}))"
