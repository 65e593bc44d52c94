"""Random graphs with a given mean degree, as a plan and as a Python data source."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition

from labelflow.functions.hashing import A1, A2, B1, B2, C1, C2, P, with_hash


def er_edges(spark: SparkSession, n: int, degree: int, salt: int = 0) -> DataFrame:
    """Edges (u, v, w) of n * degree / 2 draws: both ends and the weight (1 to 1000) from the mixed hash, loops dropped, parallel ones
    merged by the largest weight. One range scan and one aggregation at any size."""
    e = spark.range(0, n * degree // 2)
    for name, s in (("a", 1), ("b", 2), ("c", 5)):
        e = with_hash(e, name, "id", s + 10 * salt)
    e = e.select((F.col("a") % n).alias("a"), (F.col("b") % n).alias("b"), (1 + F.col("c") % 1000).alias("w")).filter("a != b")
    return e.select(F.least("a", "b").alias("u"), F.greatest("a", "b").alias("v"), "w").groupBy("u", "v").agg(F.max("w").alias("w"))


def _mixed(i: int, salt: int) -> int:
    x = pow(((i + 1) * A1 + salt * B1 + C1) % P, 5, P)
    return pow((x * A2 + salt * B2 + C2) % P, 5, P)


class _Reader(DataSourceReader):
    def __init__(self, n: int, degree: int, parts: int):
        self.n, self.draws, self.parts = n, n * degree // 2, parts

    def partitions(self):
        step = max(1, -(-self.draws // self.parts))
        return [InputPartition((a, min(a + step, self.draws))) for a in range(0, self.draws, step)]

    def read(self, partition):
        a, b = partition.value
        for i in range(a, b):
            u, v = _mixed(i, 1) % self.n, _mixed(i, 2) % self.n
            if u != v:
                yield min(u, v), max(u, v), 1 + _mixed(i, 5) % 1000


class RandomGraphSource(DataSource):
    """spark.read.format("er_graph").option("nodes", n).option("degree", d): draws (u, v, w), parallel edges not yet merged."""

    @classmethod
    def name(cls) -> str:
        return "er_graph"

    def schema(self) -> str:
        return "u long, v long, w long"

    def reader(self, schema):
        return _Reader(int(self.options.get("nodes", 1000)), int(self.options.get("degree", 5)), int(self.options.get("partitions", 8)))


def register(spark: SparkSession) -> None:
    spark.dataSource.register(RandomGraphSource)
