"""A graph that grows: arcs in append-only batch folders, deletions as tombstones, states as versions behind a manifest."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from labelflow.plans.joins import without
from labelflow.plans.stage import materialise, new_path, remove_path


class GraphStore:
    """Folders nodes/, arcs/, tombstones/ by batch_id, and state/ by version. A batch that is written again replaces itself, so a replay changes
    nothing; readers follow the manifest's version, which is written last."""

    def __init__(self, spark: SparkSession, path: str | None = None):
        self.spark = spark
        self.path = path or new_path(spark, "graph")

    def _put(self, df: DataFrame, kind: str, batch_id: int) -> None:
        df.write.mode("overwrite").parquet(f"{self.path}/{kind}/batch_id={batch_id}")

    def _get(self, kind: str, schema: str, before: int | None = None) -> DataFrame:
        jvm = self.spark.sparkContext._jvm
        where = jvm.org.apache.hadoop.fs.Path(f"{self.path}/{kind}")
        if not where.getFileSystem(self.spark.sparkContext._jsc.hadoopConfiguration()).exists(where):
            return self.spark.createDataFrame([], f"{schema}, batch_id int")
        held = self.spark.read.schema(f"{schema}, batch_id int").parquet(f"{self.path}/{kind}")
        return held if before is None else held.filter(F.col("batch_id") < before)  # folders, so the scan is pruned

    def append(self, batch_id: int, nodes: DataFrame | None = None, arcs: DataFrame | None = None, dels: DataFrame | None = None) -> None:
        if nodes is not None:
            self._put(nodes.select("node_id", F.col("truth").cast("int").alias("truth")), "nodes", batch_id)
        if arcs is not None:
            self._put(arcs.select("src", "dst", "w").repartition("src").sortWithinPartitions("src"), "arcs", batch_id)
        if dels is not None:
            self._put(dels.select("node_id").distinct(), "tombstones", batch_id)

    def _dead(self, before: int | None = None) -> DataFrame:
        return self._get("tombstones", "node_id long", before).groupBy("node_id").agg(F.max("batch_id").alias("dead"))

    def nodes(self, before: int | None = None) -> DataFrame:
        """Live nodes: inserted after, or in the batch of, their last deletion; `before` leaves out that batch and later ones."""
        born = self._get("nodes", "node_id long, truth int", before).groupBy("node_id").agg(F.max_by("truth", "batch_id").alias("truth"), F.max("batch_id").alias("born"))
        return born.join(self._dead(before), "node_id", "left").filter("dead is null or born >= dead").select("node_id", "truth")

    def arcs(self, before: int | None = None) -> DataFrame:
        """Arcs between live nodes that were written after the ends' last deletion, of the weight written last."""
        dead = materialise(self._dead(before), "dead")
        a = self._get("arcs", "src long, dst long, w long", before)
        for end in ("src", "dst"):
            a = a.join(F.broadcast(dead.withColumnRenamed("node_id", end)) if dead.count() < 500_000 else dead.withColumnRenamed("node_id", end), end, "left").filter("dead is null or batch_id >= dead").drop("dead")
        return a.groupBy("src", "dst").agg(F.max_by("w", "batch_id").alias("w"))

    def compact(self, batch_id: int) -> None:
        """Rewrites what is live as one batch and drops the older folders."""
        nodes, arcs = materialise(self.nodes(), "live-nodes"), materialise(self.arcs(), "live-arcs")
        for kind in ("nodes", "arcs", "tombstones"):
            remove_path(self.spark, f"{self.path}/{kind}")
        self.append(batch_id, nodes, arcs)

    def commit(self, version: int, state: DataFrame) -> None:
        """Writes a state version, then points the manifest at it; a version that is committed again overwrites itself."""
        state.write.mode("overwrite").parquet(f"{self.path}/state/version={version}")
        self.spark.createDataFrame([(version,)], "version int").coalesce(1).write.mode("overwrite").parquet(f"{self.path}/manifest")

    def version(self) -> int:
        return self.spark.read.parquet(f"{self.path}/manifest").first().version

    def state(self, version: int | None = None) -> DataFrame:
        return self.spark.read.parquet(f"{self.path}/state/version={self.version() if version is None else version}")

    def unreached(self, ids: DataFrame) -> DataFrame:
        """Live nodes outside a set of ids."""
        return without(self.nodes(), ids, ["node_id"])

    def save_bucketed(self, df: DataFrame, table: str, key: str = "src", buckets: int = 8) -> DataFrame:
        """A table clustered and sorted by key, so that joins of equally bucketed tables need no exchange."""
        df.write.bucketBy(buckets, key).sortBy(key).mode("overwrite").saveAsTable(table)
        return self.spark.table(table)
