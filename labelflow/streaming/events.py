"""Streams of change events: batch formation, late rows, duplicates, joins, and live labels.

The given events table is one file; `staged` deals it into files in event order, so that a stream sees several micro-batches.
Each function returns a bounded result: the stream runs over what is there and its output is read back.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from labelflow.operators.frontier import frontier_update
from labelflow.operators.graph import SimilarityGraph, arcs_of
from labelflow.plans.stage import materialise, new_path, release
from labelflow.sources.store import GraphStore
from labelflow.sources.tables import read

FILES = 6


def staged(spark: SparkSession, sf_dir: str, files: int = FILES, extra: DataFrame | None = None, tardy: str = "false") -> str:
    """Writes the events as files by rising event time, those for which the condition `tardy` holds in the last; returns the folder."""
    path = new_path(spark, "events")
    e = read(spark, sf_dir, "events").withColumn("ts", F.col("ts").cast("timestamp"))
    if extra is not None:
        e = e.unionByName(extra)
    cuts = e.select(F.col("ts").cast("double").alias("t")).approxQuantile("t", [i / files for i in range(1, files)], 0.001)
    late = F.expr(f"coalesce({tardy}, false)")
    for i in range(files):
        part = F.lit(True)
        if i:
            part = part & (F.col("ts").cast("double") > cuts[i - 1])
        if i < files - 1:
            part = part & (F.col("ts").cast("double") <= cuts[i])
        part = e.filter(part & ~late if i < files - 1 else part | late)
        part.coalesce(1).write.mode("append").parquet(path)
    return path


def stream(spark: SparkSession, path: str) -> DataFrame:
    """The staged events as a stream, one file a trigger, with an event time that watermarks accept."""
    schema = spark.read.parquet(path).schema
    return spark.readStream.schema(schema).option("maxFilesPerTrigger", 1).parquet(path)


def finish(df: DataFrame, mode: str = "append") -> DataFrame:
    """Runs a stream over all that is there into files and reads them; update and complete modes keep the last state of each key."""
    spark = df.sparkSession
    out, mark = new_path(spark, "stream-out"), new_path(spark, "stream-log")
    if mode == "append":
        query = df.writeStream.format("parquet").option("path", out).option("checkpointLocation", mark).outputMode("append").trigger(availableNow=True).start()
    else:

        def put(batch: DataFrame, batch_id: int) -> None:
            batch.write.mode("overwrite").parquet(f"{out}/last")

        query = df.writeStream.foreachBatch(put).option("checkpointLocation", mark).outputMode(mode).trigger(availableNow=True).start()
    query.awaitTermination()
    return spark.read.schema(df.schema).parquet(out if mode == "append" else f"{out}/last")


def daily_batches(events: DataFrame) -> DataFrame:
    return events.groupBy(F.window("ts", "1 day").alias("w"), "event_type").agg(F.count("*").alias("n")).select(F.col("w.start").alias("day"), "event_type", "n")


def sliding_rate(events: DataFrame) -> DataFrame:
    return events.groupBy(F.window("ts", "2 days", "1 day").alias("w")).agg(F.count("*").alias("n"), F.countDistinct("user_id").alias("users") if not events.isStreaming else F.approx_count_distinct("user_id").alias("users")).select(F.col("w.start").alias("start"), "n", "users")


def user_sessions(events: DataFrame, gap: str = "30 minutes") -> DataFrame:
    return events.groupBy("user_id", F.session_window("ts", gap).alias("w")).agg(F.count("*").alias("n")).select("user_id", F.col("w.start").alias("start"), F.col("w.end").alias("stop"), "n")


def late_changes(events: DataFrame, allowed: str = "1 day") -> DataFrame:
    """Daily counts that close once the watermark passes; the last day stays open."""
    return events.withWatermark("ts", allowed).groupBy(F.window("ts", "1 day").alias("w")).agg(F.count("*").alias("n")).select(F.col("w.start").alias("day"), "n")


def split_late(events: DataFrame, allowed: str = "1 day", out: str | None = None, mark: str | None = None) -> str:
    """Runs the stream into a folder per micro-batch, each row with `late`: whether its day had closed, that is, ended `allowed` before the
    newest event of the batches before. Late rows take this side path, none is dropped; rows without a time have no day and are late.

    A batch writes its own folder and the newest time up to it, so a replay after a restart with the same `out` and `mark` overwrites itself."""
    spark = events.sparkSession
    out, mark = out or new_path(spark, "late-out"), mark or new_path(spark, "late-log")

    def put(batch: DataFrame, batch_id: int) -> None:
        newest = spark.read.parquet(f"{out}/newest/batch_id={batch_id - 1}").first().ts if batch_id else None  # one row
        closes = F.date_trunc("day", "ts") + F.expr(f"INTERVAL 1 DAY + INTERVAL {allowed}")
        late = F.coalesce(closes <= F.lit(newest), F.col("ts").isNull())
        batch.withColumn("late", late).write.mode("overwrite").parquet(f"{out}/rows/batch_id={batch_id}")
        seen = spark.read.schema("ts timestamp").parquet(f"{out}/rows/batch_id={batch_id}")
        seen.agg(F.greatest(F.max("ts"), F.lit(newest).cast("timestamp")).alias("ts")).write.mode("overwrite").parquet(f"{out}/newest/batch_id={batch_id}")

    events.writeStream.foreachBatch(put).option("checkpointLocation", mark).trigger(availableNow=True).start().awaitTermination()
    return out


def late_corrected(spark: SparkSession, out: str, allowed: str = "1 day") -> DataFrame:
    """(day, n, n_late) of the closed days of `split_late`: rows that came in time, and those that the side path adds."""
    newest = spark.read.parquet(f"{out}/newest").agg(F.max("ts")).first()[0]
    days = spark.read.parquet(f"{out}/rows").groupBy(F.date_trunc("day", "ts").alias("day")).agg(F.count_if(~F.col("late")).alias("n"), F.count_if("late").alias("n_late"))
    return days.filter(F.col("day") + F.expr(f"INTERVAL 1 DAY + INTERVAL {allowed}") <= F.lit(newest))


def deduplicated(events: DataFrame) -> DataFrame:
    if events.isStreaming:
        return events.withWatermark("ts", "40 days").dropDuplicatesWithinWatermark(["event_id"])
    return events.dropDuplicates(["event_id"])


def enriched(events: DataFrame, customers: DataFrame) -> DataFrame:
    """Events with the segment of the user's customer row: stream-static join."""
    return events.join(customers.select(F.col("c_custkey").alias("user_id"), "c_mktsegment"), "user_id").select("event_id", "user_id", "event_type", "c_mktsegment")


def click_purchase(events: DataFrame) -> DataFrame:
    """Purchases within an hour after a click of the same user: interval join of the stream with itself."""
    if events.isStreaming:
        events = events.withWatermark("ts", "2 hours")
    c = events.filter("event_type = 'click'").select(F.col("event_id").alias("click_id"), F.col("user_id").alias("cu"), F.col("ts").alias("ct"))
    p = events.filter("event_type = 'purchase'").select(F.col("event_id").alias("purchase_id"), F.col("user_id").alias("pu"), F.col("ts").alias("pt"))
    return c.join(p, F.expr("cu = pu AND pt >= ct AND pt <= ct + INTERVAL 1 HOUR")).select("click_id", "purchase_id", F.col("cu").alias("user_id"))


def live_labels(events: DataFrame, truth: DataFrame, delta: float = 1e-3, store: GraphStore | None = None, mark: str | None = None) -> DataFrame:
    """Labels of users kept current while events arrive: a user is linked to the (type, day) cells of its events. Each micro-batch is one frontier
    update of the graph and labels that the store held before it.

    The store keeps a batch's new nodes, the new totals of the arcs it touched, and the labels as a version named by the batch. With the same
    `store` and `mark` a restarted stream goes on where it stopped, and a batch that is played again overwrites itself."""
    spark = events.sparkSession
    store = store or GraphStore(spark)

    def cell(df: DataFrame) -> DataFrame:
        key = F.concat_ws("/", "event_type", F.date_trunc("day", "ts").cast("string"))
        return df.groupBy((F.col("user_id") * 2).alias("u"), (F.pmod(F.xxhash64(key), F.lit(1 << 40)) * 2 + 1).alias("v")).agg(F.count("*").alias("w"))

    def step(batch: DataFrame, batch_id: int) -> None:
        edges = materialise(cell(batch), "stream-edges")
        nodes, arcs = materialise(store.nodes(batch_id), "stream-nodes"), materialise(store.arcs(batch_id), "stream-arcs")
        ids = edges.select(F.explode(F.array("u", "v")).alias("node_id")).distinct().join(nodes.select("node_id"), "node_id", "left_anti")
        ins = materialise(ids.join(truth.select((F.col("user_id") * 2).alias("node_id"), F.col("truth").cast("int").alias("truth")), "node_id", "left"), "stream-ins")
        up = frontier_update(SimilarityGraph(nodes, arcs), store.state(batch_id - 1) if batch_id else None, ins, edges, tau=0.0, delta=delta)
        totals = arcs_of(edges).join(arcs.withColumnRenamed("w", "had"), ["src", "dst"], "left").select("src", "dst", (F.col("w") + F.coalesce("had", F.lit(0))).alias("w"))
        store.append(batch_id, ins, totals)
        store.commit(batch_id, up.run.state.select("node_id", "f"))
        release(edges, nodes, arcs, ins)

    mark = mark or new_path(spark, "stream-log")
    events.writeStream.foreachBatch(step).option("checkpointLocation", mark).trigger(availableNow=True).start().awaitTermination()
    return store.state()
