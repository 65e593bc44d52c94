"""Corpus pipeline: toxicity filter, near-duplicate removal, decontamination, mixing, sharding.

Each stage takes (spark, docs, sf_dir) and returns a DataFrame that is written as Parquet and read again as the next one's docs.
All but the last return the columns of documents. A doc_id names one document: a stage that drops an id drops all rows of
that id, and near-duplicate removal leaves one row of an id that repeats. Rows of a null id cannot be named: toxicity judges
each by its text; the stages that drop by id keep them.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from labelflow.llm import decontaminate, mixing, near_copies, sharding, toxicity
from labelflow.llm.common import materialise, table
from labelflow.plans.joins import without

#: No SQL: the toxicity model and the fingerprints are beyond it. tests/llm holds the stages against brute force.
ORACLE_SQL = None
COLUMNS = ["doc_id", "text", "lang", "source", "n_chars"]
TOXIC_FROM = 0.3
SHARDS = 24


def drop_toxic(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Drops documents whose toxicity score reaches the threshold; the model learns from the labels' training rows."""
    docs = docs.select(*COLUMNS)
    model = toxicity.train(docs, table(spark, sf_dir, "labels"))
    return toxicity.score(docs, model).filter(F.col("_score") < TOXIC_FROM).select(*COLUMNS)


def drop_near_duplicates(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Keeps the smallest doc_id of each group of documents that steps of five-word shingle similarity 0.8 or more join, and one row of it."""
    docs = docs.select(*COLUMNS)
    kept = without(docs, materialise(near_copies.near_copies(docs, 5).select("doc_id").distinct(), "pipeline-copies"), ["doc_id"])
    repeated = materialise(docs.filter("doc_id is not null").groupBy("doc_id").agg(F.count("*").alias("n")).filter("n > 1").select("doc_id"), "pipeline-repeats")
    if repeated.isEmpty():
        return kept
    again = kept.join(repeated, "doc_id", "left_semi").dropDuplicates(["doc_id"]).select(*COLUMNS)
    return without(kept, repeated, ["doc_id"]).unionByName(again)


def drop_contaminated(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Drops documents that hold any window of ten words of a benchmark item."""
    docs = docs.select(*COLUMNS)
    found = decontaminate.decontaminate(docs, table(spark, sf_dir, "benchmark"))
    return without(docs, materialise(found.filter("contaminated").select("doc_id").distinct(), "pipeline-leaks"), ["doc_id"])


def mix_sources(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Replicates documents so that a source's share goes with its rows to the power 0.7; as many rows are expected as came in."""
    return mixing.mix(docs.select(*COLUMNS)).select(*COLUMNS)


def shard(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Adds the shard of each row, 0 to 23, of near equal bytes."""
    return sharding.assign_shards(docs.select(*COLUMNS), SHARDS).withColumnRenamed("_shard", "shard")


STAGES = [
    ("toxicity", drop_toxic),
    ("near_duplicates", drop_near_duplicates),
    ("decontamination", drop_contaminated),
    ("mixing", mix_sources),
    ("sharding", shard),
]


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All stages over the whole documents table."""
    docs = table(spark, sf_dir, "documents")
    for name, stage in STAGES:
        docs = materialise(stage(spark, docs, sf_dir), f"pipeline-{name}")
    return docs
