"""Written stages are not sent through the driver because their files are small."""

from pyspark.sql import functions as F

from labelflow.plans.joins import lookup, without
from labelflow.plans.stage import materialise


def plan(df) -> str:
    df.count()
    return df._jdf.queryExecution().toString()


def test_a_large_stage_of_small_files_is_not_broadcast(spark):
    """600,000 ids compress to less than Spark's default bound for a broadcast."""
    right = materialise(spark.range(0, 600_000, 1, 4).withColumn("truth", F.col("id") % 2), "ids")
    left = spark.range(0, 2_000_000, 1, 4).withColumn("w", F.lit(1))
    assert "BroadcastHashJoin" not in plan(left.join(right, "id"))
    assert "BroadcastHashJoin" not in plan(lookup(left, right, ["id"], "left", "w"))
    assert "BroadcastHashJoin" not in plan(without(left, right.select("id"), ["id"]))
    assert lookup(left, right, ["id"], "inner", "w").count() == 600_000


def test_a_small_stage_still_is(spark):
    right = materialise(spark.range(0, 1_000), "few")
    left = spark.range(0, 2_000_000, 1, 4)
    assert "BroadcastHashJoin" in plan(lookup(left, right, ["id"], "inner"))
