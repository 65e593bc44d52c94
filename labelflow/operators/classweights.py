"""Class contraction: the ground truth enters as two weights per node, never as vertices."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from labelflow.functions.fixed import HALF, SCALE, class_share
from labelflow.operators.components import connected_components
from labelflow.plans.joins import lookup
from labelflow.plans.stage import materialise


def contraction(arcs: DataFrame, truth: DataFrame) -> DataFrame:
    """(node_id, w0, w1, w_all): sums of parallel edges to class 0, class 1 and all neighbours; one aggregation, pre-summed per
    task, so a hub costs a row per task."""
    known = truth.filter("truth is not null").select(F.col("node_id").alias("dst"), F.col("truth").cast("int").alias("truth"))
    return class_sums(lookup(arcs, materialise(known, "truth"), ["dst"], "left", "src"))


def class_sums(seen: DataFrame, *more: Column) -> DataFrame:
    """The same of arcs (src, w, truth) that know the truth of their far end, with more sums where asked."""
    pick = lambda t: F.sum(F.when(F.col("truth") == t, F.col("w")).otherwise(0))
    return seen.groupBy(F.col("src").alias("node_id")).agg(pick(0).alias("w0"), pick(1).alias("w1"), F.sum("w").alias("w_all"), *more)


def update_contraction(weights: DataFrame, added: DataFrame, removed: DataFrame, truth: DataFrame) -> DataFrame:
    """The same table after arcs came and went: signed sums of the batch's arcs only, joined to what was."""
    plus = contraction(added, truth)
    minus = contraction(removed, truth).select("node_id", *[(-F.col(c)).alias(c) for c in ("w0", "w1", "w_all")])
    all_rows = weights.select("node_id", "w0", "w1", "w_all").unionByName(plus).unionByName(minus)
    return all_rows.groupBy("node_id").agg(*[F.sum(c).alias(c) for c in ("w0", "w1", "w_all")])


def component_weights(components: DataFrame, weights: DataFrame, truth: DataFrame) -> DataFrame:
    """(comp_id, w0, w1, size): class weights of the components' unlabelled members."""
    free = components.join(weights.select("node_id", "w0", "w1"), "node_id", "left").join(truth.filter("truth is not null").select("node_id", F.lit(1).alias("pinned")), "node_id", "left")
    pick = lambda c: F.sum(F.when(F.col("pinned").isNull(), F.coalesce(c, F.lit(0))).otherwise(0)).alias(c)
    return free.groupBy("comp_id").agg(pick("w0"), pick("w1"), F.count("*").alias("size"))


def component_label() -> Column:
    """Initial label of a component: half, moved down by the class-0 share and up by the class-1 share, which is the class-1 share."""
    return class_share(F.col("w0"), F.col("w1"))


def initial_labels(new_ids: DataFrame, sub_edges: DataFrame, weights: DataFrame, truth: DataFrame, init: str = "component", method: str = "auto") -> DataFrame:
    """(node_id, f0, comp_id) of new nodes: 'component' by supernode, 'vertex' each on its own, 'half' neutral. Truth wins."""
    if init == "component":
        comps = connected_components(sub_edges.select("u", "v"), new_ids, method)
    elif init in ("vertex", "half"):
        comps = new_ids.select("node_id", F.col("node_id").alias("comp_id"))
    else:
        raise ValueError(f"unknown initialisation {init}")
    comps = materialise(comps, "comps")
    if init == "half":
        labels = comps.withColumn("f0", F.lit(HALF).cast("long"))
    else:
        sums = materialise(component_weights(comps, weights, truth).select("comp_id", component_label().alias("f0")), "comp-labels")
        labels = lookup(comps, sums, ["comp_id"], "inner", "node_id")
    pins = truth.filter("truth is not null").select("node_id", (F.col("truth") * SCALE).cast("long").alias("pin"))
    return labels.join(pins, "node_id", "left").select("node_id", F.coalesce("pin", "f0").alias("f0"), "comp_id")
