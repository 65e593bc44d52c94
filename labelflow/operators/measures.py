"""Cost and accuracy measures."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from labelflow.functions.fixed import HALF, SCALE
from labelflow.operators.graph import SimilarityGraph
from labelflow.operators.propagate import all_labels, relax
from labelflow.plans.joins import lookup
from labelflow.plans.stage import materialise


def accuracy_vs(state: DataFrame, reference: DataFrame, reached: DataFrame | None = None, cutoff: int = HALF) -> DataFrame:
    """One row: predicted nodes, those whose class equals the reference's, their share, and the larger class's share of the reference.

    state (node_id, f) and reference (node_id, ref) in label units; only reached nodes count where given."""
    rows = state.join(reference, "node_id")
    if reached is not None:
        rows = rows.join(reached.filter("reached").select("node_id"), "node_id", "left_semi")
    same = ((F.col("f") >= cutoff) == (F.col("ref") >= cutoff)).cast("long")
    ones = F.sum((F.col("ref") >= cutoff).cast("long"))
    return rows.agg(F.count("*").alias("predicted"), F.coalesce(F.sum(same), F.lit(0)).alias("equal"), F.coalesce(ones, F.lit(0)).alias("ones")).select(
        "predicted", "equal", F.round(F.try_divide("equal", "predicted"), 6).alias("accuracy"), F.round(F.try_divide(F.greatest("ones", F.col("predicted") - F.col("ones")), F.col("predicted")), 6).alias("majority")
    )


def accuracy_truth(state: DataFrame, held_out: DataFrame) -> DataFrame:
    """The same against true classes (node_id, truth) that the run did not see."""
    return accuracy_vs(state, held_out.select("node_id", (F.col("truth") * SCALE).cast("long").alias("ref")))


def label_error(state: DataFrame, reference: DataFrame) -> DataFrame:
    e = F.abs(F.col("f") - F.col("ref"))
    return state.join(reference, "node_id").agg(F.max(e).alias("max_error"), F.sum(e).alias("sum_error"), F.count("*").alias("n"))


def energy(g: SimilarityGraph, state: DataFrame) -> DataFrame:
    """One row: half the weighted squared label differences over undirected edges, each once."""
    labels = materialise(all_labels(g, state).select("node_id", "f"), "labels")
    e = g.arcs.filter("src < dst")
    e = lookup(e, labels.select(F.col("node_id").alias("src"), F.col("f").alias("a")), ["src"], "inner", "dst")
    e = lookup(e, labels.select(F.col("node_id").alias("dst"), F.col("f").alias("b")), ["dst"], "inner", "src")
    d = (F.col("a") - F.col("b")).cast("decimal(20,0)")
    return e.agg((F.coalesce(F.sum((d * d).cast("decimal(30,0)") * F.col("w").cast("decimal(8,0)")), F.lit(0)).cast("double") / (2.0 * SCALE * SCALE)).alias("energy")).select(F.round("energy", 4).alias("energy"))


def residual(state: DataFrame, arcs: DataFrame) -> DataFrame:
    """One row: the largest distance of a label from its neighbours' average, and the nodes it was taken over."""
    r = relax(state, arcs)
    return r.filter("new is not null").agg(F.coalesce(F.max(F.abs(F.col("new") - F.col("f"))), F.lit(0)).alias("max_residual"), F.count("*").alias("n"))


def confusion(state: DataFrame, reference: DataFrame, cutoff: int = HALF) -> DataFrame:
    """actual class by predicted class, pivoted."""
    rows = state.join(reference, "node_id").select((F.col("ref") >= cutoff).cast("int").alias("actual"), (F.col("f") >= cutoff).cast("int").alias("predicted"))
    return rows.groupBy("actual").pivot("predicted", [0, 1]).count().select("actual", F.coalesce(F.col("0"), F.lit(0)).alias("predicted_0"), F.coalesce(F.col("1"), F.lit(0)).alias("predicted_1"))


def precision_recall(table: DataFrame) -> DataFrame:
    """Precision, recall and F1 of class 1 from a confusion table."""
    t = table.agg(*[F.coalesce(F.sum(F.when(F.col("actual") == a, F.col(f"predicted_{p}"))), F.lit(0)).alias(f"n{a}{p}") for a in (0, 1) for p in (0, 1)])
    p, r = F.try_divide("n11", F.col("n11") + F.col("n01")), F.try_divide("n11", F.col("n11") + F.col("n10"))
    return t.select(F.round(p, 6).alias("precision"), F.round(r, 6).alias("recall"), F.round(F.try_divide(2 * p * r, p + r), 6).alias("f1"))


def speedup(metrics: DataFrame, self_method: str = "frontier") -> DataFrame:
    """Other methods' time over ours, by what else the metrics are keyed by (batch)."""
    own = metrics.filter(F.col("method") == self_method).select("batch", F.col("seconds").alias("own"))
    return metrics.filter(F.col("method") != self_method).join(own, "batch").select("batch", "method", F.round(F.col("seconds") / F.col("own"), 6).alias("speedup"))


#: Methods that keep a matrix of all pairs of nodes.
DENSE = ("harmonic_exact", "harmonic_contracted", "recompute")


def state_bytes(method: str, n: int, m: int) -> int:
    """Bytes a method keeps: dense ones a matrix, sparse ones rows and arcs."""
    return 8 * n * n if method in DENSE else 8 * n * 512 if method == "gcn" else 40 * n + 24 * 2 * m


def graph_sizes(nodes: DataFrame, edges: DataFrame) -> DataFrame:
    """One row (nodes, edges): how many there are."""
    return nodes.agg(F.count("*").alias("nodes")).crossJoin(F.broadcast(edges.agg(F.count("*").alias("edges"))))  # one row


def capacity_table(nodes: DataFrame, edges: DataFrame, budget: int = 80_000_000_000) -> DataFrame:
    """Nodes of a graph of this one's mean degree that fit a memory budget: sqrt(budget / 8) for dense methods, budget / (40 + 48 edges a node)
    for sparse ones; and how many this one has."""
    rows = [("full_sweep", False), ("frontier", False), ("harmonic_exact", True), ("harmonic_contracted", True)]
    df = nodes.sparkSession.createDataFrame(rows, "method string, dense boolean").withColumn("budget", F.lit(budget))
    df = df.crossJoin(F.broadcast(graph_sizes(nodes, edges)))  # one row
    each = F.lit(40) + F.lit(48) * F.col("edges").cast("double") / F.col("nodes")
    return df.select("method", F.when(F.col("dense"), F.floor(F.sqrt(F.col("budget") / 8))).otherwise(F.floor(F.col("budget") / each)).cast("long").alias("max_nodes"), "nodes")


#: What each method can do, as reported: incremental, decremental, parallel, updates labels, target graph, memory device. Fixed values.
METHODS = [
    ("full_sweep", True, False, False, False, "dense", "compression"),
    ("gcn", True, False, True, False, "dense", "compression"),
    ("neural_knn", True, False, True, False, "sparse", "knn"),
    ("harmonic_contracted", True, True, True, False, "dense", "none"),
    ("harmonic_sparse_inverse", True, True, True, False, "dense", "sparse_inverse"),
    ("frontier", True, True, True, True, "sparse", "csr"),
]


def method_matrix(nodes: DataFrame, edges: DataFrame) -> DataFrame:
    """The methods' properties beside the size of a graph, and the bytes that each keeps for it."""
    df = nodes.sparkSession.createDataFrame(METHODS, "method string, incremental boolean, decremental boolean, parallel boolean, label_update boolean, target_graph string, memory string")
    n, m = F.col("nodes"), F.col("edges")
    kept = F.when(F.col("method").isin(*DENSE), 8 * n * n).when(F.col("method") == "gcn", 8 * n * 512).otherwise(40 * n + 48 * m)
    return df.crossJoin(F.broadcast(graph_sizes(nodes, edges))).withColumn("bytes", kept.cast("long"))  # one row


def capacity_probe(run, sizes: list[int], seconds: float) -> list[tuple[int, bool, float]]:
    """(size, ran, seconds) for rising sizes until a run refuses or takes longer than the budget."""
    import time

    from labelflow.operators.harmonic import CapacityError

    out = []
    for n in sizes:
        begun = time.monotonic()
        try:
            run(n)
        except CapacityError:
            out.append((n, False, time.monotonic() - begun))
            break
        took = time.monotonic() - begun
        out.append((n, took <= seconds, took))
        if took > seconds:
            break
    return out


def batch_slope(metrics: DataFrame) -> DataFrame:
    """Seconds per further batch, and how well a line fits: near-linear scaling in the number of batches."""
    return metrics.agg(F.round(F.regr_slope("seconds", "batches"), 6).alias("slope"), F.round(F.regr_r2("seconds", "batches"), 6).alias("r2"))
