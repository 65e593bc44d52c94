"""Learning baselines: a two-layer graph convolution and a neural k-nearest-neighbour learner."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from labelflow.functions.fixed import HALF, SCALE
from labelflow.operators.graph import SimilarityGraph
from labelflow.operators.harmonic import CapacityError
from labelflow.operators.propagate import free_state, full_sweep
from labelflow.plans.stage import materialise

#: Nodes whose reduced features one task may hold for training: 200,000 x 512 doubles are 800 MB.
GCN_NODES = 200_000
#: Whole steps of a pseudo label's certainty.
CERTAINTY = 4


def normalised_adjacency(arcs: DataFrame, nodes: DataFrame) -> DataFrame:
    """(src, dst, s): w / sqrt(d_src d_dst) with self loops of the mean weight."""
    loops = nodes.select(F.col("node_id").alias("src"), F.col("node_id").alias("dst")).crossJoin(F.broadcast(arcs.agg(F.coalesce(F.avg("w"), F.lit(1.0)).alias("w"))))  # one row
    a = arcs.select("src", "dst", F.col("w").cast("double").alias("w")).unionByName(loops)
    deg = materialise(a.groupBy("src").agg(F.sum("w").alias("d")), "deg")
    a = a.join(deg.withColumnRenamed("d", "ds"), "src").join(deg.select(F.col("src").alias("dst"), F.col("d").alias("dd")), "dst")
    return a.select("src", "dst", (F.col("w") / F.sqrt(F.col("ds") * F.col("dd"))).alias("s"))


def _train(ids, x, truth, s, d, val, svd_dim, hidden, out, epochs, rate, seed):
    rng = np.random.default_rng(seed)
    n = len(ids)
    order = np.argsort(s, kind="stable")
    s, d, val = s[order], d[order], val[order]
    at = np.searchsorted(s, np.arange(n))
    full = np.searchsorted(s, np.arange(n), side="right") > at

    def mul(m):
        got = np.zeros_like(m)
        if len(s):
            got[full] = np.add.reduceat(val[:, None] * m[d], at[full], axis=0)
        return got

    if x.shape[1] > svd_dim:
        _, _, vt = np.linalg.svd(x - x.mean(0), full_matrices=False)
        x = x @ vt[:svd_dim].T
    sx = mul(x)  # once: the features do not change
    w0 = rng.standard_normal((x.shape[1], hidden)) * np.sqrt(2 / max(1, x.shape[1]))
    w1 = rng.standard_normal((hidden, out)) * np.sqrt(2 / hidden)
    known = np.flatnonzero(truth >= 0)
    gold = np.eye(out)[truth[known]]
    moments = [[np.zeros_like(w), np.zeros_like(w)] for w in (w0, w1)]
    p = np.full((n, out), 1 / out)
    for t in range(1, epochs + 1):
        h = np.maximum(sx @ w0, 0)
        z = mul(h @ w1)  # out columns travel, not hidden ones
        e = np.exp(z - z.max(1, keepdims=True))
        p = e / e.sum(1, keepdims=True)
        if not len(known):
            break
        g = np.zeros_like(p)
        g[known] = (p[known] - gold) / len(known)
        back = mul(g)  # the matrix is symmetric
        grads = (sx.T @ ((back @ w1.T) * (h > 0)), h.T @ back)
        for k, (w, gr) in enumerate(zip((w0, w1), grads, strict=True)):
            m, v = moments[k]
            m += 0.1 * (gr - m)
            v += 0.001 * (gr * gr - v)
            w -= rate * (m / (1 - 0.9**t)) / (np.sqrt(v / (1 - 0.999**t)) + 1e-8)
    return p[:, 1]


def gcn_two_layer(g: SimilarityGraph, features: DataFrame, svd_dim: int = 512, hidden: int = 256, out: int = 2, epochs: int = 200, rate: float = 0.01, seed: int = 1) -> DataFrame:
    """(node_id, label) of unlabelled nodes: the probability of class 1.

    features (node_id, x array<double>). The normalised adjacency is a plan; training is full-batch on one task, and refuses graphs whose reduced
    features it can't hold, as dense accelerators do."""
    n = g.nodes.count()
    if n > GCN_NODES:
        raise CapacityError(f"{n} nodes; the graph convolution trains on one task of at most {GCN_NODES}")
    nodes = g.nodes.select("node_id", F.coalesce(F.col("truth").cast("int"), F.lit(-1)).alias("truth")).join(features.select("node_id", "x"), "node_id")
    links = materialise(normalised_adjacency(g.arcs, nodes), "adjacency")

    def run(left: pa.Table, right: pa.Table) -> pa.Table:
        left = left.sort_by("node_id")
        ids, truth = left["node_id"].to_numpy(), left["truth"].to_numpy()
        if not len(ids):
            return pa.table({"node_id": pa.array([], pa.int64()), "label": pa.array([], pa.float64())})
        x = np.stack(left["x"].to_numpy(zero_copy_only=False)).astype(float)
        src, dst, val = (right[c].to_numpy() for c in ("src", "dst", "s"))
        ok = np.isin(src, ids) & np.isin(dst, ids)
        p = _train(ids, x, truth, np.searchsorted(ids, src[ok]), np.searchsorted(ids, dst[ok]), val[ok], svd_dim, hidden, out, epochs, rate, seed)
        free = truth < 0
        return pa.table({"node_id": ids[free], "label": p[free]})

    return nodes.withColumn("k", F.lit(0)).groupBy("k").cogroup(links.withColumn("k", F.lit(0)).groupBy("k")).applyInArrow(run, "node_id long, label double")


def certain(known: DataFrame, labels: DataFrame) -> DataFrame:
    """(node_id, label): known labels CERTAINTY times, pseudo labels as many times as they are certain."""
    steps = F.round(F.abs(F.col("f") - HALF) * (CERTAINTY / HALF)).cast("int")
    pseudo = labels.select("node_id", (F.col("f") >= HALF).cast("double").alias("label"), steps.alias("times"))
    return known.withColumn("times", F.lit(CERTAINTY)).unionByName(pseudo).select("node_id", "label", F.explode(F.array_repeat(F.lit(0), F.col("times")))).select("node_id", "label")


def neural_knn(g: SimilarityGraph, features: DataFrame, delta: float = 1e-3, hidden: int = 32, rounds: int = 2, max_iter: int = 40, seed: int = 1) -> DataFrame:
    """(node_id, label): a sweep over the kNN graph gives pseudo labels; a small network learns them from the features; its probabilities
    start the next sweep. The loss is weighted by certainty, the distance of a pseudo label from the cutoff, in CERTAINTY whole steps: the
    network takes no weights, so a row stands once for each step; a known label stands CERTAINTY times, one at the cutoff not at all."""
    from pyspark.ml.classification import MultilayerPerceptronClassifier
    from pyspark.ml.functions import array_to_vector, vector_to_array

    state, arcs = free_state(g)
    x = materialise(features.select("node_id", array_to_vector("x").alias("features"), F.size("x").alias("dim")), "features")
    dim = x.first().dim
    known = g.nodes.filter("truth is not null").select("node_id", F.col("truth").cast("double").alias("label"))
    labels = full_sweep(state, arcs, delta).state
    for _ in range(rounds):
        rows = materialise(certain(known, labels).join(x, "node_id"), "train")
        if rows.select("label").distinct().count() < 2:
            break
        net = MultilayerPerceptronClassifier(layers=[dim, hidden, 2], maxIter=max_iter, seed=seed).fit(rows.select("label", "features"))
        scored = net.transform(x).select("node_id", F.round(vector_to_array("probability")[1] * SCALE).cast("long").alias("p"))
        start = materialise(state.join(scored, "node_id", "left").select("node_id", F.coalesce("p", "f").alias("f"), "w0", "w1", "w_all"), "start")
        labels = full_sweep(start, arcs, delta).state
    return labels.select("node_id", (F.col("f") / SCALE).alias("label"))


def majority(nodes: DataFrame) -> DataFrame:
    """One row: the larger class of the known nodes, and its share."""
    n1, n = F.sum("truth"), F.count("truth")
    return nodes.filter("truth is not null").agg(n1.alias("n1"), n.alias("n")).select(F.when(F.col("n1") * 2 >= F.col("n"), 1).otherwise(0).alias("class"), F.round(F.try_divide(F.greatest("n1", F.col("n") - F.col("n1")), "n"), 6).alias("share"))
