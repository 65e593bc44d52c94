"""The frontier update: a batch of insertions and deletions is applied, new nodes get component labels, and only nodes that the
change can reach are re-averaged."""

from __future__ import annotations

import time
from dataclasses import dataclass, replace

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from labelflow.functions.fixed import HALF, units
from labelflow.operators.classweights import initial_labels
from labelflow.operators.components import connected_components
from labelflow.operators.graph import SimilarityGraph, apply_deletes, apply_inserts, new_subgraph, tau_mean
from labelflow.operators.propagate import TAIL_ARCS, Run, frontier_loop, split, start_state
from labelflow.operators.similarity import insert_knn
from labelflow.plans.joins import lookup, without
from labelflow.plans.local_update import ARC, NODE, SCHEMA, STATE, STEP, TAU, run_update
from labelflow.plans.stage import materialise


@dataclass
class Update:
    graph: SimilarityGraph
    run: Run
    tau: float
    affected: DataFrame
    setup_seconds: float


def initial_frontier(affected: DataFrame, nodes: DataFrame) -> DataFrame:
    """Affected nodes that are alive and unlabelled."""
    return lookup(affected.select("node_id").distinct(), materialise(nodes.filter("truth is null").select("node_id"), "alive"), ["node_id"], "inner", "node_id", salts=1)


def frontier_update(g: SimilarityGraph, labels: DataFrame | None, ins: DataFrame | None = None, ins_edges: DataFrame | None = None, dels: DataFrame | None = None, tau: float | str = "mean", delta: float = 1e-4, init: str = "component", plan: str = "auto", commit_small: bool = False, schedule: str = "sync", max_steps: int = 100_000, tau_gates_graph: bool = False) -> Update:
    """Applies a batch and returns the new graph and labels.

    `labels` (node_id, f) are those before the batch; `ins` (node_id, truth), `ins_edges` (u, v, w) and `dels` (node_id) the batch. Deletes go
    first. `tau` is a number or 'mean', the mean edge weight; it only gates the subgraph of new nodes, unless tau_gates_graph."""
    begun = time.monotonic()
    if plan in ("auto", "tail") and g.arcs.count() + (2 * ins_edges.count() if ins_edges is not None else 0) <= TAIL_ARCS:
        return _one_task_update(g, labels, ins, ins_edges, dels, tau, delta, init, commit_small, schedule, max_steps, tau_gates_graph, begun)
    affected = None
    if dels is not None:
        g, affected = apply_deletes(g, dels)
    new_ids = None
    if ins is not None:
        if tau == "mean":
            tau = tau_mean(ins_edges.select("w").unionByName(g.arcs.filter("src < dst").select("w")))
        edges = ins_edges.filter(F.col("w") > tau) if tau_gates_graph else ins_edges
        g, more = apply_inserts(g, ins, edges)
        affected = more if affected is None else affected.unionByName(more)
        new_ids = ins.select("node_id").distinct()
    g = SimilarityGraph(materialise(g.nodes, "nodes"), materialise(g.arcs, "arcs"))
    parts = split(g, plan == "auto")
    g = replace(g, split=parts)
    f0 = labels.select("node_id", F.col("f").alias("f0")) if labels is not None else None
    if new_ids is not None:
        new_ids = materialise(new_ids, "new")
        sub = materialise(new_subgraph(g.arcs, new_ids, float(tau)), "sub")
        start = initial_labels(new_ids, sub, parts.weights, g.nodes, init).select("node_id", "f0")
        f0 = start if f0 is None else without(f0, new_ids, ["node_id"]).unionByName(start)
    state = start_state(parts, f0, HALF)
    hot = initial_frontier(affected, g.nodes) if affected is not None else state.select("node_id").limit(0)
    hot = materialise(hot, "frontier")
    setup = time.monotonic() - begun
    run = frontier_loop(state, parts.arcs, hot, delta, plan, max_steps, commit_small, schedule, packed=parts.packed)
    return Update(g, run, float(tau) if tau != "mean" else 0.0, hot, setup)


def vector_update(g: SimilarityGraph, labels: DataFrame | None, old: DataFrame, new: DataFrame, truth: DataFrame, k: int = 5, search: str = "exact", **options) -> Update:
    """An insertion of raw points: `new` vectors (node_id, q) find their k nearest among `old` and each other, and the edges found are the batch.
    `truth` (node_id, truth) names the known ones among the new; `search` and its bounds are those of insert_knn, `options` those of frontier_update."""
    edges = materialise(insert_knn(old, new, k, search), "insert-edges")
    ins = new.select("node_id").distinct().join(truth.select("node_id", F.col("truth").cast("int").alias("truth")), "node_id", "left")
    return frontier_update(g, labels, ins, edges, **options)


def _one_task_update(g, labels, ins, ins_edges, dels, tau, delta, init, commit_small, schedule, max_steps, gates, begun) -> Update:
    """The whole batch in one task; sizes have been checked."""
    blank = F.lit(None).cast("long")
    live = g.nodes.select("node_id", F.col("truth").cast("long").alias("truth"))
    live = live.join(labels.select("node_id", "f"), "node_id", "left") if labels is not None else live.withColumn("f", blank)
    left = live.withColumn("kind", F.lit(0))
    right = g.arcs.select("src", "dst", F.col("w").cast("long").alias("w"), F.lit(0).alias("kind"))
    if ins is not None:
        left = left.unionByName(ins.select("node_id", F.col("truth").cast("long").alias("truth"), blank.alias("f"), F.lit(1).alias("kind")))
        right = right.unionByName(ins_edges.select(F.col("u").alias("src"), F.col("v").alias("dst"), F.col("w").cast("long").alias("w"), F.lit(1).alias("kind")))
    if dels is not None:
        left = left.unionByName(dels.select("node_id", blank.alias("truth"), blank.alias("f"), F.lit(2).alias("kind")))
    fixed, limit = None if tau == "mean" else float(tau), units(delta)

    def kernel(a, b):
        return run_update(a, b, fixed, gates, limit, init, max_steps, commit_small, schedule)

    out = left.withColumn("k", F.lit(0)).groupBy("k").cogroup(right.withColumn("k", F.lit(0)).groupBy("k")).applyInArrow(kernel, SCHEMA)
    done = materialise(out, "update")
    small = done.filter(F.col("kind").isin(STEP, TAU)).orderBy("w1").collect()  # one row a superstep
    steps = [(r.i, r.j, r.f, r.w0) for r in small if r.kind == STEP]
    state = done.filter(F.col("kind") == STATE)
    graph = SimilarityGraph(done.filter(F.col("kind") == NODE).select(F.col("i").alias("node_id"), F.col("j").cast("int").alias("truth")), done.filter(F.col("kind") == ARC).select(F.col("i").alias("src"), F.col("j").alias("dst"), F.col("f").alias("w")))
    converged = not steps or steps[-1][1] == 0 or len(steps) < max_steps
    took = time.monotonic() - begun
    run = Run(state.select(F.col("i").alias("node_id"), "f", "w0", "w1", "w_all"), steps, took, "tail", converged, state.filter("j = 1").select(F.col("i").alias("node_id")))
    return Update(graph, run, next((r.x for r in small if r.kind == TAU), 0.0), state.filter("hot").select(F.col("i").alias("node_id")), 0.0)


def reached(g: SimilarityGraph) -> DataFrame:
    """(node_id, reached): whether a node's component holds any ground truth; labels are unique only there.

    Where the graph has been split, components are those of the unlabelled nodes, the ground truth contracted: a path to the truth first
    leaves them at a node with a labelled neighbour."""
    if g.split is not None:
        comps = materialise(connected_components(g.split.arcs.filter("src < dst").select(F.col("src").alias("u"), F.col("dst").alias("v")), g.split.free, packed=g.split.packed), "graph-comps")
        touched = g.split.weights.filter("known > 0").select("node_id")
        seeded = materialise(comps.join(touched, "node_id", "left_semi").select("comp_id").distinct().withColumn("reached", F.lit(True)), "seeded")
        free = lookup(comps, seeded, ["comp_id"], "left", "node_id").select("node_id", F.coalesce("reached", F.lit(False)).alias("reached"))
        return free.unionByName(g.nodes.filter("truth is not null").select("node_id", F.lit(True).alias("reached")))
    comps = materialise(connected_components(g.arcs.filter("src < dst").select(F.col("src").alias("u"), F.col("dst").alias("v")), g.nodes.select("node_id")), "graph-comps")
    seeded = materialise(comps.join(g.nodes.filter("truth is not null").select("node_id"), "node_id", "left_semi").select("comp_id").distinct().withColumn("reached", F.lit(True)), "seeded")
    return lookup(comps, seeded, ["comp_id"], "left", "node_id").select("node_id", F.coalesce("reached", F.lit(False)).alias("reached"))
