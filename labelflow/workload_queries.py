"""The experiment workloads on the given tables, one query each; rows are measurements, so no SQL equals them.

Stand-ins: T text (documents, TF-IDF kNN), V vectors (embeddings, cosine kNN), R random graphs of as many nodes as orders, O the
order-part graph. Sizes follow the table folder. Times are wall seconds of the update alone, graph building apart.
"""

from __future__ import annotations

import time
from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from labelflow.core_queries import order_part_graph, random_graph, seeded, text_graph, vector_graph
from labelflow.functions.fixed import SCALE
from labelflow.functions.hashing import with_hash
from labelflow.operators import graph, harmonic, learners, measures, propagate, sparse_inverse
from labelflow.operators.frontier import frontier_update, reached
from labelflow.operators.graph import SimilarityGraph
from labelflow.operators.propagate import Run, free_state, full_sweep
from labelflow.plans.stage import materialise
from labelflow.registry import query
from labelflow.sources.tables import read

DELTA = 1e-4
DELTAS = (0.1, 0.01, 0.001, 0.0001, 0.00001)
DEGREES = (3, 5, 7)
GAMMAS = (0.1, 1.0, 10.0)
#: Labelled documents of the text graphs whose number of neighbours varies.
SEEDS = 100


def n_orders(spark: SparkSession, sf_dir: str) -> int:
    return read(spark, sf_dir, "orders").count()


def stand_ins(spark: SparkSession, sf_dir: str, frac: float = 0.01) -> dict[str, SimilarityGraph]:
    """The three large stand-ins with a share of the labels shown."""
    g, _ = order_part_graph(spark, sf_dir)
    return {"random": random_graph(spark, n_orders(spark, sf_dir), 5, frac), "order_part": seeded(g, max(frac, 0.02)), "text": text_graph(spark, sf_dir, 5, max(frac, 0.05))[0]}


def reference(g: SimilarityGraph) -> DataFrame:
    """Labels of the harmonic solution, in label units."""
    return materialise(harmonic.harmonic_cg(g, 1e-9).select("node_id", F.round(F.col("label") * SCALE).cast("long").alias("ref")), "reference")


def one_batch(g: SimilarityGraph, delta: float = DELTA, init: str = "component", **how) -> tuple[Run, float]:
    """All unlabelled nodes in one batch on top of the labelled ones; the run, and the seconds of the whole update."""
    known = materialise(g.nodes.filter("truth is not null"), "known")
    free = materialise(g.nodes.filter("truth is null"), "unknown")
    among = g.arcs.join(known.select(F.col("node_id").alias("src")), "src", "left_semi").join(known.select(F.col("node_id").alias("dst")), "dst", "left_semi").select("src", "dst", "w")
    base = SimilarityGraph(known, materialise(among, "base"))
    edges = materialise(g.arcs.filter("src < dst").join(among.select("src", "dst"), ["src", "dst"], "left_anti").select(F.col("src").alias("u"), F.col("dst").alias("v"), "w"), "batch")
    begun = time.monotonic()
    up = frontier_update(base, None, free, edges, delta=delta, init=init, **how)
    return up.run, time.monotonic() - begun


def swept(g: SimilarityGraph, delta: float = DELTA, f0: DataFrame | None = None) -> tuple[Run, float]:
    begun = time.monotonic()
    state, arcs = free_state(g, f0)
    run = full_sweep(state, arcs, delta)
    return run, time.monotonic() - begun


def _accuracy(run_state: DataFrame, ref: DataFrame, flags: DataFrame) -> float:
    return float(measures.accuracy_vs(run_state, ref, flags).first().accuracy or 0.0)


def table(spark: SparkSession, rows: list[tuple], schema: str) -> DataFrame:
    return spark.createDataFrame(rows, schema)


METRICS = "dataset string, method string, parameter double, n long, iterations long, updates long, seconds double, accuracy double"


def _row(dataset, method, parameter, n, run: Run | None, seconds, accuracy) -> tuple:
    return dataset, method, float(parameter), int(n), int(run.iterations) if run else 0, int(run.updates) if run else 0, round(float(seconds), 4), None if accuracy is None else round(float(accuracy), 4)


@query("w1_size_sweep")
def w1_size_sweep(spark, sf_dir):
    """Degree 5, 1% truth, one batch: iterations and time by dataset and size."""
    n = n_orders(spark, sf_dir)
    rows = []
    for size in (max(200, n // 10), n):
        g = random_graph(spark, size, 5, 0.01)
        run, s = one_batch(g)
        rows.append(_row("random", "frontier", size, size, run, s, None))
    for name, g in stand_ins(spark, sf_dir).items():
        if name != "random":
            run, s = one_batch(g)
            rows.append(_row(name, "frontier", 0, g.nodes.count(), run, s, None))
    return table(spark, rows, METRICS)


@query("w2_delta_by_dataset")
def w2_delta_by_dataset(spark, sf_dir):
    """Threshold against accuracy, iterations and time, on text, vectors, random and order-part graphs."""
    rows = []
    for name, g in (stand_ins(spark, sf_dir) | {"vectors": vector_graph(spark, sf_dir, 5, 0.05)[0]}).items():
        ref, flags, n = reference(g), materialise(reached(g), "flags"), g.nodes.count()
        for delta in DELTAS:
            run, s = one_batch(g, delta)
            rows.append(_row(name, "frontier", delta, n, run, s, _accuracy(run.state, ref, flags)))
    return table(spark, rows, METRICS)


@query("w3_delta_by_batch")
def w3_delta_by_batch(spark, sf_dir):
    """Threshold against accuracy for growing batches on the random graph."""
    n, rows = n_orders(spark, sf_dir), []
    for size in sorted({max(150, n // 100), max(300, n // 10), n}):
        g = random_graph(spark, size, 5, 0.01)
        ref, flags = reference(g), materialise(reached(g), "flags")
        for delta in DELTAS:
            run, s = one_batch(g, delta)
            rows.append(_row("random", "frontier", delta, size, run, s, _accuracy(run.state, ref, flags)))
    return table(spark, rows, METRICS)


def growing(spark: SparkSession, g: SimilarityGraph, batches: int = 5, delta: float = DELTA, changes: DataFrame | None = None, sweeps: bool = True) -> list[tuple]:
    """Batches arrive until the graph is whole; per batch the frontier update, the restarted and the warm full sweep. `changes` gives
    the batches (see graph.make_batches), deletions among them; else nodes arrive by hash on top of most of the labelled ones. Rows
    of _row, parameter being the batch."""
    if changes is None:
        order = with_hash(g.nodes, "h", "node_id", 21)
        order = order.withColumn("batch", F.when(F.col("truth").isNotNull() & (F.col("h") % 10 < 9), 0).otherwise(1 + F.col("h") % batches))
    else:
        order = changes.filter("op = 'ins'").select("node_id", "truth", "batch_id", F.col("batch_id").alias("batch"))
    order = materialise(order, "arrival")
    edges = materialise(g.arcs.filter("src < dst").select(F.col("src").alias("u"), F.col("dst").alias("v"), "w"), "all-edges")
    at = lambda c: order.select(F.col("node_id").alias(c), F.col("batch").alias(f"b_{c}"))
    edges = materialise(edges.join(at("u"), "u").join(at("v"), "v").withColumn("batch", F.greatest("b_u", "b_v")).select("u", "v", "w", "batch"), "dated-edges")
    cur = SimilarityGraph(materialise(order.filter("batch = 0").select("node_id", "truth"), "base"), materialise(graph.arcs_of(edges.filter("batch = 0")), "base-arcs"))
    labels, rows = None, []
    for b in range(1, batches + (changes is None)):
        ins = materialise(order.filter(F.col("batch") == b).select("node_id", "truth"), "ins")
        dels = None if changes is None else materialise(changes.filter((F.col("op") == "del") & (F.col("batch_id") == b)).select("node_id"), "dels")
        begun = time.monotonic()
        up = frontier_update(cur, labels, ins, edges.filter(F.col("batch") == b).select("u", "v", "w"), dels, delta=delta)
        took = time.monotonic() - begun
        cur = up.graph
        if not sweeps:
            labels = up.run.state
            rows.append(_row("", "frontier", b, cur.nodes.count(), up.run, took, None))
            continue
        full, s_full = swept(cur, delta)
        warm_from = labels.select("node_id", F.col("f").alias("f0")) if labels is not None else None
        warm, s_warm = swept(cur, delta, warm_from)
        labels = up.run.state
        ref = full.state.select("node_id", F.col("f").alias("ref"))
        n = cur.nodes.count()
        flags = cur.nodes.select("node_id", F.lit(True).alias("reached"))
        rows.append(_row("", "frontier", b, n, up.run, took, _accuracy(up.run.state, ref, flags)))
        rows.append(_row("", "full_sweep", b, n, full, s_full, 1.0))
        rows.append(_row("", "full_sweep_warm", b, n, warm, s_warm, _accuracy(warm.state, ref, flags)))
    return rows


@query("w4_iterations_vs_sweep")
def w4_iterations_vs_sweep(spark, sf_dir):
    """Iterations and updates against full sweeps while batches arrive: random graphs by degree, text by k and with as many seeds at any k."""
    rows = []
    for d in DEGREES:
        g = random_graph(spark, n_orders(spark, sf_dir), d, 0.01)
        rows += [(f"random_deg{d}", *r[1:]) for r in growing(spark, g, 3)]
    for k in DEGREES:
        g, truth = text_graph(spark, sf_dir, k, 1.0)
        seeds = graph.choose_seeds(truth, n=SEEDS)
        g = SimilarityGraph(materialise(g.nodes.select("node_id").join(seeds, "node_id", "left"), "seeded"), g.arcs)
        rows += [(f"text_k{k}", *r[1:]) for r in growing(spark, g, 2)]
    return table(spark, rows, METRICS)


@query("w5_speedup_vs_sweep")
def w5_speedup_vs_sweep(spark, sf_dir):
    """Time and work of the full sweep over the frontier update, by batch."""
    g, _ = order_part_graph(spark, sf_dir)
    m = table(spark, [("order_part", *r[1:]) for r in growing(spark, seeded(g, 0.05), 4)], METRICS)
    own = m.filter("method = 'frontier'").select("parameter", F.col("seconds").alias("own_s"), F.col("updates").alias("own_u"))
    return m.filter("method != 'frontier'").join(own, "parameter").select("dataset", "method", F.col("parameter").cast("int").alias("batch"), F.round(F.col("seconds") / F.col("own_s"), 3).alias("time_ratio"), F.round(F.col("updates") / F.greatest("own_u", F.lit(1)), 3).alias("work_ratio"))


def timed(run: Callable[[], DataFrame]) -> tuple[DataFrame, float]:
    begun = time.monotonic()
    out = materialise(run(), "timed")
    return out, time.monotonic() - begun


def _label_accuracy(labels: DataFrame, ref: DataFrame, flags: DataFrame) -> float:
    return _accuracy(labels.select("node_id", F.round(F.col("label") * SCALE).cast("long").alias("f")), ref, flags)


@query("w6_vs_contracted")
def w6_vs_contracted(spark, sf_dir):
    """Against the contracted harmonic, as far as its matrix fits; seconds with inputs at hand (compute) and with reading them (transfer)."""
    rows = []
    for n in (500, 1_000, 2_000):
        g = random_graph(spark, n, 5, 0.1)
        _, cold = timed(lambda g=g: harmonic.harmonic_contracted(g))
        state, arcs = free_state(g)
        _, warm = timed(lambda s=state, a=arcs: harmonic._one_task(s, a, harmonic._solve_dense))
        run, s = one_batch(g)
        rows += [("contracted", n, round(warm, 4), round(cold, 4)), ("frontier", n, round(run.seconds, 4), round(s, 4))]
    return table(spark, rows, "method string, n int, compute_seconds double, total_seconds double")


def _features(docs: DataFrame) -> DataFrame:
    from pyspark.ml.functions import vector_to_array

    from labelflow.operators.similarity import hashed_tfidf

    return hashed_tfidf(docs, features=256).select("node_id", vector_to_array("features").alias("x"))


@query("w7_vs_neural_knn")
def w7_vs_neural_knn(spark, sf_dir):
    """Vectors, a few per cent of truth, five batches: frontier against the neural learner, accuracy on the planted classes."""
    g, x, truth = vector_graph(spark, sf_dir, 5, 0.04)
    held = truth.join(g.nodes.filter("truth is null").select("node_id"), "node_id", "left_semi")
    order = materialise(with_hash(g.nodes, "h", "node_id", 21).withColumn("batch", F.when(F.col("truth").isNotNull(), 0).otherwise(1 + F.col("h") % 5)), "arrival")
    rows = []
    acc = lambda df, some: float(measures.accuracy_truth(df, some).first().accuracy or 0)
    for b in range(1, 6):  # what has arrived by batch b
        here = materialise(order.filter(F.col("batch") <= b).select("node_id"), "here")
        arcs = g.arcs.join(here.withColumnRenamed("node_id", "src"), "src", "left_semi").join(here.withColumnRenamed("node_id", "dst"), "dst", "left_semi")
        part = SimilarityGraph(materialise(g.nodes.join(here, "node_id", "left_semi"), "part"), materialise(arcs.select("src", "dst", "w"), "part-arcs"))
        some = materialise(held.join(here, "node_id", "left_semi"), "held")
        run, s = one_batch(part)
        got, t = timed(lambda part=part, here=here: learners.neural_knn(part, x.join(here, "node_id", "left_semi")))
        n = part.nodes.count()
        rows += [_row("vectors", "frontier", b, n, run, s, acc(run.state, some)), _row("vectors", "neural_knn", b, n, None, t, acc(got.select("node_id", F.round(F.col("label") * SCALE).cast("long").alias("f")), some))]
    return table(spark, rows, METRICS)


@query("w8_vs_gcn")
def w8_vs_gcn(spark, sf_dir):
    """Text: frontier against the graph convolution, accuracy on the language."""
    g, truth = text_graph(spark, sf_dir, 5, 0.05)
    held = truth.join(g.nodes.filter("truth is null").select("node_id"), "node_id", "left_semi")
    x = materialise(_features(read(spark, sf_dir, "documents")), "features")
    run, s = one_batch(g)
    got, t = timed(lambda: learners.gcn_two_layer(g, x, epochs=60))
    acc = lambda df: float(measures.accuracy_truth(df, held).first().accuracy or 0)
    n = g.nodes.count()
    return table(spark, [_row("text", "frontier", 0, n, run, s, acc(run.state)), _row("text", "gcn", 0, n, None, t, acc(got.select("node_id", F.round(F.col("label") * SCALE).cast("long").alias("f"))))], METRICS)


@query("w9_single_batch_times")
def w9_single_batch_times(spark, sf_dir):
    """All methods on one batch with 1% truth; a dense method that refuses the size has no time."""
    rows = []
    for name, g in stand_ins(spark, sf_dir).items():
        n = g.nodes.count()
        run, s = one_batch(g)
        rows.append(_row(name, "frontier", 0, n, run, s, None))
        run, s = swept(g)
        rows.append(_row(name, "full_sweep", 0, n, run, s, None))
        try:
            _, s = timed(lambda g=g: harmonic.harmonic_contracted(g, 3_000))
            rows.append(_row(name, "harmonic_contracted", 0, n, None, s, None))
        except harmonic.CapacityError:
            rows.append((name, "harmonic_contracted", 0.0, n, 0, 0, None, None))
        try:
            _, s = timed(lambda g=g: sparse_inverse.harmonic_sparse_inverse(g, 1.0, "ratio", 60))
            rows.append(_row(name, "harmonic_sparse_inverse", 1.0, n, None, s, None))
        except harmonic.CapacityError:
            rows.append((name, "harmonic_sparse_inverse", 1.0, n, 0, 0, None, None))
    rows += _learned(spark, sf_dir)
    return table(spark, rows, METRICS)


def _learned(spark: SparkSession, sf_dir: str) -> list[tuple]:
    """The learners, which need features: the graph convolution and the neural kNN on text and vectors, and the frontier beside them."""
    rows = []
    text, labels = text_graph(spark, sf_dir, 5, 0.05)
    vectors, x, planted = vector_graph(spark, sf_dir, 5, 0.04)
    words = materialise(_features(read(spark, sf_dir, "documents")), "features")
    for name, g, feats, truth in (("text", text, words, labels), ("vectors", vectors, x, planted)):
        n = g.nodes.count()
        held = materialise(truth.join(g.nodes.filter("truth is null").select("node_id"), "node_id", "left_semi"), "held")
        acc = lambda df: float(measures.accuracy_truth(df, held).first().accuracy or 0)  # noqa: B023, E731
        as_units = lambda df: df.select("node_id", F.round(F.col("label") * SCALE).cast("long").alias("f"))
        run, s = one_batch(g)
        rows.append(_row(f"{name}_learned", "frontier", 0, n, run, s, acc(run.state)))
        got, s = timed(lambda g=g, feats=feats: learners.gcn_two_layer(g, feats, epochs=60))
        rows.append(_row(f"{name}_learned", "gcn", 0, n, None, s, acc(as_units(got))))
        got, s = timed(lambda g=g, feats=feats: learners.neural_knn(g, feats))
        rows.append(_row(f"{name}_learned", "neural_knn", 0, n, None, s, acc(as_units(got))))
    return rows


@query("w10_random_batches")
def w10_random_batches(spark, sf_dir):
    """Random graphs of rising size: time and accuracy of every method, gamma in 0.1, 1 and 10."""
    n, rows = n_orders(spark, sf_dir), []
    for size in sorted({min(n, 500), min(n, 1_500), n}):
        g = random_graph(spark, size, 5, 0.1)
        ref, flags = reference(g), materialise(reached(g), "flags")
        run, s = one_batch(g)
        rows.append(_row("random", "frontier", 0, size, run, s, _accuracy(run.state, ref, flags)))
        run, s = swept(g)
        rows.append(_row("random", "full_sweep", 0, size, run, s, _accuracy(run.state, ref, flags)))
        if size <= 1_500:
            got, s = timed(lambda g=g: harmonic.harmonic_contracted(g))
            rows.append(_row("random", "harmonic_contracted", 0, size, None, s, _label_accuracy(got, ref, flags)))
            for gamma in GAMMAS:
                got, s = timed(lambda g=g, x=gamma: sparse_inverse.harmonic_sparse_inverse(g, x, "ratio", 60))
                rows.append(_row("random", "harmonic_sparse_inverse", gamma, size, None, s, _label_accuracy(got, ref, flags)))
    return table(spark, rows, METRICS)


@query("w11_summary")
def w11_summary(spark, sf_dir):
    """Average and best accuracy, average and largest time ratio, largest graph, by method."""
    m = materialise(w10_random_batches(spark, sf_dir).unionByName(w9_single_batch_times(spark, sf_dir)), "metrics")
    own = m.filter("method = 'frontier'").groupBy("dataset", "n").agg(F.min("seconds").alias("own"))
    return m.join(own, ["dataset", "n"]).groupBy("method").agg(F.round(F.avg("accuracy"), 4).alias("accuracy_avg"), F.round(F.max("accuracy"), 4).alias("accuracy_max"), F.round(F.avg(F.col("seconds") / F.col("own")), 3).alias("ratio_avg"), F.round(F.max(F.col("seconds") / F.col("own")), 3).alias("ratio_max"), F.max(F.when(F.col("seconds").isNotNull(), F.col("n"))).alias("max_nodes"))


@query("w12_dynamic_mix")
def w12_dynamic_mix(spark, sf_dir):
    """Batches of 90% unlabelled inserts, 1% labelled ones and 9% deletions with replacement, on text, random and order-part graphs."""
    rows = []
    graphs = {"text": text_graph(spark, sf_dir, 5, 1.0)[0], "random": random_graph(spark, n_orders(spark, sf_dir), 5, 1.0), "order_part": order_part_graph(spark, sf_dir)[0]}
    for name, g in graphs.items():
        changes = materialise(graph.normalise_changes(graph.make_batches(g.nodes, 4)), "changes")
        rows += [(name, *r[1:]) for r in growing(spark, g, 4, changes=changes)]
    return table(spark, rows, METRICS)


@query("w13_batch_scaling")
def w13_batch_scaling(spark, sf_dir):
    """Total seconds by number of equal batches, 1 to 20, and the line through them."""
    g = random_graph(spark, n_orders(spark, sf_dir), 5, 0.02)
    rows, total = [], 0.0
    for r in growing(spark, g, 20, sweeps=False):
        total += r[6]
        rows.append((int(r[2]), total))
    m = table(spark, rows, "batches int, seconds double")
    return m.crossJoin(F.broadcast(measures.batch_slope(m)))  # one row


@query("w14_overlap")
def w14_overlap(spark, sf_dir):
    """Reading the old arcs while the new nodes' components run, against one after the other."""
    from concurrent.futures import ThreadPoolExecutor

    from pyspark import inheritable_thread_target

    from labelflow.core_queries import fresh_ids
    from labelflow.operators.components import connected_components

    g, edges = order_part_graph(spark, sf_dir)
    new = fresh_ids(spark, sf_dir)
    tau = graph.tau_mean(edges)
    load = lambda: materialise(g.arcs.repartition("src").sortWithinPartitions("src"), "warm").count()
    find = lambda: materialise(connected_components(graph.new_subgraph(g.arcs, new, tau), new), "found").count()
    begun = time.monotonic()
    load()
    find()
    serial = time.monotonic() - begun
    begun = time.monotonic()
    with ThreadPoolExecutor(2) as pool:
        jobs = [pool.submit(inheritable_thread_target(spark)(f)) for f in (load, find)]
        _ = [j.result() for j in jobs]
    both = time.monotonic() - begun
    return table(spark, [("serial", round(serial, 4)), ("overlapped", round(both, 4)), ("gain", round(serial / both, 4))], "measure string, value double")


@query("w15_toy_components", "SELECT * FROM (VALUES (5, 8, 8), (5, 9, 8), (5, 10, 10), (1, 8, 8), (1, 9, 8), (1, 10, 8)) t(tau, node_id, comp_id)")
def w15_toy_components(spark, sf_dir):
    """Three nodes, thresholds 5 and 1: an edge of weight equal to the threshold is removed."""
    from labelflow.operators.components import connected_components

    edges = spark.createDataFrame([(8, 9, 9), (9, 10, 3), (8, 10, 1)], "u long, v long, w long")
    nodes = spark.createDataFrame([(8,), (9,), (10,)], "node_id long")
    out = None
    for tau in (5, 1):
        got = connected_components(edges.filter(F.col("w") > tau), nodes, "hook_jump").select(F.lit(tau).alias("tau"), "node_id", "comp_id")
        out = got if out is None else out.unionByName(got)
    return out


@query("w16_init_ablation")
def w16_init_ablation(spark, sf_dir):
    """Neutral, per-node and component initial labels: iterations, work, accuracy."""
    rows = []
    for name, g in stand_ins(spark, sf_dir).items():
        ref, flags, n = reference(g), materialise(reached(g), "flags"), g.nodes.count()
        for init in ("half", "vertex", "component"):
            run, s = one_batch(g, DELTA, init)
            rows.append(_row(name, init, 0, n, run, s, _accuracy(run.state, ref, flags)))
    return table(spark, rows, METRICS)


@query("w17_dataset_summary")
def w17_dataset_summary(spark, sf_dir):
    out = []
    for name, g in stand_ins(spark, sf_dir).items():
        out.append((name, g.nodes.count(), g.arcs.count() // 2, g.nodes.filter("truth is not null").count()))
    g, _, _ = vector_graph(spark, sf_dir)
    out.append(("vectors", g.nodes.count(), g.arcs.count() // 2, g.nodes.filter("truth is not null").count()))
    return table(spark, out, "dataset string, nodes long, edges long, labelled long")


@query("w19_review_labels")
def w19_review_labels(spark, sf_dir):
    """The quality marks as review labels over the text graph: accuracy against the harmonic solution, beside the majority."""
    g, _ = text_graph(spark, sf_dir)
    marks = read(spark, sf_dir, "labels").select(F.col("doc_id").alias("node_id"), F.col("quality").alias("truth"))
    g = SimilarityGraph(materialise(g.nodes.select("node_id").join(graph.choose_seeds(marks, frac=0.5), "node_id", "left"), "nodes"), g.arcs)
    run, _ = one_batch(g)
    return measures.accuracy_vs(run.state, reference(g), reached(g))


@query("w20_feature_export")
def w20_feature_export(spark, sf_dir):
    """Labels and component sizes as columns beside the documents, for other learners."""
    from labelflow.operators.components import connected_components

    g, _ = text_graph(spark, sf_dir)
    state, arcs = free_state(g)
    f = propagate.all_labels(g, full_sweep(state, arcs, 1e-3).state)
    comps = materialise(connected_components(g.arcs.filter("src < dst").select(F.col("src").alias("u"), F.col("dst").alias("v")), g.nodes.select("node_id")), "comps")
    sizes = comps.groupBy("comp_id").agg(F.count("*").alias("size"))
    return f.join(comps, "node_id").join(sizes, "comp_id").select("node_id", F.round(F.col("f") / SCALE, 6).alias("label"), "comp_id", "size")


@query("w_capacity")
def w_capacity(spark, sf_dir):
    """Largest random graph that a dense and a sparse method accept here: the size doubles until a method refuses it by its own bound or
    takes over ten seconds, or the table's orders have been used up 16 times."""
    rows = []
    sizes = [1_000 << k for k in range(20) if 1_000 << k <= 16 * n_orders(spark, sf_dir)]
    for method, run in (("harmonic_contracted", lambda n: harmonic.harmonic_contracted(random_graph(spark, n)).count()), ("frontier", lambda n: one_batch(random_graph(spark, n)))):
        for n, ok, s in measures.capacity_probe(run, sizes, 10.0):
            rows.append((method, n, ok, round(s, 3)))
    return table(spark, rows, "method string, n int, ran boolean, seconds double")


def late_batch(spark: SparkSession, sf_dir: str, frac: float = 0.02, delta: float = DELTA) -> list[tuple]:
    """The orders of the last two months arrive on a graph whose labels have settled: frontier update, restarted sweep, warm sweep."""
    from labelflow.core_queries import gone_ids, within

    g, edges = order_part_graph(spark, sf_dir)
    g = seeded(g, frac)
    orders = read(spark, sf_dir, "orders")
    cut = orders.agg((F.date_trunc("month", F.max("o_orderdate")) - F.expr("INTERVAL 1 MONTH")).alias("cut"))
    new = materialise(orders.join(F.broadcast(cut), F.col("o_orderdate") >= F.col("cut")).select((F.col("o_orderkey") * 2).alias("node_id")), "late")  # one row
    old = within(g, new)
    labels = swept(old, delta / 10)[0].state
    ins = materialise(g.nodes.join(new, "node_id", "left_semi"), "late-nodes")
    ins_edges = materialise(edges.join(new.withColumnRenamed("node_id", "u"), "u", "left_semi"), "late-edges")
    dels = materialise(gone_ids(spark, sf_dir), "late-dels")
    old = SimilarityGraph(materialise(old.nodes, "old-nodes"), old.arcs)
    begun = time.monotonic()
    up = frontier_update(old, labels, ins, ins_edges, dels, delta=delta)
    took = time.monotonic() - begun
    full, s_full = swept(up.graph, delta)
    warm, s_warm = swept(up.graph, delta, labels.select("node_id", F.col("f").alias("f0")))
    ref, n = reference(up.graph), up.graph.nodes.count()
    flags = materialise(reached(up.graph), "flags")
    return [_row("order_part", m, delta, n, r, s, _accuracy(r.state, ref, flags)) for m, r, s in (("frontier", up.run, took), ("full_sweep", full, s_full), ("full_sweep_warm", warm, s_warm))]


@query("w_workload_summary")
def w_workload_summary(spark, sf_dir):
    """The headline: a late batch on a settled order-part graph, every method judged against the harmonic solution."""
    return table(spark, late_batch(spark, sf_dir), METRICS)
