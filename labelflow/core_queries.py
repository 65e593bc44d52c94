"""Queries of the method itself, on the order-part graph: components, initial labels, sweeps, frontier steps, updates, baselines."""

from __future__ import annotations



from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from labelflow import oracle_parts as sql
from labelflow.functions.fixed import HALF, SCALE
from labelflow.functions.hashing import P, hash_sql
from labelflow.operators import graph, harmonic, learners, measures, propagate, similarity, sparse_inverse
from labelflow.operators.classweights import component_weights, contraction, initial_labels, update_contraction
from labelflow.operators.components import connected_components
from labelflow.operators.frontier import frontier_update, reached
from labelflow.operators.graph import SimilarityGraph
from labelflow.plans.joins import lookup, without
from labelflow.plans.stage import materialise
from labelflow.registry import query
from labelflow.sources.random_graph import er_edges
from labelflow.sources.tables import read

DELTA = 1e-4
STEPS = 10


def order_part_graph(spark: SparkSession, sf_dir: str) -> tuple[SimilarityGraph, DataFrame]:
    nodes, edges = graph.order_part(read(spark, sf_dir, "orders"), read(spark, sf_dir, "lineitem"))
    edges = materialise(edges, "edges")
    return SimilarityGraph(materialise(nodes, "nodes"), materialise(graph.arcs_of(edges), "arcs")), edges


def fresh_ids(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Orders of the last two months and every tenth part."""
    orders = read(spark, sf_dir, "orders")
    cut = orders.agg((F.date_trunc("month", F.max("o_orderdate")) - F.expr("INTERVAL 1 MONTH")).alias("cut"))
    late = orders.join(F.broadcast(cut), F.col("o_orderdate") >= F.col("cut")).select((F.col("o_orderkey") * 2).alias("node_id"))  # one row
    parts = read(spark, sf_dir, "lineitem").filter("l_partkey % 10 = 0").select((F.col("l_partkey") * 2 + 1).alias("node_id")).distinct()
    return materialise(late.unionByName(parts), "fresh")


def gone_ids(spark: SparkSession, sf_dir: str) -> DataFrame:
    orders = read(spark, sf_dir, "orders")
    cut = orders.agg((F.date_trunc("month", F.max("o_orderdate")) - F.expr("INTERVAL 1 MONTH")).alias("cut"))
    return orders.filter("o_orderkey % 97 = 5").join(F.broadcast(cut), F.col("o_orderdate") < F.col("cut")).select((F.col("o_orderkey") * 2).alias("node_id"))


def within(g: SimilarityGraph, out: DataFrame) -> SimilarityGraph:
    """The graph without some nodes."""
    nodes = without(g.nodes, out, ["node_id"])
    arcs = without(without(g.arcs, out.withColumnRenamed("node_id", "src"), ["src"]), out.withColumnRenamed("node_id", "dst"), ["dst"])
    return SimilarityGraph(nodes, materialise(arcs, "old-arcs"))


_BASE = f"WITH {sql.EDGES}, {sql.NODES}, {sql.arcs()}, {sql.contraction()}, {sql.start()}, {sql.free_arcs()}"
_SUB = f"""WITH RECURSIVE {sql.EDGES}, fresh AS MATERIALIZED ({sql.NEW_IDS}), {sql.arcs()}, tau AS (SELECT avg(w) AS tau FROM edges),
sub AS MATERIALIZED (SELECT src, dst, w FROM arcs, tau WHERE w > tau AND src IN (SELECT node_id FROM fresh) AND dst IN (SELECT node_id FROM fresh)), {sql.components('fresh', 'sub')}"""


@query("cc_new_vertices", f"{_SUB} SELECT node_id, comp_id FROM cc")
def cc_new_vertices(spark, sf_dir):
    g, edges = order_part_graph(spark, sf_dir)
    new = fresh_ids(spark, sf_dir)
    return connected_components(graph.new_subgraph(g.arcs, new, graph.tau_mean(edges)), new)


@query("cc_hook_jump", f"{_SUB} SELECT node_id, comp_id FROM cc")
def cc_hook_jump(spark, sf_dir):
    g, edges = order_part_graph(spark, sf_dir)
    new = fresh_ids(spark, sf_dir)
    return connected_components(graph.new_subgraph(g.arcs, new, graph.tau_mean(edges)), new, "hook_jump")


@query("cc_stars", f"{_SUB} SELECT node_id, comp_id FROM cc")
def cc_stars(spark, sf_dir):
    g, edges = order_part_graph(spark, sf_dir)
    new = fresh_ids(spark, sf_dir)
    return connected_components(graph.new_subgraph(g.arcs, new, graph.tau_mean(edges)), new, "stars")


_TAU = f"WITH {sql.EDGES}, tau AS (SELECT avg(w) AS tau FROM edges)"


@query("cc_tau_flagged", f"{_TAU} SELECT u, v, w, w > tau AS keep FROM edges, tau")
def cc_tau_flagged(spark, sf_dir):
    _, edges = graph.order_part(read(spark, sf_dir, "orders"), read(spark, sf_dir, "lineitem"))
    return graph.flag_arcs(edges.crossJoin(F.broadcast(edges.agg(F.avg("w").alias("tau")))), F.col("tau")).drop("tau")  # one row


@query("densify_components", f"{_SUB} SELECT node_id, comp_id, dense_rank() OVER (ORDER BY comp_id) - 1 AS dense_id FROM cc")
def densify_components(spark, sf_dir):
    from labelflow.operators.components import densify

    return densify(cc_new_vertices(spark, sf_dir)).select("node_id", "comp_id", "dense_id")


_INIT = f"""{_SUB}, {sql.NODES}, {sql.contraction()},
comp AS (SELECT comp_id, sum(CASE WHEN truth IS NULL THEN coalesce(w0, 0) ELSE 0 END) AS w0, sum(CASE WHEN truth IS NULL THEN coalesce(w1, 0) ELSE 0 END) AS w1, count(*) AS size FROM cc JOIN nodes USING (node_id) LEFT JOIN cw USING (node_id) GROUP BY comp_id)"""
_F0 = f"CASE WHEN truth IS NOT NULL THEN truth * {SCALE} WHEN w0 + w1 > 0 THEN (2 * w1 * {SCALE} + w0 + w1) // (2 * (w0 + w1)) ELSE {HALF} END"


def _init(spark, sf_dir, init):
    g, edges = order_part_graph(spark, sf_dir)
    new = fresh_ids(spark, sf_dir)
    return initial_labels(new, graph.new_subgraph(g.arcs, new, graph.tau_mean(edges)), contraction(g.arcs, g.nodes), g.nodes, init)


@query("init_component_labels", f"{_INIT} SELECT cc.node_id, CAST({_F0} AS BIGINT) AS f0, comp_id FROM cc JOIN comp USING (comp_id) JOIN nodes USING (node_id)")
def init_component_labels(spark, sf_dir):
    return _init(spark, sf_dir, "component")


@query("init_vertex_labels", f"WITH {sql.EDGES}, {sql.NODES}, {sql.arcs()}, {sql.contraction()}, fresh AS ({sql.NEW_IDS}) SELECT node_id, CAST({_F0} AS BIGINT) AS f0, node_id AS comp_id FROM fresh JOIN nodes USING (node_id) LEFT JOIN cw USING (node_id)".replace("WHEN w0 + w1 > 0", "WHEN coalesce(w0 + w1, 0) > 0"))
def init_vertex_labels(spark, sf_dir):
    return _init(spark, sf_dir, "vertex")


@query("init_half", f"WITH {sql.NODES}, fresh AS ({sql.NEW_IDS}) SELECT node_id, CAST(CASE WHEN truth IS NOT NULL THEN truth * {SCALE} ELSE {HALF} END AS BIGINT) AS f0, node_id AS comp_id FROM fresh JOIN nodes USING (node_id)")
def init_half(spark, sf_dir):
    return _init(spark, sf_dir, "half")


@query("component_weights", f"{_INIT} SELECT comp_id, CAST(w0 AS BIGINT) AS w0, CAST(w1 AS BIGINT) AS w1, size FROM comp")
def component_weights_query(spark, sf_dir):
    g, edges = order_part_graph(spark, sf_dir)
    new = fresh_ids(spark, sf_dir)
    comps = connected_components(graph.new_subgraph(g.arcs, new, graph.tau_mean(edges)), new)
    return component_weights(comps, contraction(g.arcs, g.nodes), g.nodes)


@query("contraction_weights", f"{_BASE} SELECT node_id, w0, w1, w_all FROM cw")
def contraction_weights(spark, sf_dir):
    g, _ = order_part_graph(spark, sf_dir)
    return contraction(g.arcs, g.nodes)


@query("contraction_incremental", f"{_BASE}, gone AS ({sql.DEL_IDS}) SELECT src AS node_id, CAST(sum(CASE WHEN truth = 0 THEN w ELSE 0 END) AS BIGINT) AS w0, CAST(sum(CASE WHEN truth = 1 THEN w ELSE 0 END) AS BIGINT) AS w1, CAST(sum(w) AS BIGINT) AS w_all FROM arcs LEFT JOIN nodes ON dst = node_id WHERE src NOT IN (SELECT node_id FROM gone) AND dst NOT IN (SELECT node_id FROM gone) GROUP BY src")
def contraction_incremental(spark, sf_dir):
    g, _ = order_part_graph(spark, sf_dir)
    gone = materialise(gone_ids(spark, sf_dir), "gone")
    after, _ = graph.apply_deletes(g, gone)
    removed = g.arcs.join(after.arcs, ["src", "dst"], "left_anti")
    out = update_contraction(contraction(g.arcs, g.nodes), after.arcs.limit(0), removed, g.nodes)
    return out.filter("w_all > 0").join(F.broadcast(gone), "node_id", "left_anti") if gone.count() < 500_000 else out.filter("w_all > 0").join(gone, "node_id", "left_anti")


def _swept(spark, sf_dir, k, weighted=True, plan="auto"):
    g, _ = order_part_graph(spark, sf_dir)
    if not weighted:
        g = SimilarityGraph(g.nodes, propagate.unweighted(g.arcs))
    state, arcs = propagate.free_state(g)
    return g, arcs, propagate.full_sweep(state, arcs, 0.0, plan, k)


@query("sweep_k20_order_part", f"{_BASE}, {sql.sweeps(20)} SELECT node_id, f, w1, w_all FROM s20")
def sweep_k20(spark, sf_dir):
    return _swept(spark, sf_dir, 20)[2].state.select("node_id", "f", "w1", "w_all")


@query("sweep_k3_distributed", f"{_BASE}, {sql.sweeps(3)} SELECT node_id, f FROM s3")
def sweep_k3_distributed(spark, sf_dir):
    return _swept(spark, sf_dir, 3, plan="sync")[2].state.select("node_id", "f")


_UNW = _BASE.replace("CAST(sum(l_quantity) AS BIGINT) AS w", "CAST(1 AS BIGINT) AS w")


@query("sweep_unweighted", f"{_UNW}, {sql.sweeps(8)} SELECT node_id, f FROM s8")
def sweep_unweighted(spark, sf_dir):
    return _swept(spark, sf_dir, 8, False)[2].state.select("node_id", "f")


@query("sweep_weighted_vs_unweighted", f"{_BASE}, {sql.sweeps(8)}, b AS (SELECT * FROM ({_UNW}, {sql.sweeps(8)} SELECT node_id, f FROM s8)) SELECT count(*) AS n, count(*) FILTER (WHERE (s8.f >= {HALF}) = (b.f >= {HALF})) AS same_class, max(abs(s8.f - b.f)) AS max_difference FROM s8 JOIN b USING (node_id)")
def sweep_weighted_vs_unweighted(spark, sf_dir):
    a = _swept(spark, sf_dir, 8)[2].state.select("node_id", F.col("f").alias("a"))
    b = _swept(spark, sf_dir, 8, False)[2].state.select("node_id", F.col("f").alias("b"))
    same = ((F.col("a") >= HALF) == (F.col("b") >= HALF)).cast("long")
    return a.join(b, "node_id").agg(F.count("*").alias("n"), F.sum(same).alias("same_class"), F.max(F.abs(F.col("a") - F.col("b"))).alias("max_difference"))


def _relaxed(spark, sf_dir, form):
    _, arcs, run = _swept(spark, sf_dir, 3)
    return propagate.relax(run.state, arcs, None, form).select("node_id", "new")


_RELAXED = f"{_BASE}, {sql.sweeps(4)} SELECT s4.node_id, CASE WHEN w_all > 0 THEN f END AS new FROM s4"


@query("relax_average", _RELAXED)
def relax_average(spark, sf_dir):
    return _relaxed(spark, sf_dir, "average")


@query("relax_adjust", _RELAXED)
def relax_adjust(spark, sf_dir):
    return _relaxed(spark, sf_dir, "adjust")


def update(spark, sf_dir, inserts=True, deletes=True, steps=STEPS, delta=DELTA, **how):
    """The batch of the update queries, on labels of five sweeps."""
    g, edges = order_part_graph(spark, sf_dir)
    new = fresh_ids(spark, sf_dir) if inserts else None
    old = within(g, new) if inserts else g
    parts = propagate.split(old, packing=True)
    labels = propagate.full_sweep(propagate.start_state(parts), parts.arcs, 0.0, "auto", 5, packed=parts.packed).state
    ins = ins_edges = None
    if inserts:
        ins = materialise(g.nodes.join(new, "node_id", "left_semi"), "ins-nodes")
        near = lookup(edges, new.select(F.col("node_id").alias("u"), F.lit(1).alias("a")), ["u"], "left", "v")
        touching = lookup(near, new.select(F.col("node_id").alias("v"), F.lit(1).alias("b")), ["v"], "left", "u")
        ins_edges = materialise(touching.filter("a = 1 or b = 1").select("u", "v", "w"), "ins-edges")
    return frontier_update(old, labels, ins, ins_edges, gone_ids(spark, sf_dir) if deletes else None, delta=delta, max_steps=steps, **how)


_LAST = f"SELECT node_id, f, w0, w1, w_all FROM t{STEPS}"


@query("update_mixed", sql.update_sql(True, True, STEPS, DELTA, _LAST))
def update_mixed(spark, sf_dir):
    return update(spark, sf_dir).run.state


@query("update_insert_only", sql.update_sql(True, False, STEPS, DELTA, _LAST))
def update_insert_only(spark, sf_dir):
    return update(spark, sf_dir, deletes=False).run.state


@query("update_delete_only", sql.update_sql(False, True, STEPS, DELTA, _LAST))
def update_delete_only(spark, sf_dir):
    return update(spark, sf_dir, inserts=False).run.state


@query("frontier_k10", sql.update_sql(True, False, STEPS, DELTA, f"SELECT node_id, f, node_id IN (SELECT node_id FROM h{STEPS}) AS still_hot FROM t{STEPS}"))
def frontier_k10(spark, sf_dir):
    run = update(spark, sf_dir, deletes=False).run
    hot = run.hot.select("node_id", F.lit(True).alias("still_hot"))
    return run.state.join(hot, "node_id", "left").select("node_id", "f", F.coalesce("still_hot", F.lit(False)).alias("still_hot"))


@query("frontier_k3_distributed", sql.update_sql(True, True, 3, DELTA, "SELECT node_id, f FROM t3"))
def frontier_k3_distributed(spark, sf_dir):
    return update(spark, sf_dir, steps=3, plan="sync").run.state.select("node_id", "f")


@query("initial_frontier", sql.update_sql(True, True, 0, DELTA, "SELECT node_id FROM h0"))
def initial_frontier_query(spark, sf_dir):
    up = update(spark, sf_dir, steps=0)
    state, _ = propagate.free_state(up.graph)
    return up.affected.join(state.filter("w_all > 0"), "node_id", "left_semi")


_LABELS = f"SELECT node_id, f FROM t{STEPS}"


@query("frontier_commit_small", sql.update_sql(True, True, STEPS, DELTA, _LABELS, commit_small=True))
def frontier_commit_small(spark, sf_dir):
    return update(spark, sf_dir, commit_small=True).run.state.select("node_id", "f")


@query("frontier_two_phase", sql.update_sql(True, True, STEPS, DELTA, _LABELS, schedule="two_phase"))
def frontier_two_phase(spark, sf_dir):
    return update(spark, sf_dir, schedule="two_phase").run.state.select("node_id", "f")


@query("frontier_two_phase_distributed", sql.update_sql(True, True, 2, DELTA, "SELECT node_id, f FROM t2", schedule="two_phase"))
def frontier_two_phase_distributed(spark, sf_dir):
    return update(spark, sf_dir, steps=2, schedule="two_phase", plan="sync").run.state.select("node_id", "f")


@query("frontier_tau_gates_graph", sql.update_sql(True, True, STEPS, DELTA, _LABELS, gates=True))
def frontier_tau_gates_graph(spark, sf_dir):
    return update(spark, sf_dir, tau_gates_graph=True).run.state.select("node_id", "f")


@query("frontier_converged")
def frontier_converged(spark, sf_dir):
    """The finished update as classes, with whether a label is unique."""
    up = update(spark, sf_dir, steps=100_000)
    flags = reached(up.graph)
    return propagate.classify(up.run.state).join(flags, "node_id").select("node_id", "f", "class", "reached")


@query("entry_summary")
def entry_summary(spark, sf_dir):
    """Flagship: an update of the order-part graph, by class and reach: nodes, agreement with the harmonic solution, supersteps, updates."""
    up = update(spark, sf_dir, steps=100_000)
    ref = harmonic.harmonic_cg(up.graph).select("node_id", F.col("label").alias("ref"))
    rows = propagate.classify(up.run.state).join(ref, "node_id").join(reached(up.graph), "node_id")
    agree = F.avg(((F.col("f") >= HALF) == (F.col("ref") >= 0.5 - 1e-9)).cast("double"))
    return rows.groupBy("class", "reached").agg(F.count("*").alias("n"), F.round(agree, 4).alias("accuracy"), F.lit(up.run.iterations).alias("supersteps"), F.lit(up.run.updates).alias("updates"))


# ---- baselines ------------------------------------------------------------------------------------------------------


def seeded(g: SimilarityGraph, frac: float = 0.1, salt: int = 1) -> SimilarityGraph:
    """The graph with the known labels of a share of nodes only."""
    seeds = graph.choose_seeds(g.nodes, frac=frac, salt=salt).select("node_id", F.col("truth").alias("seed"))
    return SimilarityGraph(materialise(g.nodes.join(seeds, "node_id", "left").select("node_id", F.col("seed").alias("truth")), "nodes"), g.arcs)


def random_graph(spark: SparkSession, n: int, degree: int = 5, frac: float = 0.1) -> SimilarityGraph:
    """Random graph of n nodes; a share of them labelled by the parity of a hash."""
    from labelflow.functions.hashing import with_hash

    edges = er_edges(spark, n, degree)
    nodes = with_hash(with_hash(spark.range(0, n).withColumnRenamed("id", "node_id"), "h", "node_id", 1), "y", "node_id", 9)
    truth = F.when(F.col("h") < int(P * frac), F.col("y") % 2).cast("int")
    return SimilarityGraph(materialise(nodes.select("node_id", truth.alias("truth")), "nodes"), materialise(graph.arcs_of(edges), "arcs"))


SMALL = 1_500


@query("harmonic_dense_small")
def harmonic_dense_small(spark, sf_dir):
    return harmonic.harmonic_dense(random_graph(spark, SMALL)).select("node_id", F.round("label", 6).alias("label"))


@query("harmonic_cg")
def harmonic_cg_query(spark, sf_dir):
    g, _ = order_part_graph(spark, sf_dir)
    return harmonic.harmonic_cg(g).select("node_id", F.round("label", 6).alias("label"))


@query("contracted_harmonic")
def contracted_harmonic(spark, sf_dir):
    return harmonic.harmonic_contracted(random_graph(spark, SMALL)).select("node_id", F.round("label", 6).alias("label"))


@query("recompute_update")
def recompute_update_query(spark, sf_dir):
    g = random_graph(spark, SMALL)
    dels = g.nodes.filter("node_id % 50 = 3").select("node_id")
    return harmonic.recompute_update(g, dels=dels)[1].select("node_id", F.round("label", 6).alias("label"))


@query("star_mesh_elimination", f"{_BASE}, x AS (SELECT min(node_id) AS x FROM nodes WHERE node_id % 2 = 1), st AS (SELECT dst, w FROM arcs, x WHERE src = x), al AS (SELECT src, dst, CAST(w AS DOUBLE) AS w FROM arcs, x WHERE src <> x AND dst <> x UNION ALL SELECT a.dst, b.dst, CAST(a.w AS DOUBLE) * b.w / (SELECT sum(w) FROM st) FROM st a, st b WHERE a.dst <> b.dst) SELECT src, dst, round(sum(w), 6) AS w FROM al GROUP BY src, dst")
def star_mesh_elimination(spark, sf_dir):
    g, _ = order_part_graph(spark, sf_dir)
    first = g.nodes.filter("node_id % 2 = 1").agg(F.min("node_id")).first()[0]
    return harmonic.eliminate(g.arcs, first).select("src", "dst", F.round("w", 6).alias("w"))


def _sparse(gamma, readout="raw"):
    return lambda spark, sf_dir: sparse_inverse.harmonic_sparse_inverse(random_graph(spark, SMALL), gamma, readout, 60).select("node_id", F.round("label", 6).alias("label"), "nonzero")


for _name, _gamma in (("g01", 0.1), ("g1", 1.0), ("g10", 10.0)):
    query(f"sparse_inverse_{_name}")(_sparse(_gamma))
query("sparse_inverse_ratio_g1")(_sparse(1.0, "ratio"))


@query("sparse_inverse_drop_tolerance")
def sparse_inverse_drop(spark, sf_dir):
    return sparse_inverse.drop_tolerance_inverse(random_graph(spark, SMALL), 1e-3).select("node_id", F.round("label", 6).alias("label"))


def vector_graph(spark: SparkSession, sf_dir: str, k: int = 5, frac: float = 0.1) -> tuple[SimilarityGraph, DataFrame, DataFrame]:
    """kNN graph of the embeddings, planted classes (sign of the first coordinate) shown for a share; features; all classes."""
    emb = read(spark, sf_dir, "embeddings")
    q = materialise(similarity.quantised(emb), "q")
    edges = materialise(similarity.knn_edges(similarity.dense_pairs(q), k), "knn")
    truth = emb.select(F.col("vec_id").alias("node_id"), F.when(F.col("embedding")[0] >= 0, 1).otherwise(0).alias("truth"))
    g = seeded(SimilarityGraph(truth, materialise(graph.arcs_of(edges), "arcs")), frac)
    return g, emb.select(F.col("vec_id").alias("node_id"), F.transform("embedding", lambda x: x.cast("double")).alias("x")), truth


@query("gcn_scores")
def gcn_scores(spark, sf_dir):
    g, x, _ = vector_graph(spark, sf_dir)
    return learners.gcn_two_layer(g, x, epochs=100).select("node_id", F.round("label", 4).alias("label"))


@query("neural_knn_scores")
def neural_knn_scores(spark, sf_dir):
    g, x, _ = vector_graph(spark, sf_dir)
    return learners.neural_knn(g, x).select("node_id", F.round("label", 4).alias("label"))


@query("majority_class", f"WITH {sql.NODES}, t AS (SELECT sum(truth) AS n1, count(truth) AS n FROM nodes WHERE truth IS NOT NULL) SELECT CASE WHEN n1 * 2 >= n THEN 1 ELSE 0 END AS class, round(CAST(greatest(n1, n - n1) AS DOUBLE) / n, 6) AS share FROM t")
def majority_class(spark, sf_dir):
    return learners.majority(graph.order_part(read(spark, sf_dir, "orders"), read(spark, sf_dir, "lineitem"))[0])


@query("sweep_warm_start")
def sweep_warm_start(spark, sf_dir):
    g, _ = order_part_graph(spark, sf_dir)
    state, arcs = propagate.free_state(seeded(g))
    first = propagate.full_sweep(state, arcs, 1e-2)
    return propagate.full_sweep(first.state, arcs, DELTA).state.select("node_id", "f")


@query("sweep_accelerated")
def sweep_accelerated(spark, sf_dir):
    g, _ = order_part_graph(spark, sf_dir)
    state, arcs = propagate.free_state(seeded(g))
    return propagate.full_sweep(state, arcs, DELTA, accel="cheby").state.select("node_id", "f")


@query("sweep_blocked")
def sweep_blocked(spark, sf_dir):
    g, _ = order_part_graph(spark, sf_dir)
    state, arcs = propagate.free_state(g)
    return propagate.full_sweep(state, arcs, 1e-3, plan="blocked", max_steps=20).state.select("node_id", "f")


# ---- measures -------------------------------------------------------------------------------------------------------

_ALL = f"al AS (SELECT node_id, truth * {SCALE} AS f FROM nodes WHERE truth IS NOT NULL UNION ALL SELECT node_id, f FROM s5)"


@query("energy_state", f"{_BASE}, {sql.sweeps(5)}, {_ALL} SELECT round(CAST(sum(CAST(a.f - b.f AS HUGEINT) * (a.f - b.f) * w) AS DOUBLE) / 2e18, 4) AS energy FROM edges JOIN al a ON a.node_id = u JOIN al b ON b.node_id = v")
def energy_state(spark, sf_dir):
    g, _, run = _swept(spark, sf_dir, 5)
    return measures.energy(g, run.state)


@query("residual_state", f"{_BASE}, {sql.sweeps(6)} SELECT max(abs(s6.f - s5.f)) AS max_residual, count(*) AS n FROM s5 JOIN s6 USING (node_id) WHERE s5.w_all > 0")
def residual_state(spark, sf_dir):
    _, arcs, run = _swept(spark, sf_dir, 5)
    return measures.residual(run.state, arcs)


_TWO = f"{_BASE}, {sql.sweeps(20)}, j AS (SELECT s2.node_id, s2.f, s20.f AS ref FROM s2 JOIN s20 USING (node_id))"


def _two(spark, sf_dir):
    a = _swept(spark, sf_dir, 2)[2].state
    return a, _swept(spark, sf_dir, 20)[2].state.select("node_id", F.col("f").alias("ref"))


@query("accuracy_vs_reference", f"{_TWO} SELECT count(*) AS predicted, count(*) FILTER (WHERE (f >= {HALF}) = (ref >= {HALF})) AS equal, round(CAST(count(*) FILTER (WHERE (f >= {HALF}) = (ref >= {HALF})) AS DOUBLE) / count(*), 6) AS accuracy, round(CAST(greatest(count(*) FILTER (WHERE ref >= {HALF}), count(*) FILTER (WHERE ref < {HALF})) AS DOUBLE) / count(*), 6) AS majority FROM j")
def accuracy_vs_reference(spark, sf_dir):
    return measures.accuracy_vs(*_two(spark, sf_dir))


@query("label_error", f"{_TWO} SELECT max(abs(f - ref)) AS max_error, CAST(sum(abs(f - ref)) AS BIGINT) AS sum_error, count(*) AS n FROM j")
def label_error(spark, sf_dir):
    return measures.label_error(*_two(spark, sf_dir))


@query("confusion_matrix", f"{_TWO} SELECT CAST(ref >= {HALF} AS INT) AS actual, count(*) FILTER (WHERE f < {HALF}) AS predicted_0, count(*) FILTER (WHERE f >= {HALF}) AS predicted_1 FROM j GROUP BY 1")
def confusion_matrix(spark, sf_dir):
    return measures.confusion(*_two(spark, sf_dir))


@query("precision_recall", f"{_TWO}, t AS (SELECT count(*) FILTER (WHERE f >= {HALF} AND ref >= {HALF}) AS tp, count(*) FILTER (WHERE f >= {HALF} AND ref < {HALF}) AS fp, count(*) FILTER (WHERE f < {HALF} AND ref >= {HALF}) AS fn FROM j), r AS (SELECT CAST(tp AS DOUBLE) / (tp + fp) AS p, CAST(tp AS DOUBLE) / (tp + fn) AS r FROM t) SELECT round(p, 6) AS precision, round(r, 6) AS recall, round(2 * p * r / (p + r), 6) AS f1 FROM r")
def precision_recall(spark, sf_dir):
    return measures.precision_recall(measures.confusion(*_two(spark, sf_dir)))


_SIZES = f"{_TAU.split(', tau AS')[0]}, {sql.NODES}, z AS (SELECT (SELECT count(*) FROM nodes) AS n, (SELECT count(*) FROM edges) AS m)"


@query("method_matrix", f"{_SIZES} SELECT t.*, n AS nodes, m AS edges, CAST(CASE WHEN method = 'harmonic_contracted' THEN 8 * n * n WHEN method = 'gcn' THEN 8 * n * 512 ELSE 40 * n + 48 * m END AS BIGINT) AS bytes FROM (VALUES ('full_sweep', true, false, false, false, 'dense', 'compression'), ('gcn', true, false, true, false, 'dense', 'compression'), ('neural_knn', true, false, true, false, 'sparse', 'knn'), ('harmonic_contracted', true, true, true, false, 'dense', 'none'), ('harmonic_sparse_inverse', true, true, true, false, 'dense', 'sparse_inverse'), ('frontier', true, true, true, true, 'sparse', 'csr')) t(method, incremental, decremental, parallel, label_update, target_graph, memory), z")
def method_matrix(spark, sf_dir):
    nodes, edges = graph.order_part(read(spark, sf_dir, "orders"), read(spark, sf_dir, "lineitem"))
    return measures.method_matrix(nodes, edges)


@query("capacity_formula", f"{_SIZES} SELECT method, CAST(CASE WHEN dense THEN floor(sqrt(80000000000 / 8)) ELSE floor(80000000000 / (40 + 48 * CAST(m AS DOUBLE) / n)) END AS BIGINT) AS max_nodes, n AS nodes FROM (VALUES ('full_sweep', false), ('frontier', false), ('harmonic_exact', true), ('harmonic_contracted', true)) t(method, dense), z")
def capacity_formula(spark, sf_dir):
    nodes, edges = graph.order_part(read(spark, sf_dir, "orders"), read(spark, sf_dir, "lineitem"))
    return measures.capacity_table(nodes, edges)


# ---- graphs, seeds, batches -----------------------------------------------------------------------------------------


def _er(degree):
    m = f"(SELECT count(*) * {degree} // 2 FROM orders)"
    draws = hash_sql(hash_sql(hash_sql(f"(SELECT unnest(range(0, {m})) AS id)", "id", 1, "a"), "id", 2, "b"), "id", 5, "c")
    text = f"WITH n AS (SELECT count(*) AS n FROM orders), d AS (SELECT a % n AS a, b % n AS b, 1 + c % 1000 AS w FROM {draws}, n) SELECT least(a, b) AS u, greatest(a, b) AS v, max(w) AS w FROM d WHERE a <> b GROUP BY 1, 2"
    return text, lambda spark, sf_dir: er_edges(spark, read(spark, sf_dir, "orders").count(), degree)


for _d in (3, 5, 7):
    query(f"er_graph_deg{_d}", _er(_d)[0])(_er(_d)[1])


@query("source_er_graph", _er(3)[0])
def source_er_graph(spark, sf_dir):
    from labelflow.sources.random_graph import register

    register(spark)
    rows = spark.read.format("er_graph").option("nodes", read(spark, sf_dir, "orders").count()).option("degree", 3).load()
    return rows.groupBy("u", "v").agg(F.max("w").alias("w"))


def _knn_sql(k):
    return f"""WITH q AS (SELECT vec_id, list_transform(embedding, lambda x: CAST(floor(CAST(x AS DOUBLE) * 1000 + 0.5) AS BIGINT)) AS q FROM embeddings),
p AS (SELECT a.vec_id AS u, b.vec_id AS v, CAST(list_dot_product(list_transform(a.q, lambda x: CAST(x AS DOUBLE)), list_transform(b.q, lambda x: CAST(x AS DOUBLE))) AS BIGINT) AS sim FROM q a JOIN q b ON a.vec_id <> b.vec_id),
t AS (SELECT * FROM (SELECT *, row_number() OVER (PARTITION BY u ORDER BY sim DESC, v) AS place FROM p) WHERE place <= {k} AND sim > 0)"""


def _knn(k, symmetrise):
    return lambda spark, sf_dir: similarity.knn_edges(similarity.dense_pairs(materialise(similarity.quantised(read(spark, sf_dir, "embeddings")), "q")), k, symmetrise)


for _k in (3, 5, 7):
    query(f"knn_embeddings_k{_k}", f"{_knn_sql(_k)} SELECT least(u, v) AS u, greatest(u, v) AS v, max(sim) AS w FROM t GROUP BY 1, 2")(_knn(_k, "union"))
query("knn_embeddings_mutual", f"{_knn_sql(5)} SELECT least(u, v) AS u, greatest(u, v) AS v, max(sim) AS w FROM t GROUP BY 1, 2 HAVING count(*) = 2")(_knn(5, "mutual"))


@query("knn_topk", f"{_knn_sql(5)} SELECT u, v, sim FROM (SELECT *, row_number() OVER (PARTITION BY u ORDER BY sim DESC, v) AS r FROM p) WHERE r <= 5")
def knn_topk(spark, sf_dir):
    return similarity.knn(similarity.dense_pairs(materialise(similarity.quantised(read(spark, sf_dir, "embeddings")), "q")), 5)


@query("eps_neighbours_exact", f"{_knn_sql(5)} SELECT least(u, v) AS u, greatest(u, v) AS v, max(sim) AS w FROM p WHERE sim > 300000 GROUP BY 1, 2")
def eps_neighbours_exact(spark, sf_dir):
    return similarity.eps_edges(similarity.dense_pairs(materialise(similarity.quantised(read(spark, sf_dir, "embeddings")), "q")), 300000)


@query("knn_lsh")
def knn_lsh(spark, sf_dir):
    return similarity.lsh_knn(materialise(similarity.quantised(read(spark, sf_dir, "embeddings")), "q"), 5, planes=3, tables=16)


@query("knn_of_inserts", f"{_knn_sql(5)}, i AS (SELECT * FROM t WHERE u % 5 = 0) SELECT least(u, v) AS u, greatest(u, v) AS v, max(sim) AS w FROM i GROUP BY 1, 2")
def knn_of_inserts(spark, sf_dir):
    q = materialise(similarity.quantised(read(spark, sf_dir, "embeddings")), "q")
    return similarity.insert_knn(q.filter("node_id % 5 != 0"), q.filter("node_id % 5 = 0"), 5)


_TFIDF = r"""WITH w AS (SELECT doc_id, unnest(regexp_extract_all(lower(text), '[^\x00-\x2F\x3A-\x40\x5B-\x60\x7B-\x7F]+')) AS term FROM documents),
tf AS (SELECT doc_id, term, count(*) AS tf FROM w GROUP BY 1, 2), n AS (SELECT count(*) AS n FROM documents), df AS (SELECT term, count(*) AS df FROM tf GROUP BY term HAVING count(*) >= 2),
x AS (SELECT doc_id, term, tf * ln(CAST(n + 1 AS DOUBLE) / (df + 1)) AS x FROM tf JOIN df USING (term), n), nz AS (SELECT * FROM x WHERE x > 0), m AS (SELECT doc_id, sqrt(sum(x * x)) AS norm FROM nz GROUP BY doc_id)"""


@query("tfidf_terms", f"{_TFIDF} SELECT doc_id AS node_id, term, round(x / norm, 6) AS weight FROM nz JOIN m USING (doc_id)")
def tfidf_terms(spark, sf_dir):
    return similarity.tfidf(read(spark, sf_dir, "documents")).select("node_id", "term", F.round("weight", 6).alias("weight"))


def text_graph(spark: SparkSession, sf_dir: str, k: int = 5, frac: float = 0.1) -> tuple[SimilarityGraph, DataFrame]:
    """kNN graph of documents by the cosine over all their terms; class 1 is English, shown for a share; and all classes."""
    docs = read(spark, sf_dir, "documents")
    terms = materialise(similarity.tfidf(docs.select("doc_id", "text")), "tfidf")
    edges = similarity.knn_edges(materialise(similarity.cosine_knn(terms, k), "pairs"), k)
    truth = docs.select(F.col("doc_id").alias("node_id"), graph.one_vs_rest(F.col("lang"), "en").alias("truth"))
    return seeded(SimilarityGraph(truth, materialise(graph.arcs_of(edges), "arcs")), frac), truth


@query("tfidf_knn_docs")
def tfidf_knn_docs(spark, sf_dir):
    return text_graph(spark, sf_dir)[0].arcs.filter("src < dst").select(F.col("src").alias("u"), F.col("dst").alias("v"), "w")


@query("tfidf_hashed")
def tfidf_hashed(spark, sf_dir):
    from pyspark.ml.functions import vector_to_array

    return similarity.hashed_tfidf(read(spark, sf_dir, "documents"), features=1 << 10).select("node_id", F.round(F.aggregate(vector_to_array("features"), F.lit(0.0), lambda a, x: a + x * x), 6).alias("norm"))


_KNOWN = f"kn AS (SELECT * FROM {hash_sql('(SELECT * FROM nodes WHERE truth IS NOT NULL)', 'node_id', 1)})"


@query("choose_seeds_fraction", f"WITH {sql.NODES}, {_KNOWN} SELECT node_id, truth FROM kn WHERE h < {int(P * 0.01)}")
def choose_seeds_fraction(spark, sf_dir):
    return graph.choose_seeds(graph.order_part(read(spark, sf_dir, "orders"), read(spark, sf_dir, "lineitem"))[0], frac=0.01)


@query("choose_seeds_count", f"WITH {sql.NODES}, {_KNOWN} SELECT node_id, truth FROM kn ORDER BY h, node_id LIMIT 100")
def choose_seeds_count(spark, sf_dir):
    return graph.choose_seeds(graph.order_part(read(spark, sf_dir, "orders"), read(spark, sf_dir, "lineitem"))[0], n=100)


@query("choose_seeds_per_class", f"WITH {sql.NODES}, {_KNOWN} SELECT node_id, truth FROM (SELECT *, row_number() OVER (PARTITION BY truth ORDER BY h, node_id) AS r FROM kn) WHERE r <= 40")
def choose_seeds_per_class(spark, sf_dir):
    return graph.choose_seeds(graph.order_part(read(spark, sf_dir, "orders"), read(spark, sf_dir, "lineitem"))[0], per_class=40)


@query("balanced_sample", f"SELECT doc_id, lang FROM (SELECT *, row_number() OVER (PARTITION BY lang ORDER BY h, doc_id) AS r FROM {hash_sql('documents', 'doc_id', 1)}) WHERE r <= 20")
def balanced_sample(spark, sf_dir):
    return graph.balanced_sample(read(spark, sf_dir, "documents").select("doc_id", "lang"), "doc_id", "lang", 20)


_CUT = round(1_000_000 * 0.01 / 0.91)
_DEL = round(1_000_000 * 0.09 / 0.91 / graph.DRAWS)


_DRAWN = "\n".join(f"UNION ALL SELECT CAST(batch_id + 1 + t % (9 - batch_id) AS INT), 'del', node_id, NULL FROM {hash_sql(hash_sql('r', 'node_id', 5 + 2 * k, 'x'), 'node_id', 6 + 2 * k, 't')} WHERE batch_id < 9 AND x % 1000000 < {_DEL}" for k in range(graph.DRAWS))


@query("make_batches_90_1_9", f"WITH {sql.NODES}, r AS (SELECT *, CAST(h % 10 AS INT) AS batch_id FROM {hash_sql(hash_sql('nodes', 'node_id', 3), 'node_id', 4, 'h2')}) SELECT batch_id, 'ins' AS op, node_id, CASE WHEN h2 % 1000000 < {_CUT} THEN truth END AS truth FROM r {_DRAWN}")
def make_batches(spark, sf_dir):
    return graph.make_batches(graph.order_part(read(spark, sf_dir, "orders"), read(spark, sf_dir, "lineitem"))[0], 10)


@query("reached_flags", f"WITH RECURSIVE {sql.EDGES}, {sql.NODES}, {sql.arcs()}, {sql.components('nodes', 'arcs')} SELECT node_id, comp_id IN (SELECT comp_id FROM cc JOIN nodes USING (node_id) WHERE truth IS NOT NULL) AS reached FROM cc")
def reached_flags(spark, sf_dir):
    return reached(order_part_graph(spark, sf_dir)[0])


