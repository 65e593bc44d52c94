"""Baselines, measures, graphs, store and streams."""

import numpy as np
import pytest
from pyspark.sql import functions as F

from labelflow import core_queries, surface_queries
from labelflow.functions.fixed import SCALE
from labelflow.functions.hashing import with_hash
from labelflow.operators import graph, harmonic, learners, measures, propagate, similarity, sparse_inverse
from labelflow.operators.graph import SimilarityGraph
from labelflow.sources.random_graph import _mixed, er_edges
from labelflow.sources.store import GraphStore
from labelflow.sources.tables import require_keys
from labelflow.streaming import events
from tests.test_propagate import dense, labels_of, random_graph
from tests.test_propagate import graph as make

SF = "/root/testdata/sf0.001"


@pytest.fixture(scope="module")
def connected(spark):
    """A connected graph, so that every label is unique."""
    truth, edges = random_graph(30, 80, 12)
    edges = {(a, b): w for a, b, w in edges} | {(i, i + 1): 5 for i in range(29)}
    edges = [(a, b, w) for (a, b), w in edges.items()]
    return make(spark, truth, edges), truth, edges


def as_map(df):
    return {r.node_id: r.label for r in df.collect()}


def test_harmonic_methods_agree(spark, connected):
    g, truth, edges = connected
    want = dense(truth, edges)
    for got in (as_map(harmonic.harmonic_dense(g)), as_map(harmonic.harmonic_contracted(g)), as_map(harmonic.harmonic_cg(g, 1e-10)), as_map(harmonic.harmonic_cg(g, 1e-5, plan="distributed", max_rounds=12))):
        assert set(got) == set(want)
        assert max(abs(got[i] - want[i]) for i in want) < 2e-3


def test_elimination_keeps_the_others(spark, connected):
    g, truth, edges = connected
    gone = next(i for i in truth if truth[i] is None)
    mesh = harmonic.eliminate(g.arcs, gone).filter("src < dst").collect()
    left = {i: t for i, t in truth.items() if i != gone}
    place = {i: k for k, i in enumerate(left)}
    got = dense({place[i]: t for i, t in left.items()}, [(place[r.src], place[r.dst], r.w) for r in mesh])
    want = dense(truth, edges)
    assert max(abs(got[place[i]] - want[i]) for i in want if i != gone) < 1e-8


def test_sparse_inverse(spark, connected):
    g, truth, edges = connected
    want = dense(truth, edges)
    exact = as_map(sparse_inverse.harmonic_sparse_inverse(g, 0.0, "ratio", 3000))
    assert max(abs(exact[i] - want[i]) for i in want) < 0.02
    counts = [sum(r.nonzero for r in sparse_inverse.harmonic_sparse_inverse(g, x).collect()) for x in (0.1, 1.0, 10.0)]
    assert counts == sorted(counts, reverse=True) and counts[0] > counts[2]


def test_dense_methods_refuse_large_graphs(connected):
    with pytest.raises(harmonic.CapacityError):
        harmonic.harmonic_dense(connected[0], guard=5)


def test_learners_find_separable_classes(spark):
    rng = np.random.default_rng(1)
    n = 80
    x = [(i, [float(v) for v in rng.normal(1.5 if i % 2 else -1.5, 1, 6)]) for i in range(n)]
    features = spark.createDataFrame(x, "node_id long, x array<double>")
    q = features.select("node_id", F.transform("x", lambda v: F.floor(v * 1000 + 0.5).cast("long")).alias("q"))
    edges = similarity.knn_edges(similarity.dense_pairs(q), 5)
    nodes = spark.createDataFrame([(i, i % 2 if i < 16 else None) for i in range(n)], "node_id long, truth int")
    g = SimilarityGraph(nodes, graph.arcs_of(edges))
    for got in (as_map(learners.gcn_two_layer(g, features, hidden=16, epochs=60)), as_map(learners.neural_knn(g, features, rounds=1, max_iter=20))):
        assert sum((p >= 0.5) == (i % 2 == 1) for i, p in got.items()) > 0.9 * len(got)


def test_random_graph_rule_and_mean_degree(spark):
    h = {r.id: r.h for r in with_hash(spark.range(20), "h", "id", 5).collect()}
    assert h == {i: _mixed(i, 5) for i in range(20)}
    e = er_edges(spark, 4000, 5)
    assert abs(2 * e.count() / 4000 - 5) < 0.1
    degrees = graph.weighted_degree(graph.arcs_of(e)).agg(F.variance("degree")).first()[0]
    assert 3.0 < degrees < 6.0  # a linear hash would give 0.5


def test_approximate_neighbours_recall(spark):
    q = core_queries.materialise(similarity.quantised(spark.read.parquet(f"{SF}/embeddings.parquet")), "q")
    exact = {(r.u, r.v) for r in similarity.knn(similarity.dense_pairs(q), 5).collect()}
    found = {(r.u, r.v) for r in similarity.lsh_knn(q, 5, planes=3, tables=24).collect()}
    assert len(exact & found) >= 0.9 * len(exact)


def test_batches_keep_the_mix(spark):
    nodes = spark.range(20_000).select(F.col("id").alias("node_id"), (F.col("id") % 2).cast("int").alias("truth"))
    b = {(r.op, r.known): r["count"] for r in graph.make_batches(nodes, 20).withColumn("known", F.col("truth").isNotNull()).groupBy("op", "known").count().collect()}
    total = sum(b.values())
    assert abs(b[("ins", False)] / total - 0.90) < 0.02 and abs(b[("ins", True)] / total - 0.01) < 0.004 and abs(b[("del", False)] / total - 0.09) < 0.02


def test_measures(spark):
    state = spark.createDataFrame([(1, SCALE), (2, 0), (3, SCALE // 2), (4, 10)], "node_id long, f long")
    ref = spark.createDataFrame([(1, SCALE), (2, SCALE), (3, SCALE // 2), (4, 0)], "node_id long, ref long")
    r = measures.accuracy_vs(state, ref).first()
    assert (r.predicted, r.equal, r.accuracy, r.majority) == (4, 3, 0.75, 0.75)
    assert tuple(measures.precision_recall(measures.confusion(state, ref)).first()) == (1.0, 0.666667, 0.8)
    assert measures.state_bytes("harmonic_exact", 1000, 0) == 8_000_000


def test_store_versions_tombstones_and_compaction(spark):
    store = GraphStore(spark)
    nodes = lambda rows: spark.createDataFrame(rows, "node_id long, truth int")
    arcs = lambda rows: spark.createDataFrame([x for a, b, w in rows for x in ((a, b, w), (b, a, w))], "src long, dst long, w long")
    store.append(1, nodes([(1, 0), (2, None), (3, 1)]), arcs([(1, 2, 5), (2, 3, 7)]))
    store.append(2, None, None, nodes([(3, None)]))
    store.append(3, nodes([(3, None)]), arcs([(1, 3, 2)]))
    store.append(3, nodes([(3, None)]), arcs([(1, 3, 2)]))  # a replay
    for _ in range(2):
        assert {(r.node_id, r.truth) for r in store.nodes().collect()} == {(1, 0), (2, None), (3, None)}
        assert {(r.src, r.dst, r.w) for r in store.arcs().filter("src < dst").collect()} == {(1, 2, 5), (1, 3, 2)}
        store.compact(4)
    store.commit(7, nodes([(1, 1)]))
    assert store.version() == 7 and store.state().count() == 1


def test_null_keys_are_refused(spark):
    with pytest.raises(Exception, match="null key"):
        require_keys(spark.createDataFrame([(None, 1)], "node_id long, x int"), "node_id").collect()


def test_late_days_stay_open(spark):
    path = events.staged(spark, SF, 3)
    days = {r.day for r in events.finish(events.late_changes(events.stream(spark, path))).collect()}
    every = {r.d for r in spark.read.parquet(path).select(F.date_trunc("day", "ts").alias("d")).distinct().collect()}
    assert days < every and max(every) not in days


def test_live_labels_of_a_stream(spark):
    rows = surface_queries.stream_live_labels(spark, SF).collect()
    assert rows and all(0 <= r.f <= SCALE for r in rows)


def test_labels_of_helper(spark, connected):
    g, truth, edges = connected
    state, arcs = propagate.free_state(g)
    assert set(labels_of(propagate.full_sweep(state, arcs, 1e-3))) == {i for i in truth if truth[i] is None}
