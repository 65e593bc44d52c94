"""Graphs beyond the tail's bound: packed in one task, with the rows of the one-task update and no written stage a superstep."""

import sys
from dataclasses import replace

import numpy as np
import pyarrow as pa

from labelflow import core_queries
from labelflow.operators import components, frontier, harmonic, propagate
from labelflow.operators.graph import SimilarityGraph, arcs_of
from labelflow.plans import joins, local, packed, stage

SF = "/root/testdata/sf0.001"


def _beyond(monkeypatch, most: int) -> None:
    for module in (propagate, frontier):
        monkeypatch.setattr(module, "TAIL_ARCS", most)
    monkeypatch.setattr(components, "ONE_TASK_EDGES", most)


def test_entry_beyond_the_tail_is_as_in_one_task(spark, monkeypatch):
    expected = sorted(core_queries.entry_summary(spark, SF).collect())
    written = []

    def noted(df, label="stage", by=None):
        written.append(label)
        return real(df, label, by)

    real = stage.materialise
    for name, module in list(sys.modules.items()):
        if name.startswith("labelflow") and getattr(module, "materialise", None) is real:
            monkeypatch.setattr(module, "materialise", noted)
    _beyond(monkeypatch, 1_000)
    assert sorted(core_queries.entry_summary(spark, SF).collect()) == expected
    assert not {"sweep", "step", "ball", "cc-move"} & set(written), "a stage a superstep"
    assert written.count("seen") + written.count("weights") <= 4, "arcs are looked up once a graph"


def _islands(spark) -> SimilarityGraph:
    """Two components with truth, one without, and a node without arcs."""
    truth = {0: 0, 5: 1, 12: 1}
    nodes = spark.createDataFrame([(i, truth.get(i)) for i in range(25)], "node_id long, truth int")
    edges = [(i, i + 1, 1 + i % 3) for i in [*range(9), *range(10, 15), *range(16, 23)]] + [(16, 20, 2)]
    return SimilarityGraph(nodes, arcs_of(spark.createDataFrame(edges, "u long, v long, w long")))


def test_split_graph_reaches_the_same_nodes(spark, monkeypatch):
    g = _islands(spark)
    expected = sorted(frontier.reached(g).collect())
    assert [r.node_id for r in expected if not r.reached] == list(range(16, 25))
    labels = {r.node_id: r.label for r in harmonic.harmonic_cg(g).collect()}
    _beyond(monkeypatch, 20)
    parts = propagate.split(g, packing=True)
    assert parts.packed is not None
    assert sorted(frontier.reached(replace(g, split=parts)).collect()) == expected
    assert sorted(frontier.reached(replace(g, split=replace(parts, packed=None))).collect()) == expected
    far = {r.node_id: r.label for r in harmonic.harmonic_cg(replace(g, split=parts)).collect()}
    assert far.keys() == labels.keys() and all(abs(far[i] - labels[i]) < 1e-6 for i in labels)


def test_packed_loop_equals_the_tail(spark, monkeypatch):
    g = _islands(spark)
    state, arcs = propagate.free_state(g)
    hot = state.select("node_id")
    tails = [propagate.frontier_loop(state, arcs, hot, 1e-6, schedule=s) for s in ("sync", "two_phase")] + [propagate.full_sweep(state, arcs, 1e-5)]
    _beyond(monkeypatch, 20)
    p = propagate.split(g, packing=True).packed
    runs = [propagate.frontier_loop(state, arcs, hot, 1e-6, schedule=s, packed=p) for s in ("sync", "two_phase")] + [propagate.full_sweep(state, arcs, 1e-5, packed=p)]
    for run, tail in zip(runs, tails, strict=True):
        assert run.plan == "packed" and run.steps == tail.steps and run.converged == tail.converged
        assert sorted(run.state.collect()) == sorted(tail.state.collect())


def test_layout_in_pieces(monkeypatch):
    """Rows dealt over several blocks, spread a few arcs at a time, weights of eight bytes in one block."""
    monkeypatch.setattr(local, "PIECE", 3)
    rng = np.random.default_rng(7)
    ids, n = rng.permutation(np.arange(100, 160)), 60
    u, v = np.triu_indices(n, 1)
    pick = rng.random(len(u)) < 0.03
    u, v = u[pick], v[pick]
    w = rng.integers(1, 9, len(u))
    w[0] = 2**40
    s, d, ww = np.r_[u, v], np.r_[v, u], np.r_[w, w]
    blocks = [packed._unblob(pa.scalar(packed.arc_block(pa.table({"ps": s[i::3].astype(np.int32), "pd": d[i::3].astype(np.int32), "w": ww[i::3]})))) for i in range(3)]
    rows, plain, f = packed.lay_out(ids, blocks), local.Rows(ids, ids[s], ids[d], ww), rng.integers(0, 1000, n)
    assert (rows.sums(np.arange(n), f)[plain.order] == plain.sums(np.arange(n), f[plain.order])).all()
    assert np.allclose(rows.weighted(f / 7), np.bincount(s, ww * f[d] / 7, n))
    least = {r["node_id"]: r["comp_id"] for r in components.label_block(pa.table({"u": ids[u], "v": ids[v]})).to_pylist()}
    assert packed.components(rows).tolist() == [least.get(i, i) for i in ids.tolist()]


def test_salts_only_for_hubs(spark, monkeypatch):
    rows = spark.range(100).selectExpr("id as a", "id % 2 as b")
    monkeypatch.setattr(joins, "HUB_ROWS", 30)
    assert joins.salts_for(rows, "a") == 1
    assert joins.salts_for(rows, "a", "b") == joins.SALTS
