"""Propagation against closed forms, dense solutions and across plans."""

import numpy as np
import pytest

from labelflow.functions.fixed import SCALE
from labelflow.operators import components, propagate
from labelflow.operators.classweights import initial_labels
from labelflow.operators.frontier import frontier_update, reached
from labelflow.operators.graph import SimilarityGraph, arcs_of


def graph(spark, truth, edges):
    nodes = spark.createDataFrame(list(truth.items()), "node_id long, truth int")
    return SimilarityGraph(nodes, arcs_of(spark.createDataFrame(edges, "u long, v long, w long")))


def chain(spark, n):
    truth = {i: None for i in range(n)} | {0: 0, n - 1: 1}
    return graph(spark, truth, [(i, i + 1, 1) for i in range(n - 1)])


def labels_of(run):
    return {r.node_id: r.f / SCALE for r in run.state.collect()}


def random_graph(n=60, m=150, seed=3):
    rng = np.random.default_rng(seed)
    edges = {(min(a, b), max(a, b)): int(rng.integers(1, 50)) for a, b in rng.integers(0, n, (m, 2)).tolist() if a != b}
    truth = {i: (None if i % 7 else int(rng.integers(0, 2))) for i in range(n)}
    return truth, [(a, b, w) for (a, b), w in edges.items()]


def dense(truth, edges):
    n = len(truth)
    w = np.zeros((n, n))
    for a, b, x in edges:
        w[a, b] += x
        w[b, a] += x
    free = [i for i in truth if truth[i] is None and w[i].sum() > 0]
    known = [i for i in truth if truth[i] is not None]
    lap = np.diag(w.sum(1)) - w
    y = np.array([float(truth[i]) for i in known])
    sol = np.linalg.lstsq(lap[np.ix_(free, free)], w[np.ix_(free, known)] @ y, rcond=None)[0]
    return dict(zip(free, sol, strict=True))


@pytest.mark.parametrize("plan", ["tail", "sync"])
def test_chain_is_linear(spark, plan):
    g = chain(spark, 6)
    state, arcs = propagate.free_state(g)
    run = propagate.full_sweep(state, arcs, 1e-7 if plan == "tail" else 1e-2, plan=plan, max_steps=500)
    got = labels_of(run)
    for i in range(1, 5):
        assert abs(got[i] - i / 5) < (1e-5 if plan == "tail" else 0.1)
    assert run.converged


def test_plans_give_identical_labels(spark):
    truth, edges = random_graph()
    g = graph(spark, truth, edges)
    state, arcs = propagate.free_state(g)
    runs = [propagate.full_sweep(state, arcs, 0, plan=p, max_steps=6) for p in ("tail", "sync")]
    assert labels_of(runs[0]) == labels_of(runs[1])
    hot = state.select("node_id")
    loops = [propagate.frontier_loop(state, arcs, hot, 1e-2, plan=p, max_steps=5) for p in ("tail", "sync")]
    assert labels_of(loops[0]) == labels_of(loops[1])
    assert [s[:2] for s in loops[0].steps] == [s[:2] for s in loops[1].steps]
    forms = [propagate.relax(state, arcs, None, f).select("node_id", "new").collect() for f in ("average", "adjust")]
    assert sorted(forms[0]) == sorted(forms[1])


def test_ball_plan_is_the_sync_plan(spark, monkeypatch):
    """Where balls of some rings fit, a run in balls takes the steps of the sync plan; where none fits, it is the sync plan."""
    g = chain(spark, 24)
    state, arcs = propagate.free_state(g)
    hot = spark.createDataFrame([(1,), (22,)], "node_id long")
    want = propagate.frontier_loop(state, arcs, hot, 1e-2, plan="sync", max_steps=4)
    for most, plan in ((12, "ball"), (1, "sync")):
        monkeypatch.setattr(propagate, "TAIL_ARCS", most)
        got = propagate.frontier_loop(state, arcs, hot, 1e-2, max_steps=4)
        assert labels_of(got) == labels_of(want)
        assert [s[:2] for s in got.steps] == [s[:2] for s in want.steps]
        assert plan in got.plan and got.converged == want.converged


def test_ball_plan_runs_to_the_end(spark, monkeypatch):
    truth, edges = random_graph()
    g = graph(spark, truth, edges)
    state, arcs = propagate.free_state(g)
    hot = state.select("node_id").orderBy("node_id").limit(2)
    want = propagate.frontier_loop(state, arcs, hot, 5e-2)
    assert want.plan == "tail"
    monkeypatch.setattr(propagate, "TAIL_ARCS", arcs.count() - 1)
    got = propagate.frontier_loop(state, arcs, hot, 5e-2)
    assert got.plan != "tail" and got.converged == want.converged
    assert labels_of(got) == labels_of(want) and [s[:2] for s in got.steps] == [s[:2] for s in want.steps]


def test_all_reach_the_harmonic_solution(spark):
    truth, edges = random_graph()
    g = graph(spark, truth, edges)
    want = dense(truth, edges)
    state, arcs = propagate.free_state(g)
    seen = {r.node_id for r in reached(g).filter("reached").collect()}
    for run in (propagate.full_sweep(state, arcs, 1e-9), propagate.frontier_loop(state, arcs, state, 1e-9), propagate.full_sweep(state, arcs, 1e-9, accel=0.3), propagate.frontier_loop(state, arcs, state, 1e-9, schedule="two_phase")):
        got = labels_of(run)
        assert run.converged
        assert max(abs(got[i] - want[i]) for i in want if i in seen) < 2e-3


def test_blocked_plan(spark):
    g = chain(spark, 9)
    state, arcs = propagate.free_state(g)
    run = propagate.full_sweep(state, arcs, 1e-3, plan="blocked", blocks=2, inner=100, max_steps=25, block_width=5)
    got = labels_of(run)
    assert run.converged and max(abs(got[i] - i / 8) for i in range(1, 8)) < 0.03


def test_residual_is_within_delta_and_labels_in_range(spark):
    truth, edges = random_graph(seed=9)
    g = graph(spark, truth, edges)
    state, arcs = propagate.free_state(g)
    run = propagate.frontier_loop(state, arcs, state, 1e-3)
    rows = propagate.relax(run.state, arcs).collect()
    assert all(r.new is None or abs(r.new - r.f) <= 1e-3 * SCALE for r in rows)
    assert all(0 <= r.f <= SCALE for r in rows)


def test_updates_match_a_rebuild(spark):
    truth, edges = random_graph(seed=5)
    new = {i for i in truth if i >= 45}
    old_g = graph(spark, {i: t for i, t in truth.items() if i not in new}, [e for e in edges if e[0] not in new and e[1] not in new])
    state, arcs = propagate.free_state(old_g)
    before = propagate.full_sweep(state, arcs, 1e-9)
    ins = spark.createDataFrame([(i, truth[i]) for i in new], "node_id long, truth int")
    ins_edges = spark.createDataFrame([e for e in edges if e[0] in new or e[1] in new], "u long, v long, w long")
    dels = spark.createDataFrame([(3,), (3,), (8,), (7,), (9999,)], "node_id long")
    up = frontier_update(old_g, before.state, ins, ins_edges, dels, delta=1e-9)
    gone = {3, 7, 8}
    left = {i: t for i, t in truth.items() if i not in gone}
    place = {i: k for k, i in enumerate(left)}
    want = dense({place[i]: t for i, t in left.items()}, [(place[a], place[b], w) for a, b, w in edges if a in left and b in left])
    got = labels_of(up.run)
    ok = {r.node_id for r in reached(up.graph).filter("reached").collect()}
    checked = [i for i in left if place[i] in want and i in ok]
    assert len(checked) > 30
    assert max(abs(got[i] - want[place[i]]) for i in checked) < 2e-3
    assert not set(got) & gone


def test_labels_also_go_down(spark):
    g = graph(spark, {0: 1, 1: None, 2: None}, [(0, 1, 1), (1, 2, 1)])
    state, arcs = propagate.free_state(g)
    before = propagate.full_sweep(state, arcs, 1e-9)
    up = frontier_update(g, before.state, spark.createDataFrame([(3, 0)], "node_id long, truth int"), spark.createDataFrame([(2, 3, 1)], "u long, v long, w long"), delta=1e-9)
    got = labels_of(up.run)
    assert abs(got[1] - 2 / 3) < 1e-5 and abs(got[2] - 1 / 3) < 1e-5


def test_component_labels(spark):
    nodes = spark.createDataFrame([(1, None), (2, None), (3, None), (10, 0), (11, 1)], "node_id long, truth int")
    arcs = arcs_of(spark.createDataFrame([(1, 2, 9), (1, 10, 3), (2, 11, 1)], "u long, v long, w long"))
    from labelflow.operators.classweights import contraction

    got = {r.node_id: r.f0 for r in initial_labels(nodes.filter("node_id < 4").select("node_id"), spark.createDataFrame([(1, 2)], "u long, v long"), contraction(arcs, nodes), nodes).collect()}
    assert got == {1: SCALE // 4, 2: SCALE // 4, 3: SCALE // 2}


def test_hook_and_jump_trace(spark):
    """Nodes 8, 9, 10 with weights 9, 3, 1: above 5 leaves {8, 9}, {10}; above 1 gives parents 8 8 9, then 8 8 8."""
    edges = spark.createDataFrame([(8, 9, 9), (9, 10, 3), (8, 10, 1)], "u long, v long, w long")
    nodes = spark.createDataFrame([(8,), (9,), (10,)], "node_id long")
    as_map = lambda df: {r[0]: r[1] for r in df.collect()}
    assert as_map(components.connected_components(edges.filter("w > 5"), nodes, "hook_jump")) == {8: 8, 9: 8, 10: 10}
    trace = []
    components.hook_jump(edges.filter("w > 1"), trace)
    assert as_map(trace[0]) == {8: 8, 9: 8, 10: 9}
    assert as_map(trace[1]) == {8: 8, 9: 8, 10: 8}


@pytest.mark.parametrize("method", ["hook_jump", "stars", "contract", "one_task", "auto"])
def test_components(spark, method):
    edges = spark.createDataFrame([(2, 9), (9, 1), (1, 8), (8, 0), (20, 21), (22, 21), (5, 5)], "u long, v long")
    nodes = spark.createDataFrame([(i,) for i in (0, 1, 2, 8, 9, 20, 21, 22, 30)], "node_id long")
    got = {r.node_id: r.comp_id for r in components.connected_components(edges, nodes, method).collect()}
    assert got == {0: 0, 1: 0, 2: 0, 8: 0, 9: 0, 20: 20, 21: 20, 22: 20, 30: 30}
    dense_ids = {r.comp_id: r.dense_id for r in components.densify(components.connected_components(edges, nodes, method)).collect()}
    assert dense_ids == {0: 0, 20: 1, 30: 2}
