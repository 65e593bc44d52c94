"""Arriving points, accelerated sweeps, certainty weights, late rows and restarts."""

from __future__ import annotations

import os
import shutil

import numpy as np
import pytest
from pyspark.sql import functions as F

from labelflow.functions.fixed import SCALE
from labelflow.operators import graph, learners, propagate, similarity
from labelflow.operators.frontier import frontier_update, vector_update
from labelflow.operators.graph import SimilarityGraph
from labelflow.plans.local import Rows, sweep_steps
from labelflow.plans.stage import materialise, new_path
from labelflow.sources.store import GraphStore
from labelflow.streaming import events

SF = "/root/testdata/sf0.001"


@pytest.fixture(scope="module")
def vectors(spark):
    return materialise(similarity.quantised(spark.read.parquet(f"{SF}/embeddings.parquet")), "q")


def path_rows(n):
    """A path whose first end is tied to a known 1 and whose last to a known 0."""
    a = np.arange(n - 1)
    rows = Rows(np.arange(n), np.concatenate([a, a + 1]), np.concatenate([a + 1, a]), np.ones(2 * n - 2, np.int64))
    w1 = np.zeros(n, np.int64)
    w1[0] = 1
    return rows, np.full(n, SCALE // 2), w1, np.full(n, 2, np.int64)


@pytest.mark.parametrize("accel", ["cheby", 0.3, 0.99])
def test_accelerated_sweeps_end_at_the_harmonic_labels(accel):
    n = 60
    rows, f, w1, w_all = path_rows(n)
    plain = f.copy()
    slow = len(sweep_steps(rows, plain, w1, w_all, 10_000, 20_000))
    fast = len(sweep_steps(rows, f, w1, w_all, 10_000, 20_000, accel))
    want = SCALE * (1 - np.arange(1, n + 1) / (n + 1))
    assert max(np.abs(f - want).max(), np.abs(plain - want).max()) < 1e-2 * SCALE
    assert fast < slow / (1.02 if accel == 0.3 else 3)


def test_acceleration_refuses_a_radius_of_one():
    rows, f, w1, w_all = path_rows(5)
    with pytest.raises(ValueError, match="accel"):
        sweep_steps(rows, f, w1, w_all, 100, 10, 1.0)


def test_pseudo_labels_count_by_certainty(spark):
    known = spark.createDataFrame([(1, 1.0)], "node_id long, label double")
    labels = spark.createDataFrame([(2, SCALE), (3, 0), (4, SCALE // 2), (5, SCALE * 3 // 4), (6, None)], "node_id long, f long")
    got = {(r.node_id, r.label): r["count"] for r in learners.certain(known, labels).groupBy("node_id", "label").count().collect()}
    assert got == {(1, 1.0): 4, (2, 1.0): 4, (3, 0.0): 4, (5, 1.0): 2}


def test_lsh_of_the_registered_parameters(spark, vectors):
    exact = {(r.u, r.v) for r in similarity.knn(similarity.dense_pairs(vectors), 5).collect()}
    for rows in (2_000, 20):  # at 20 every bucket is dealt over salts
        found = [(r.u, r.v) for r in similarity.lsh_knn(vectors, 5, planes=3, tables=16, bucket_rows=rows).collect()]
        assert len(found) == len(set(found)) and len(exact & set(found)) >= 0.9 * len(exact)


def test_arriving_vectors_find_their_edges(spark, vectors):
    new, old = vectors.filter("node_id % 10 = 3"), vectors.filter("node_id % 10 <> 3")
    exact = {(r.u, r.v): r.w for r in similarity.insert_knn(old, new, 5).collect()}
    near = {(r.u, r.v): r.w for r in similarity.insert_knn(old, new, 5, "lsh").collect()}
    assert exact and len(exact.keys() & near.keys()) >= 0.9 * len(exact)
    assert all(u % 10 == 3 or v % 10 == 3 for u, v in near) and all(near[p] == exact[p] for p in near.keys() & exact.keys())
    with pytest.raises(ValueError, match="search"):
        similarity.insert_knn(old, new, 5, "guess")


def test_an_update_from_raw_vectors_is_the_update_with_their_edges(spark, vectors):
    new, old = vectors.filter("node_id % 10 = 3"), vectors.filter("node_id % 10 <> 3")
    truth = vectors.select("node_id", F.when(F.col("node_id") % 7 == 0, (F.col("node_id") % 2).cast("int")).alias("truth"))
    g = SimilarityGraph(truth.join(old, "node_id", "left_semi"), materialise(graph.arcs_of(similarity.knn_edges(similarity.dense_pairs(old), 5)), "arcs"))
    labels = propagate.full_sweep(*propagate.free_state(g), 1e-4).state
    by_points = vector_update(g, labels, old, new, truth, 5)
    by_edges = frontier_update(g, labels, truth.join(new, "node_id", "left_semi"), similarity.insert_knn(old, new, 5))
    got, want = ({r.node_id: r.f for r in u.run.state.collect()} for u in (by_points, by_edges))
    assert got == want and any(i % 10 == 3 for i in got)


def test_late_rows_take_the_side_path(spark):
    path = events.staged(spark, SF, 4, tardy="event_id % 7 = 0")
    out = events.split_late(events.stream(spark, path))
    rows = spark.read.parquet(f"{out}/rows")
    every = spark.read.parquet(path)
    assert rows.count() == every.count() and rows.filter("late").count() > 0
    assert rows.filter("late and event_id % 7 <> 0").count() == 0
    newest = every.agg(F.max("ts")).first()[0]
    want = {r.day: r.n for r in every.groupBy(F.date_trunc("day", "ts").alias("day")).agg(F.count("*").alias("n")).filter(F.col("day") + F.expr("INTERVAL 2 DAY") <= F.lit(newest)).collect()}
    got = events.late_corrected(spark, out).collect()
    assert {r.day: r.n + r.n_late for r in got} == want and sum(r.n_late for r in got) == rows.filter("late").count()


def test_live_labels_survive_a_restart(spark):
    path = events.staged(spark, SF, 3).removeprefix("file://")
    files = sorted((f for f in os.listdir(path) if f.endswith(".parquet")), key=lambda f: os.stat(f"{path}/{f}").st_mtime_ns)
    truth = spark.read.parquet(f"{SF}/events.parquet").select("user_id").distinct().filter("user_id % 5 = 0").select("user_id", (F.col("user_id") % 2).cast("int").alias("truth"))
    whole = {r.node_id: r.f for r in events.live_labels(events.stream(spark, path), truth).collect()}
    part, store, mark = new_path(spark, "restart").removeprefix("file://"), GraphStore(spark), new_path(spark, "restart-log")
    os.makedirs(part)
    seen = []
    for some in (files[:2], files[2:]):
        for f in some:
            shutil.copy2(f"{path}/{f}", part)
        seen.append({r.node_id: r.f for r in events.live_labels(events.stream(spark, part), truth, store=store, mark=mark).collect()})
    assert len(files) == 3 and seen[0] != whole and seen[1] == whole
    replay = store.nodes(before=2).count(), store.nodes().count()
    assert store.version() == 2 and replay[0] < replay[1]
