"""What the distributed frontier keeps: arcs in folders, changed labels beside the state; inserts of live nodes; repeated deletions."""

import pytest
from pyspark.sql import functions as F

from labelflow.operators import graph, propagate
from labelflow.operators.frontier import frontier_update
from labelflow.operators.graph import SimilarityGraph


def path(spark, n, truth):
    nodes = spark.createDataFrame([(i, truth.get(i)) for i in range(n)], "node_id long, truth int")
    return SimilarityGraph(nodes, graph.arcs_of(spark.createDataFrame([(i, i + 1, 2) for i in range(n - 1)], "u long, v long, w long")))


def test_arcs_are_read_by_folder(spark, monkeypatch):
    monkeypatch.setattr(propagate, "ARCS_PER_BUCKET", 4)
    g = path(spark, 40, {})
    stored = propagate.Bucketed(g.arcs, g.arcs.count())
    hot = spark.createDataFrame([(7,)], "node_id long")
    some = stored.of(hot)
    assert stored.buckets > 8 and some.filter("src = 7").count() == 2
    assert some.count() < g.arcs.count() / 2
    assert some.select(F.input_file_name()).distinct().count() == 1 and "PartitionFilters: []" not in some._jdf.queryExecution().toString()


def test_changes_are_merged_and_plans_agree(spark, monkeypatch):
    g = path(spark, 30, {0: 0, 29: 1})
    state, arcs = propagate.free_state(g)
    hot = state.select("node_id")
    want = {r.node_id: r.f for r in propagate.frontier_loop(state, arcs, hot, 1e-2, "tail").state.collect()}
    monkeypatch.setattr(propagate, "MOST_CHANGES", 5)
    run = propagate.frontier_loop(state, arcs, hot, 1e-2, "sync")
    assert {r.node_id: r.f for r in run.state.collect()} == want
    assert run.steps[0][2] == arcs.count() and run.arcs_touched > 0


@pytest.mark.parametrize("plan", ["auto", "sync"])
def test_an_insert_of_a_live_node_sets_its_truth(spark, plan):
    g = path(spark, 4, {0: 0})
    ins = spark.createDataFrame([(3, 1), (0, None), (9, None)], "node_id long, truth int")
    edges = spark.createDataFrame([(3, 9, 2)], "u long, v long, w long")
    up = frontier_update(g, None, ins, edges, delta=1e-6, plan=plan)
    assert {r.node_id: r.truth for r in up.graph.nodes.collect()} == {0: 0, 1: None, 2: None, 3: 1, 9: None}
    f = {r.node_id: r.f / propagate.SCALE for r in up.run.state.collect()}
    assert f == {1: pytest.approx(1 / 3, abs=1e-4), 2: pytest.approx(2 / 3, abs=1e-4), 9: 1.0}


def test_a_node_may_be_deleted_by_two_batches(spark):
    nodes = spark.range(4000).select(F.col("id").alias("node_id"), F.lit(1).alias("truth"))
    dels = graph.make_batches(nodes, 10).filter("op = 'del'").groupBy("node_id").agg(F.countDistinct("batch_id").alias("n"))
    assert dels.filter("n > 1").count() > 0
