"""Rows of two workloads against known answers: the toy components, and the sizes of the stand-in datasets counted in DuckDB."""

from __future__ import annotations

import duckdb

from labelflow import workload_queries as w

SF = "/root/testdata/sf0.001"


def test_toy_components(spark):
    got = {(r.tau, r.node_id): r.comp_id for r in w.w15_toy_components(spark, SF).collect()}
    # an edge whose weight equals the threshold goes, so 9-10 of weight 3 stays at 1 and only 8-9 of weight 9 at 5
    assert got == {(5, 8): 8, (5, 9): 8, (5, 10): 10, (1, 8): 8, (1, 9): 8, (1, 10): 8}


def test_dataset_sizes(spark):
    got = {r.dataset: r for r in w.w17_dataset_summary(spark, SF).collect()}
    con = duckdb.connect()
    count = lambda sql: con.execute(sql.replace("{", f"read_parquet('{SF}/").replace("}", ".parquet')")).fetchall()[0][0]
    assert set(got) == {"random", "order_part", "text", "vectors"}
    assert got["random"].nodes == count("select count(*) from {orders}")
    assert got["order_part"].nodes == count("select (select count(*) from {orders}) + (select count(*) from {part})")
    assert got["order_part"].edges == count("select count(*) from (select distinct l_orderkey, l_partkey from {lineitem})")
    assert got["text"].nodes == count("select count(distinct doc_id) from {documents}")
    assert got["vectors"].nodes == count("select count(distinct vec_id) from {embeddings}")
    # a union of five neighbours a node: no more edges than list entries
    for name in ("text", "vectors"):
        assert 0 < got[name].labelled <= got[name].nodes and got[name].edges <= 5 * got[name].nodes
    assert all(0 < r.labelled < r.nodes for r in got.values())
