"""Operators, sources, sinks and functions that users of the methods need, each as a query."""

from __future__ import annotations

import pandas as pd
from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F
from pyspark.sql import types as T

from labelflow import oracle_parts as sql
from labelflow.core_queries import _BASE, _SUB, _swept, fresh_ids, gone_ids, order_part_graph
from labelflow.functions.fixed import HALF, SCALE
from labelflow.operators import graph, propagate, similarity
from labelflow.operators.components import hook_jump
from labelflow.plans.stage import materialise, new_path
from labelflow.registry import query
from labelflow.sources.store import GraphStore
from labelflow.sources.tables import read, scan_nodes, schema_of
from labelflow.streaming import events as ev

# ---- scans and sources ----------------------------------------------------------------------------------------------

for _t, _c in (("documents", "SELECT doc_id AS node_id, CAST(lang = 'en' AS TINYINT) AS truth FROM documents"), ("orders", "SELECT o_orderkey AS node_id, CAST(CASE o_orderstatus WHEN 'F' THEN 0 WHEN 'O' THEN 1 END AS TINYINT) AS truth FROM orders"), ("embeddings", "SELECT vec_id AS node_id, CAST(embedding[1] >= 0 AS TINYINT) AS truth FROM embeddings"), ("pages", "SELECT page_id AS node_id, CAST(contains(url, '/en/') AS TINYINT) AS truth FROM pages")):
    query(f"scan_nodes_{_t}", _c)(lambda spark, sf_dir, t=_t: scan_nodes(spark, sf_dir, t))


def _written(df: DataFrame, kind: str) -> str:
    path = new_path(df.sparkSession, kind)
    getattr(df.write.option("header", True) if kind == "csv" else df.write, kind)(path)
    return path


@query("read_csv_edges", f"WITH {sql.EDGES} SELECT u, v, w FROM edges")
def read_csv_edges(spark, sf_dir):
    edges = graph.bipartite_edges(read(spark, sf_dir, "lineitem"), "l_orderkey", "l_partkey", F.col("l_quantity"))
    return spark.read.schema("u long, v long, w long, broken string").option("header", True).option("columnNameOfCorruptRecord", "broken").option("enforceSchema", True).csv(_written(edges, "csv")).select("u", "v", "w")


@query("read_json_changes", "SELECT event_id AS node_id, event_type AS op, CAST(user_id % 2 AS TINYINT) AS truth FROM events")
def read_json_changes(spark, sf_dir):
    e = read(spark, sf_dir, "events").select(F.col("event_id").alias("node_id"), F.col("event_type").alias("op"), (F.col("user_id") % 2).alias("truth"))
    return spark.read.schema("node_id long, op string, truth byte, broken string").option("columnNameOfCorruptRecord", "broken").json(_written(e, "json")).select("node_id", "op", "truth")


# ---- sinks ----------------------------------------------------------------------------------------------------------


@query("sink_state_versions", f"{_BASE}, {sql.sweeps(2)} SELECT node_id, f FROM s2")
def sink_state_versions(spark, sf_dir):
    _, _, run = _swept(spark, sf_dir, 2)
    store = GraphStore(spark)
    store.commit(1, run.state.limit(0).select("node_id", "f"))
    store.commit(2, run.state.select("node_id", "f"))
    store.commit(2, run.state.select("node_id", "f"))  # a replay
    return store.state()


@query("sink_growing_store", f"{_BASE}, gone AS ({sql.DEL_IDS}) SELECT src, dst, w FROM arcs WHERE src NOT IN (SELECT node_id FROM gone) AND dst NOT IN (SELECT node_id FROM gone)")
def sink_growing_store(spark, sf_dir):
    g, _ = order_part_graph(spark, sf_dir)
    store = GraphStore(spark)
    store.append(1, g.nodes, g.arcs.filter("src % 3 = 0"))
    store.append(2, None, g.arcs.filter("src % 3 != 0"))
    store.append(3, None, None, gone_ids(spark, sf_dir))
    store.compact(4)
    return store.arcs()


# ---- projection, filter, predicate ----------------------------------------------------------------------------------


@query("edges_over_tau", f"WITH {sql.EDGES} SELECT u, v, w FROM edges WHERE w > 25")
def edges_over_tau(spark, sf_dir):
    return graph.threshold_arcs(graph.bipartite_edges(read(spark, sf_dir, "lineitem"), "l_orderkey", "l_partkey", F.col("l_quantity")), 25)


@query("edges_mean_tau", f"WITH {sql.EDGES} SELECT u, v, w FROM edges WHERE w > (SELECT avg(w) FROM edges)")
def edges_mean_tau(spark, sf_dir):
    _, edges = order_part_graph(spark, sf_dir)
    return graph.threshold_arcs(edges, graph.tau_mean(edges))


@query("flag_sparsified", f"WITH {sql.EDGES} SELECT u, v, w, w > 25 AS keep FROM edges")
def flag_sparsified(spark, sf_dir):
    return graph.flag_arcs(graph.bipartite_edges(read(spark, sf_dir, "lineitem"), "l_orderkey", "l_partkey", F.col("l_quantity")), 25)


@query("binarise_quantity", "SELECT l_orderkey, l_linenumber, CAST(l_quantity >= 25 AS INT) AS truth FROM lineitem")
def binarise_quantity(spark, sf_dir):
    return read(spark, sf_dir, "lineitem").select("l_orderkey", "l_linenumber", graph.binarise(F.col("l_quantity"), 25).alias("truth"))


@query("one_vs_rest_label", "SELECT vec_id AS node_id, CAST(label = 3 AS INT) AS truth FROM embeddings")
def one_vs_rest_label(spark, sf_dir):
    return read(spark, sf_dir, "embeddings").select(F.col("vec_id").alias("node_id"), graph.one_vs_rest(F.col("label"), 3).alias("truth"))


@query("live_nodes", "SELECT o_orderkey AS node_id FROM orders WHERE o_orderstatus IN ('O', 'P') AND o_totalprice BETWEEN 1000 AND 200000")
def live_nodes(spark, sf_dir):
    return read(spark, sf_dir, "orders").filter(F.col("o_orderstatus").isin("O", "P") & F.col("o_totalprice").between(1000, 200000)).select(F.col("o_orderkey").alias("node_id"))


@query("lang_seed_nodes", "SELECT doc_id AS node_id FROM documents WHERE lang IN ('en', 'fr') AND regexp_matches(source, '^src1')")
def lang_seed_nodes(spark, sf_dir):
    return read(spark, sf_dir, "documents").filter(F.col("lang").isin("en", "fr") & F.col("source").rlike("^src1")).select(F.col("doc_id").alias("node_id"))


@query("laplacian_entry", f"WITH {sql.EDGES}, {sql.arcs()} SELECT src, dst, -w AS entry FROM arcs UNION ALL SELECT src, src, CAST(sum(w) AS BIGINT) FROM arcs GROUP BY src")
def laplacian_entry(spark, sf_dir):
    g, _ = order_part_graph(spark, sf_dir)
    off = g.arcs.select("src", "dst", (-F.col("w")).alias("entry"))
    return off.unionByName(graph.weighted_degree(g.arcs).select(F.col("node_id").alias("src"), F.col("node_id").alias("dst"), F.col("w_all").alias("entry")))


# ---- joins ----------------------------------------------------------------------------------------------------------

_LABELLED = f"WITH {sql.EDGES}, {sql.arcs()}, {sql.NODES} SELECT src, dst, w, truth FROM arcs JOIN nodes ON node_id = dst"


@query("arc_label_join", _LABELLED)
def arc_label_join(spark, sf_dir):
    g, _ = order_part_graph(spark, sf_dir)
    return g.arcs.join(g.nodes.withColumnRenamed("node_id", "dst"), "dst").select("src", "dst", "w", "truth")


@query("arc_label_join_smj", _LABELLED)
def arc_label_join_smj(spark, sf_dir):
    g, _ = order_part_graph(spark, sf_dir)
    return g.arcs.join(g.nodes.withColumnRenamed("node_id", "dst").hint("merge"), "dst").select("src", "dst", "w", "truth")


@query("affected_by_delete", f"WITH {sql.EDGES}, {sql.arcs()}, gone AS ({sql.DEL_IDS}) SELECT DISTINCT dst AS node_id FROM arcs JOIN gone ON src = node_id")
def affected_by_delete(spark, sf_dir):
    g, _ = order_part_graph(spark, sf_dir)
    return graph.neighbours_of(g.arcs, materialise(gone_ids(spark, sf_dir), "gone"))


@query("frontier_arcs", f"WITH {sql.EDGES}, {sql.arcs()}, fresh AS ({sql.NEW_IDS}) SELECT src, dst, w FROM arcs WHERE src IN (SELECT node_id FROM fresh)")
def frontier_arcs(spark, sf_dir):
    g, _ = order_part_graph(spark, sf_dir)
    return g.arcs.join(fresh_ids(spark, sf_dir).withColumnRenamed("node_id", "src"), "src", "left_semi").select("src", "dst", "w")


@query("drop_deleted_arcs", f"WITH {sql.EDGES}, {sql.arcs()}, gone AS ({sql.DEL_IDS}) SELECT src, dst, w FROM arcs WHERE src NOT IN (SELECT node_id FROM gone) AND dst NOT IN (SELECT node_id FROM gone)")
def drop_deleted_arcs(spark, sf_dir):
    return graph.apply_deletes(order_part_graph(spark, sf_dir)[0], gone_ids(spark, sf_dir))[0].arcs


@query("unlabelled_nodes", "SELECT doc_id AS node_id FROM documents WHERE doc_id NOT IN (SELECT doc_id FROM labels)")
def unlabelled_nodes(spark, sf_dir):
    return read(spark, sf_dir, "documents").select("doc_id").join(read(spark, sf_dir, "labels").select("doc_id"), "doc_id", "left_anti").withColumnRenamed("doc_id", "node_id")


_BANDS = [(0.0, 0.1), (0.1, 0.25), (0.25, 0.5), (0.5, 0.75), (0.75, 0.9), (0.9, 1.01)]


@query("score_band_join", f"{_BASE}, {sql.sweeps(5)}, b AS (SELECT * FROM (VALUES {', '.join(f'({round(a * SCALE)}, {round(b * SCALE)})' for a, b in _BANDS)}) t(lo, hi)) SELECT lo, hi, count(*) AS n FROM s5 JOIN b ON f >= lo AND f < hi GROUP BY lo, hi")
def score_band_join(spark, sf_dir):
    bands = spark.createDataFrame([(round(a * SCALE), round(b * SCALE)) for a, b in _BANDS], "lo long, hi long")
    return _swept(spark, sf_dir, 5)[2].state.join(F.broadcast(bands), (F.col("f") >= F.col("lo")) & (F.col("f") < F.col("hi"))).groupBy("lo", "hi").agg(F.count("*").alias("n"))


@query("label_as_of", "SELECT e.event_id, e.user_id, v.value AS label FROM (SELECT * FROM events WHERE event_type = 'click') e ASOF LEFT JOIN (SELECT user_id, ts, max(value) AS value FROM events WHERE event_type = 'purchase' GROUP BY 1, 2) v ON e.user_id = v.user_id AND e.ts >= v.ts")
def label_as_of(spark, sf_dir):
    """The label known at an event's time: versions and events in one sorted run per key, the last version carried forward."""
    e = read(spark, sf_dir, "events")
    versions = e.filter("event_type = 'purchase'").groupBy("user_id", "ts").agg(F.max("value").alias("version")).select("user_id", "ts", "version", F.lit(0).alias("kind"), F.lit(None).cast("long").alias("event_id"))
    asked = e.filter("event_type = 'click'").select("user_id", "ts", F.lit(None).cast("double").alias("version"), F.lit(1).alias("kind"), "event_id")
    run = Window.partitionBy("user_id").orderBy("ts", "kind").rowsBetween(Window.unboundedPreceding, 0)
    return versions.unionByName(asked).withColumn("label", F.last("version", True).over(run)).filter("kind = 1").select("event_id", "user_id", "label")


@query("truth_within_interval", "SELECT a.event_id AS a, b.event_id AS b FROM events a JOIN events b ON a.user_id = b.user_id AND b.ts > a.ts AND b.ts <= a.ts + INTERVAL 1 HOUR")
def truth_within_interval(spark, sf_dir):
    """Pairs of a user's events within an hour: equality on user and hour slot, each event in its own slot and the next."""
    e = read(spark, sf_dir, "events").select("event_id", "user_id", F.col("ts").cast("timestamp").alias("ts"))
    slot = F.floor(F.col("ts").cast("double") / 3600).cast("long")
    a = e.select(F.col("event_id").alias("a"), "user_id", F.col("ts").alias("ta"), F.explode(F.array(slot, slot + 1)).alias("slot"))
    b = e.select(F.col("event_id").alias("b"), "user_id", F.col("ts").alias("tb"), slot.alias("slot"))
    return a.join(b, ["user_id", "slot"]).filter("tb > ta AND tb <= ta + INTERVAL 1 HOUR").select("a", "b")


@query("state_coverage", "SELECT d.doc_id, l.quality, l.doc_id IS NOT NULL AS labelled FROM documents d LEFT JOIN labels l USING (doc_id)")
def state_coverage(spark, sf_dir):
    return read(spark, sf_dir, "documents").select("doc_id").join(read(spark, sf_dir, "labels").select("doc_id", "quality", F.lit(True).alias("labelled")), "doc_id", "left").select("doc_id", "quality", F.coalesce("labelled", F.lit(False)).alias("labelled"))


@query("truth_or_estimate", f"{_BASE}, {sql.sweeps(3)} SELECT coalesce(n.node_id, s.node_id) AS node_id, CAST(coalesce(n.truth * {SCALE}, s.f) AS BIGINT) AS f FROM nodes n FULL JOIN s3 s ON s.node_id = n.node_id")
def truth_or_estimate(spark, sf_dir):
    g, _, run = _swept(spark, sf_dir, 3)
    s = run.state.select("node_id", "f")
    return g.nodes.join(s, "node_id", "full").select("node_id", F.coalesce(F.col("truth").cast("long") * SCALE, "f").alias("f"))


@query("co_purchase_edges", "SELECT a.l_partkey AS u, b.l_partkey AS v, count(*) AS w FROM lineitem a JOIN lineitem b ON a.l_orderkey = b.l_orderkey AND a.l_partkey < b.l_partkey GROUP BY 1, 2")
def co_purchase_edges(spark, sf_dir):
    li = read(spark, sf_dir, "lineitem").select("l_orderkey", "l_partkey")
    return li.select("l_orderkey", F.col("l_partkey").alias("u")).join(li.select("l_orderkey", F.col("l_partkey").alias("v")), "l_orderkey").filter("u < v").groupBy("u", "v").agg(F.count("*").alias("w"))


@query("parent_jump", f"{_SUB} SELECT node_id, comp_id FROM cc WHERE node_id IN (SELECT src FROM sub)")
def parent_jump(spark, sf_dir):
    g, edges = order_part_graph(spark, sf_dir)
    return hook_jump(graph.new_subgraph(g.arcs, fresh_ids(spark, sf_dir), graph.tau_mean(edges)))


# ---- aggregation ----------------------------------------------------------------------------------------------------


@query("weighted_degree", f"WITH {sql.EDGES}, {sql.arcs()} SELECT src AS node_id, CAST(sum(w) AS BIGINT) AS w_all, count(*) AS degree FROM arcs GROUP BY src")
def weighted_degree(spark, sf_dir):
    return graph.weighted_degree(order_part_graph(spark, sf_dir)[0].arcs)


@query("neighbour_list", f"WITH {sql.EDGES}, {sql.arcs()} SELECT src AS node_id, list(dst ORDER BY dst) AS dsts, list(w ORDER BY dst) AS ws FROM arcs GROUP BY src")
def neighbour_list(spark, sf_dir):
    rows = order_part_graph(spark, sf_dir)[0].arcs.groupBy(F.col("src").alias("node_id")).agg(F.sort_array(F.collect_list(F.struct("dst", "w"))).alias("a"))
    return rows.select("node_id", F.col("a.dst").alias("dsts"), F.col("a.w").alias("ws"))


@query("distinct_neighbours", "SELECT l_suppkey, count(DISTINCT l_partkey) AS n FROM lineitem GROUP BY 1")
def distinct_neighbours(spark, sf_dir):
    return read(spark, sf_dir, "lineitem").groupBy("l_suppkey").agg(F.countDistinct("l_partkey").alias("n"))


@query("approx_neighbours")
def approx_neighbours(spark, sf_dir):
    return read(spark, sf_dir, "lineitem").groupBy("l_suppkey").agg(F.approx_count_distinct("l_partkey", 0.02).alias("n"))


@query("accuracy_cube", "SELECT lang, source, grouping(lang) * 2 + grouping(source) AS g, count(*) AS n, count(quality) AS labelled, sum(quality) AS good FROM documents LEFT JOIN labels USING (doc_id) GROUP BY CUBE (lang, source)")
def accuracy_cube(spark, sf_dir):
    d = read(spark, sf_dir, "documents").select("doc_id", "lang", "source").join(read(spark, sf_dir, "labels"), "doc_id", "left")
    return d.cube("lang", "source").agg(F.grouping_id().alias("g"), F.count("*").alias("n"), F.count("quality").alias("labelled"), F.sum("quality").alias("good"))


@query("seed_rollup", "SELECT o_orderstatus, o_orderpriority, count(*) AS n FROM orders GROUP BY ROLLUP (o_orderstatus, o_orderpriority)")
def seed_rollup(spark, sf_dir):
    return read(spark, sf_dir, "orders").rollup("o_orderstatus", "o_orderpriority").agg(F.count("*").alias("n"))


@query("grouping_sets_batches", "SELECT event_type, user_id % 10 AS shard, count(*) AS n FROM events GROUP BY GROUPING SETS ((event_type), (user_id % 10), ())")
def grouping_sets_batches(spark, sf_dir):
    e = read(spark, sf_dir, "events").withColumn("shard", F.col("user_id") % 10)
    return e.groupingSets([["event_type"], ["shard"], []], "event_type", "shard").agg(F.count("*").alias("n"))


@query("weight_stats", f"WITH {sql.EDGES} SELECT count(*) AS n, min(w) AS low, max(w) AS high, round(avg(w), 6) AS mean, round(stddev_samp(w), 6) AS sd FROM edges")
def weight_stats(spark, sf_dir):
    return order_part_graph(spark, sf_dir)[1].agg(F.count("*").alias("n"), F.min("w").alias("low"), F.max("w").alias("high"), F.round(F.avg("w"), 6).alias("mean"), F.round(F.stddev("w"), 6).alias("sd"))


@query("degree_percentiles", f"WITH {sql.EDGES}, {sql.arcs()}, d AS (SELECT src, count(*) AS degree FROM arcs GROUP BY src) SELECT round(quantile_cont(degree, 0.5), 6) AS p50, round(quantile_cont(degree, 0.9), 6) AS p90, round(quantile_cont(degree, 0.99), 6) AS p99, max(degree) AS top FROM d")
def degree_percentiles(spark, sf_dir):
    d = graph.weighted_degree(order_part_graph(spark, sf_dir)[0].arcs)
    return d.agg(*[F.round(F.percentile("degree", F.lit(p)), 6).alias(n) for p, n in ((0.5, "p50"), (0.9, "p90"), (0.99, "p99"))], F.max("degree").alias("top"))


# ---- windows --------------------------------------------------------------------------------------------------------


@query("label_change_lag", f"{_BASE}, {sql.sweeps(3)}, v AS (SELECT 1 AS version, node_id, f FROM s1 UNION ALL SELECT 2, node_id, f FROM s2 UNION ALL SELECT 3, node_id, f FROM s3) SELECT version, node_id, f - lag(f) OVER (PARTITION BY node_id ORDER BY version) AS change FROM v")
def label_change_lag(spark, sf_dir):
    v = None
    for k in (1, 2, 3):
        s = _swept(spark, sf_dir, k)[2].state.select(F.lit(k).alias("version"), "node_id", "f")
        v = s if v is None else v.unionByName(s)
    return v.select("version", "node_id", (F.col("f") - F.lag("f").over(Window.partitionBy("node_id").orderBy("version"))).alias("change"))


@query("cumulative_seed_share", "SELECT user_id, event_id, sum(CASE WHEN event_type = 'purchase' THEN 1 ELSE 0 END) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS UNBOUNDED PRECEDING) AS purchases FROM events")
def cumulative_seed_share(spark, sf_dir):
    w = Window.partitionBy("user_id").orderBy("ts", "event_id").rowsBetween(Window.unboundedPreceding, 0)
    return read(spark, sf_dir, "events").select("user_id", "event_id", F.sum((F.col("event_type") == "purchase").cast("int")).over(w).alias("purchases"))


@query("moving_event_rate", "SELECT event_id, count(*) OVER (PARTITION BY user_id ORDER BY CAST(floor(epoch(ts)) AS BIGINT) RANGE BETWEEN 86400 PRECEDING AND CURRENT ROW) AS n FROM events")
def moving_event_rate(spark, sf_dir):
    e = read(spark, sf_dir, "events").withColumn("t", F.floor(F.col("ts").cast("timestamp").cast("double")).cast("long"))
    return e.select("event_id", F.count("*").over(Window.partitionBy("user_id").orderBy("t").rangeBetween(-86400, 0)).alias("n"))


@query("batch_ntile", "SELECT user_id, event_id, ntile(4) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS batch FROM events")
def batch_ntile(spark, sf_dir):
    return read(spark, sf_dir, "events").select("user_id", "event_id", F.ntile(4).over(Window.partitionBy("user_id").orderBy("ts", "event_id")).alias("batch"))


@query("score_percent_rank", "SELECT o_orderkey, round(percent_rank() OVER (PARTITION BY o_orderstatus ORDER BY o_totalprice), 6) AS place FROM orders")
def score_percent_rank(spark, sf_dir):
    return read(spark, sf_dir, "orders").select("o_orderkey", F.round(F.percent_rank().over(Window.partitionBy("o_orderstatus").orderBy("o_totalprice")), 6).alias("place"))


# ---- sort, top-k, set operations ------------------------------------------------------------------------------------


@query("most_uncertain", f"{_BASE}, {sql.sweeps(5)} SELECT node_id, f FROM s5 ORDER BY abs(f - {HALF}), node_id LIMIT 20")
def most_uncertain(spark, sf_dir):
    return _swept(spark, sf_dir, 5)[2].state.select("node_id", "f").orderBy(F.abs(F.col("f") - HALF), "node_id").limit(20)


@query("top_hubs", f"WITH {sql.EDGES}, {sql.arcs()} SELECT src AS node_id, CAST(sum(w) AS BIGINT) AS w_all, count(*) AS degree FROM arcs GROUP BY src ORDER BY degree DESC, node_id LIMIT 10")
def top_hubs(spark, sf_dir):
    return graph.weighted_degree(order_part_graph(spark, sf_dir)[0].arcs).orderBy(F.desc("degree"), "node_id").limit(10)


@query("frontier_union", f"WITH {sql.EDGES}, {sql.arcs()}, fresh AS ({sql.NEW_IDS}), gone AS ({sql.DEL_IDS}) SELECT node_id FROM fresh UNION SELECT dst FROM arcs JOIN gone ON src = node_id")
def frontier_union(spark, sf_dir):
    return fresh_ids(spark, sf_dir).union(affected_by_delete(spark, sf_dir)).distinct()


@query("frontier_minus_truth", f"WITH {sql.NODES}, fresh AS ({sql.NEW_IDS}) SELECT node_id FROM fresh EXCEPT SELECT node_id FROM nodes WHERE truth IS NOT NULL")
def frontier_minus_truth(spark, sf_dir):
    nodes = graph.order_part(read(spark, sf_dir, "orders"), read(spark, sf_dir, "lineitem"))[0]
    return fresh_ids(spark, sf_dir).exceptAll(nodes.filter("truth is not null").select("node_id"))


@query("component_intersect", "SELECT DISTINCT l_partkey FROM lineitem WHERE l_quantity > 40 INTERSECT SELECT l_partkey FROM lineitem WHERE l_discount > 0.05")
def component_intersect(spark, sf_dir):
    li = read(spark, sf_dir, "lineitem")
    return li.filter("l_quantity > 40").select("l_partkey").intersect(li.filter("l_discount > 0.05").select("l_partkey"))


# ---- scalar functions -----------------------------------------------------------------------------------------------


@query("tokens", r"SELECT doc_id, len(regexp_extract_all(lower(text), '[^\x00-\x2F\x3A-\x40\x5B-\x60\x7B-\x7F]+')) AS n, regexp_extract_all(lower(text), '[^\x00-\x2F\x3A-\x40\x5B-\x60\x7B-\x7F]+')[1] AS head FROM documents")
def tokens(spark, sf_dir):
    t = similarity.tokens(F.col("text"))
    return read(spark, sf_dir, "documents").select("doc_id", F.size(t).cast("long").alias("n"), F.get(t, 0).alias("head"))


@query("url_host_nodes", "SELECT page_id, regexp_extract(url, '^https?://([^/?#:]+)', 1) AS host FROM pages")
def url_host_nodes(spark, sf_dir):
    return read(spark, sf_dir, "pages").select("page_id", F.regexp_extract("url", r"^https?://([^/?#:]+)", 1).alias("host"))


@query("strip_html", "SELECT page_id, length(trim(regexp_replace(regexp_replace(html, '<[^>]*>', ' ', 'g'), '[ ]+', ' ', 'g'))) AS n FROM pages")
def strip_html(spark, sf_dir):
    return read(spark, sf_dir, "pages").select("page_id", F.length(F.trim(F.regexp_replace(F.regexp_replace("html", "<[^>]*>", " "), "[ ]+", " "))).cast("long").alias("n"))


@query("batch_of_day", "SELECT event_id, date_diff('day', TIMESTAMP '2024-01-01', date_trunc('day', ts)) AS batch FROM events")
def batch_of_day(spark, sf_dir):
    return read(spark, sf_dir, "events").select("event_id", F.datediff(F.to_date("ts"), F.lit("2024-01-01").cast("date")).cast("long").alias("batch"))


@query("order_month_batch", "SELECT o_orderkey, (year(o_orderdate) - 1992) * 12 + month(o_orderdate) AS batch FROM orders")
def order_month_batch(spark, sf_dir):
    return read(spark, sf_dir, "orders").select("o_orderkey", ((F.year("o_orderdate") - 1992) * 12 + F.month("o_orderdate")).cast("long").alias("batch"))


@query("time_batches", "SELECT date_trunc('day', ts) AS batch_start, count(*) AS n FROM events GROUP BY 1")
def time_batches(spark, sf_dir):
    return graph.time_batches(read(spark, sf_dir, "events"), "ts").groupBy(F.col("batch_start").cast("timestamp_ntz").alias("batch_start")).agg(F.count("*").alias("n"))


@query("idf_weight", r"WITH w AS (SELECT DISTINCT doc_id, unnest(regexp_extract_all(lower(text), '[^\x00-\x2F\x3A-\x40\x5B-\x60\x7B-\x7F]+')) AS term FROM documents) SELECT term, count(*) AS df, round(ln(CAST((SELECT count(*) FROM documents) + 1 AS DOUBLE) / (count(*) + 1)), 6) AS idf FROM w GROUP BY term")
def idf_weight(spark, sf_dir):
    docs = read(spark, sf_dir, "documents")
    df = docs.select("doc_id", F.explode(F.array_distinct(similarity.tokens(F.col("text")))).alias("term")).groupBy("term").agg(F.count("*").alias("df"))
    return df.select("term", "df", F.round(F.log(F.lit(float(docs.count() + 1)) / (F.col("df") + 1)), 6).alias("idf"))


_VEC = "list_transform(embedding, lambda x: CAST(floor(CAST(x AS DOUBLE) * 1000 + 0.5) AS DOUBLE))"


@query("vector_norm", f"SELECT vec_id AS node_id, CAST(list_dot_product({_VEC}, {_VEC}) AS BIGINT) AS norm2 FROM embeddings")
def vector_norm(spark, sf_dir):
    return similarity.quantised(read(spark, sf_dir, "embeddings")).select("node_id", F.aggregate("q", F.lit(0).cast("long"), lambda a, x: a + x * x).alias("norm2"))


@query("cosine_embedding", f"WITH q AS (SELECT vec_id, {_VEC} AS q FROM embeddings) SELECT a.vec_id AS u, b.vec_id AS v, round(list_dot_product(a.q, b.q) / sqrt(list_dot_product(a.q, a.q) * list_dot_product(b.q, b.q)), 6) AS cosine FROM q a JOIN q b ON b.vec_id = a.vec_id + 1")
def cosine_embedding(spark, sf_dir):
    q = similarity.quantised(read(spark, sf_dir, "embeddings"))
    dot = lambda a, b: F.aggregate(F.zip_with(a, b, lambda x, y: x * y), F.lit(0).cast("long"), lambda s, x: s + x)
    pair = q.select(F.col("node_id").alias("u"), F.col("q").alias("a")).join(q.select(F.col("node_id").alias("v"), F.col("q").alias("b")), F.col("v") == F.col("u") + 1)
    return pair.select("u", "v", F.round(dot("a", "b") / F.sqrt((dot("a", "a") * dot("b", "b")).cast("double")), 6).alias("cosine"))


@query("term_map", "WITH t AS (SELECT lang, source, count(*) AS n FROM documents GROUP BY 1, 2) SELECT lang, max(n) FILTER (WHERE source = 'src0') AS n0, count(*) AS keys FROM t GROUP BY lang")
def term_map(spark, sf_dir):
    t = read(spark, sf_dir, "documents").groupBy("lang", "source").agg(F.count("*").alias("n"))
    m = t.groupBy("lang").agg(F.map_from_entries(F.collect_list(F.struct("source", "n"))).alias("m"))
    return m.select("lang", F.try_element_at("m", F.lit("src0")).alias("n0"), F.size("m").cast("long").alias("keys"))


@query("neighbour_map", "SELECT l_orderkey, max(q) FILTER (WHERE r = 1) AS first_q, count(*) AS n FROM (SELECT l_orderkey, l_partkey, sum(l_quantity) AS q, row_number() OVER (PARTITION BY l_orderkey ORDER BY l_partkey) AS r FROM lineitem GROUP BY 1, 2) GROUP BY l_orderkey")
def neighbour_map(spark, sf_dir):
    e = read(spark, sf_dir, "lineitem").groupBy("l_orderkey", "l_partkey").agg(F.sum("l_quantity").alias("q"))
    m = e.groupBy("l_orderkey").agg(F.map_from_entries(F.sort_array(F.collect_list(F.struct("l_partkey", "q")))).alias("m"))
    return m.select("l_orderkey", F.element_at(F.map_values("m"), 1).alias("first_q"), F.size("m").cast("long").alias("n"))


@query("event_props", "SELECT event_id, CAST(json_extract(props, '$.k') AS INT) AS k FROM events")
def event_props(spark, sf_dir):
    return read(spark, sf_dir, "events").select("event_id", F.from_json("props", "k INT")["k"].alias("k"))


@query("neutral_init", "SELECT o_orderkey, coalesce(CASE o_orderstatus WHEN 'F' THEN 0.0 WHEN 'O' THEN 1.0 END, 0.5) AS f, 1.0 / nullif(o_custkey % 3, 0) AS r FROM orders")
def neutral_init(spark, sf_dir):
    o = read(spark, sf_dir, "orders")
    f = F.coalesce(F.when(F.col("o_orderstatus") == "F", 0.0).when(F.col("o_orderstatus") == "O", 1.0), F.lit(0.5))
    return o.select("o_orderkey", f.alias("f"), F.try_divide(F.lit(1.0), F.col("o_custkey") % 3).alias("r"))


# ---- user functions -------------------------------------------------------------------------------------------------


@query("udf_classify", f"{_BASE}, {sql.sweeps(5)} SELECT node_id, CAST(f >= {HALF} AS INT) AS class FROM s5")
def udf_classify(spark, sf_dir):
    @F.pandas_udf("int")
    def classify(f: pd.Series) -> pd.Series:
        return (f >= HALF).astype("int32")

    return _swept(spark, sf_dir, 5)[2].state.select("node_id", classify("f").alias("class"))


@query("classify_builtin", f"{_BASE}, {sql.sweeps(5)} SELECT node_id, CAST(f >= {HALF} AS INT) AS class FROM s5")
def classify_builtin(spark, sf_dir):
    return propagate.classify(_swept(spark, sf_dir, 5)[2].state).select("node_id", "class")


@query("udaf_weighted_mean", "SELECT l_orderkey, round(sum(l_quantity * l_discount) / sum(l_quantity), 10) AS mean FROM lineitem GROUP BY 1")
def udaf_weighted_mean(spark, sf_dir):
    @F.pandas_udf("double")
    def mean(w: pd.Series, x: pd.Series) -> float:
        return float((w * x).sum() / w.sum())

    return read(spark, sf_dir, "lineitem").groupBy("l_orderkey").agg(F.round(mean("l_quantity", "l_discount"), 10).alias("mean"))


@query("udtf_neighbours", f"WITH {sql.EDGES}, {sql.arcs()}, t AS (SELECT src, dst, w, row_number() OVER (PARTITION BY src ORDER BY w DESC, dst) AS r FROM arcs WHERE src % 2 = 1) SELECT src, dst, w FROM t WHERE r <= 3")
def udtf_neighbours(spark, sf_dir):
    @F.udtf(returnType="dst: bigint, w: bigint")
    class Heaviest:
        def eval(self, dsts: list, ws: list, k: int):
            yield from sorted(zip(dsts, ws, strict=True), key=lambda p: (-p[1], p[0]))[:k]

    spark.udtf.register("heaviest_neighbours", Heaviest)
    neighbour_list(spark, sf_dir).filter("node_id % 2 = 1").createOrReplaceTempView("labelflow_rows")
    return spark.sql("SELECT node_id AS src, t.dst, t.w FROM labelflow_rows, LATERAL heaviest_neighbours(dsts, ws, 3) t")


@query("sql_supernode_label", f"{_BASE} SELECT node_id, round(CASE WHEN w0 + w1 > 0 THEN CAST(w1 AS DOUBLE) / (w0 + w1) ELSE 0.5 END, 6) AS f0 FROM cw")
def sql_supernode_label(spark, sf_dir):
    from labelflow.operators.classweights import contraction

    g, _ = order_part_graph(spark, sf_dir)
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION supernode_label(w0 BIGINT, w1 BIGINT) RETURNS DOUBLE RETURN coalesce(try_divide(CAST(w1 AS DOUBLE), w0 + w1), 0.5D)")
    contraction(g.arcs, g.nodes).createOrReplaceTempView("labelflow_weights")
    return spark.sql("SELECT node_id, round(supernode_label(w0, w1), 6) AS f0 FROM labelflow_weights")


# ---- streams --------------------------------------------------------------------------------------------------------


def _stream(spark: SparkSession, sf_dir: str, extra: DataFrame | None = None) -> DataFrame:
    return ev.stream(spark, ev.staged(spark, sf_dir, extra=extra))


def _plain(c: str) -> Column:
    return F.col(c).cast("timestamp_ntz").alias(c)


@query("stream_daily_batches", "SELECT date_trunc('day', ts) AS day, event_type, count(*) AS n FROM events GROUP BY 1, 2")
def stream_daily_batches(spark, sf_dir):
    return ev.finish(ev.daily_batches(_stream(spark, sf_dir)), "complete").select(_plain("day"), "event_type", "n")


@query("stream_sliding_rate", "SELECT d AS start, count(*) AS n FROM (SELECT unnest([date_trunc('day', ts), date_trunc('day', ts) - INTERVAL 1 DAY]) AS d FROM events) GROUP BY 1")
def stream_sliding_rate(spark, sf_dir):
    return ev.finish(ev.sliding_rate(_stream(spark, sf_dir)), "complete").select(_plain("start"), "n")


@query("stream_user_sessions", "WITH e AS (SELECT user_id, ts, CASE WHEN ts - lag(ts) OVER (PARTITION BY user_id ORDER BY ts) < INTERVAL 30 MINUTE THEN 0 ELSE 1 END AS fresh FROM events), s AS (SELECT user_id, ts, sum(fresh) OVER (PARTITION BY user_id ORDER BY ts ROWS UNBOUNDED PRECEDING) AS s FROM e) SELECT user_id, min(ts) AS start, max(ts) + INTERVAL 30 MINUTE AS stop, count(*) AS n FROM s GROUP BY user_id, s")
def stream_user_sessions(spark, sf_dir):
    return ev.finish(ev.user_sessions(_stream(spark, sf_dir)), "complete").select("user_id", _plain("start"), _plain("stop"), "n")


@query("stream_late_changes", "SELECT date_trunc('day', ts) AS day, count(*) AS n FROM events GROUP BY 1 HAVING date_trunc('day', ts) + INTERVAL 2 DAY <= (SELECT max(ts) FROM events)")
def stream_late_changes(spark, sf_dir):
    """Every seventh event arrives in the last file; the side path brings those whose day has closed."""
    out = ev.split_late(ev.stream(spark, ev.staged(spark, sf_dir, tardy="event_id % 7 = 0")))
    return ev.late_corrected(spark, out).select(_plain("day"), (F.col("n") + F.col("n_late")).alias("n"))


@query("stream_closed_days", "SELECT date_trunc('day', ts) AS day, count(*) AS n FROM events GROUP BY 1 HAVING date_trunc('day', ts) + INTERVAL 2 DAY <= (SELECT max(ts) FROM events)")
def stream_closed_days(spark, sf_dir):
    return ev.finish(ev.late_changes(_stream(spark, sf_dir))).select(_plain("day"), "n")


@query("stream_dedupe_changes", "SELECT event_id, user_id, event_type FROM events")
def stream_dedupe_changes(spark, sf_dir):
    again = read(spark, sf_dir, "events").filter("event_id % 5 = 0").withColumn("ts", F.col("ts").cast("timestamp"))
    return ev.finish(ev.deduplicated(_stream(spark, sf_dir, again)).select("event_id", "user_id", "event_type"))


@query("stream_enrich_users", "SELECT event_id, user_id, event_type, c_mktsegment FROM events JOIN customer ON c_custkey = user_id")
def stream_enrich_users(spark, sf_dir):
    return ev.finish(ev.enriched(_stream(spark, sf_dir), read(spark, sf_dir, "customer")))


@query("stream_click_purchase", "SELECT c.event_id AS click_id, p.event_id AS purchase_id, c.user_id FROM events c JOIN events p ON c.user_id = p.user_id AND p.ts >= c.ts AND p.ts <= c.ts + INTERVAL 1 HOUR WHERE c.event_type = 'click' AND p.event_type = 'purchase'")
def stream_click_purchase(spark, sf_dir):
    return ev.finish(ev.click_purchase(_stream(spark, sf_dir)))


@query("stream_live_labels")
def stream_live_labels(spark, sf_dir):
    e = read(spark, sf_dir, "events")
    users = e.groupBy("user_id").agg(F.sum("value").alias("total"))
    mean = users.agg(F.avg("total")).first()[0] or 0.0
    truth = users.filter("user_id % 5 = 0").select("user_id", (F.col("total") >= mean).cast("int").alias("truth"))
    return ev.live_labels(ev.stream(spark, ev.staged(spark, sf_dir, 3)), truth).select("node_id", "f")


_CHECKED = {"orders": "o_orderkey", "lineitem": "l_orderkey", "events": "event_id"}


@query("schema_checks", " UNION ALL ".join(f"SELECT '{n}' AS name, CAST((SELECT count(*) FROM (DESCRIBE {n})) AS INT) AS columns, count(*) AS n_rows, count({k}) AS keyed FROM {n}" for n, k in _CHECKED.items()))
def schema_checks(spark, sf_dir):
    """Columns that the files have, rows, and rows with a key, of three tables; every declared column must be there in its type."""
    out = None
    for name, key in _CHECKED.items():
        found = spark.read.parquet(f"{sf_dir}/{name}.parquet")
        types = {f.name: f.dataType for f in found.schema.fields}
        wrong = [f.name for f in schema_of(name).fields if types.get(f.name) != f.dataType]
        if wrong:
            raise ValueError(f"{name}: not as declared: {wrong}")
        one = found.agg(F.count("*").alias("n_rows"), F.count(key).alias("keyed")).select(F.lit(name).alias("name"), F.lit(len(types)).cast("int").alias("columns"), "n_rows", "keyed")
        out = one if out is None else out.unionByName(one)
    return out
