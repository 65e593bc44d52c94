"""Similarity graphs as tables: nodes (node_id, truth) and arcs (src, dst, w) in both directions, w a whole number.

Changes are applied to the tables; nothing here iterates.
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from labelflow.functions.hashing import with_hash
from labelflow.plans.joins import BROADCAST_ROWS, lookup, salts_for, without
from labelflow.plans.stage import materialise


@dataclass(frozen=True)
class SimilarityGraph:
    nodes: DataFrame  # node_id, truth (0, 1 or null)
    arcs: DataFrame  # src, dst, w
    split: object | None = None  # what propagate.split found of this graph, where it has been asked


def canonical(edges: DataFrame, combine: str = "max") -> DataFrame:
    """Edges (u, v, w) with u < v, no loops, parallel ones combined by max or sum, non-positive weights gone."""
    how = {"max": F.max, "sum": F.sum}[combine]
    e = edges.filter("u != v and w > 0").select(F.least("u", "v").alias("u"), F.greatest("u", "v").alias("v"), "w")
    return e.groupBy("u", "v").agg(how("w").alias("w"))


def arcs_of(edges: DataFrame) -> DataFrame:
    """Both directions of each edge, in one pass over the edges."""
    both = F.array(F.struct(F.col("u").alias("src"), F.col("v").alias("dst"), "w"), F.struct(F.col("v").alias("src"), F.col("u").alias("dst"), "w"))
    return edges.select(F.explode(both).alias("a")).select("a.*")


def bipartite_edges(rows: DataFrame, left: str, right: str, weight: Column) -> DataFrame:
    """Edges of a join table: left keys become even ids, right keys odd ones, parallel rows are summed."""
    e = rows.groupBy((F.col(left) * 2).alias("u"), (F.col(right) * 2 + 1).alias("v")).agg(F.sum(weight).cast("long").alias("w"))
    return e.filter("w > 0")


def weighted_degree(arcs: DataFrame) -> DataFrame:
    return arcs.groupBy(F.col("src").alias("node_id")).agg(F.sum("w").alias("w_all"), F.count("*").alias("degree"))


def tau_mean(edges: DataFrame) -> float:
    """The mean edge weight, the threshold's default."""
    return float(edges.agg(F.avg("w")).first()[0] or 0.0)


def flag_arcs(arcs: DataFrame, tau: float | Column) -> DataFrame:
    """Keeps every arc and marks those above the threshold: flagged ones may be needed later."""
    return arcs.withColumn("keep", F.col("w") > tau)


def threshold_arcs(arcs: DataFrame, tau: float | Column) -> DataFrame:
    """Arcs strictly above the threshold; an equal weight goes."""
    return arcs.filter(F.col("w") > tau)


def neighbours_of(arcs: DataFrame, ids: DataFrame) -> DataFrame:
    """Distinct ends of arcs that start in ids (node_id)."""
    return lookup_ids(arcs, ids, "src").select(F.col("dst").alias("node_id")).distinct()


def lookup_ids(rows: DataFrame, ids: DataFrame, column: str) -> DataFrame:
    """Semi-join by a distinct id table: broadcast behind a count, dealt over salts beyond."""
    return lookup(rows, ids.select(F.col("node_id").alias(column)), [column], "inner", "dst" if column == "src" and "dst" in rows.columns else column)


def apply_deletes(g: SimilarityGraph, dels: DataFrame) -> tuple[SimilarityGraph, DataFrame]:
    """The graph without the deleted nodes, and the neighbours they had. Ids may repeat or be unknown."""
    gone = materialise(dels.select("node_id").distinct(), "dels")
    affected = without(neighbours_of(g.arcs, gone), gone, ["node_id"])
    arcs = without(without(g.arcs, gone.select(F.col("node_id").alias("src")), ["src"]), gone.select(F.col("node_id").alias("dst")), ["dst"])
    return SimilarityGraph(without(g.nodes, gone, ["node_id"]), arcs), affected


def apply_inserts(g: SimilarityGraph, ins: DataFrame, ins_edges: DataFrame) -> tuple[SimilarityGraph, DataFrame]:
    """The graph with new nodes (node_id, truth) and edges (u, v, w) that touch them, and the affected: new nodes and their
    neighbours. Edges whose other end is not in the graph are left out; co-inserted nodes may be partners. An insert that names a
    node of the graph sets its truth where it carries one, and keeps it where not; of several inserts of a node the largest counts."""
    new = materialise(ins.groupBy("node_id").agg(F.max("truth").alias("truth")), "ins")
    known = lookup(g.nodes.select("node_id", "truth"), new.withColumnRenamed("truth", "told"), ["node_id"], "left", "node_id", salts=1)
    known = known.select("node_id", F.coalesce("told", "truth").alias("truth"))
    nodes = known.unionByName(without(new, g.nodes.select("node_id"), ["node_id"]))
    live = materialise(nodes.select("node_id"), "live")
    salts = salts_for(ins_edges, "u", "v") if live.count() > BROADCAST_ROWS else 1  # a side that is broadcast needs none
    edges = lookup(lookup(ins_edges, live.select(F.col("node_id").alias("u")), ["u"], "inner", "v", salts=salts), live.select(F.col("node_id").alias("v")), ["v"], "inner", "u", salts=salts)
    added = materialise(arcs_of(canonical(edges.select("u", "v", "w"))), "ins-arcs")
    affected = new.select("node_id").union(neighbours_of(added.unionByName(g.arcs.select(*added.columns)), new)).distinct()
    return SimilarityGraph(nodes, g.arcs.select("src", "dst", "w").unionByName(added)), affected


def new_subgraph(arcs: DataFrame, new_ids: DataFrame, tau: float | Column) -> DataFrame:
    """Edges (u < v) among new nodes above the threshold."""
    inner = lookup(lookup(arcs, new_ids.select(F.col("node_id").alias("src")), ["src"], "inner", "dst"), new_ids.select(F.col("node_id").alias("dst")), ["dst"], "inner", "src")
    return threshold_arcs(inner, tau).filter("src < dst").select(F.col("src").alias("u"), F.col("dst").alias("v"), "w")


def binarise(col: Column, cutoff: float) -> Column:
    return F.when(col >= cutoff, 1).otherwise(0)


def one_vs_rest(col: Column, value) -> Column:
    return F.when(col == value, 1).otherwise(0)


def balanced_sample(df: DataFrame, ident: str, label: str, n: int, salt: int = 1) -> DataFrame:
    """The n rows of least hash in each class."""
    rank = F.row_number().over(Window.partitionBy(label).orderBy("h", ident))
    return with_hash(df, "h", ident, salt).withColumn("rank", rank).filter(F.col("rank") <= n).drop("rank", "h")


def choose_seeds(nodes: DataFrame, frac: float | None = None, n: int | None = None, per_class: int | None = None, salt: int = 1) -> DataFrame:
    """node_id, truth of the known nodes that keep their label: a share of them, a fixed number, or a number per class, by least
    hash. Exact counts come from ranges over the hash, not from one sorted task: a share is a bound on the hash itself."""
    known = with_hash(nodes.filter("truth is not null"), "h", "node_id", salt)
    if per_class is not None:
        rank = F.row_number().over(Window.partitionBy("truth").orderBy("h", "node_id"))
        return known.withColumn("rank", rank).filter(F.col("rank") <= per_class).select("node_id", "truth")
    if n is not None:
        return known.orderBy("h", "node_id").limit(n).select("node_id", "truth")
    from labelflow.functions.hashing import P

    return known.filter(F.col("h") < int(P * frac)).select("node_id", "truth")


#: Times that a node may be drawn for deletion.
DRAWS = 3


def make_batches(nodes: DataFrame, n_batches: int, mix: tuple[float, float, float] = (0.90, 0.01, 0.09), salt: int = 3) -> DataFrame:
    """Change batches (batch_id, op, node_id, truth): every node is inserted in one batch chosen by hash, a share of the inserts with
    its label, and the rest of a batch are deletions drawn by hash from the nodes of earlier batches.

    Deletions are drawn with replacement: DRAWS times by hashes of their own, so that the same node may be hit by two batches. The
    graph never loses all nodes, since a batch only deletes among earlier ones."""
    unlabelled, labelled, deleted = mix
    rows = nodes.select("node_id", "truth")
    for name, s in (("h", salt), ("h2", salt + 1)):
        rows = with_hash(rows, name, "node_id", s)
    rows = rows.withColumn("batch_id", (F.col("h") % n_batches).cast("int"))
    cut = round(1_000_000 * labelled / (unlabelled + labelled))
    ins = rows.select("batch_id", F.lit("ins").alias("op"), "node_id", F.when(F.col("h2") % 1_000_000 < cut, F.col("truth")).alias("truth"))
    # a draw hits a node of batch b, in batch b + 1 + (hash mod rest), with the share that keeps deletions at their part of a batch
    rest = n_batches - 1 - F.col("batch_id")
    share = round(1_000_000 * deleted / (unlabelled + labelled) / DRAWS)
    dels = None
    for k in range(DRAWS):
        drawn = with_hash(with_hash(rows, "hit", "node_id", salt + 2 + 2 * k), "when", "node_id", salt + 3 + 2 * k)
        drawn = drawn.filter((rest > 0) & (F.col("hit") % 1_000_000 < share))
        drawn = drawn.select((F.col("batch_id") + 1 + F.col("when") % F.greatest(rest, F.lit(1))).cast("int").alias("batch_id"), F.lit("del").alias("op"), "node_id", F.lit(None).cast("int").alias("truth"))
        dels = drawn if dels is None else dels.unionByName(drawn)
    return ins.withColumn("truth", F.col("truth").cast("int")).unionByName(dels)


def normalise_changes(changes: DataFrame) -> DataFrame:
    """Distinct deletes and one insert per node and batch; an id in both lists is deleted, then inserted."""
    return changes.groupBy("batch_id", "op", "node_id").agg(F.max("truth").alias("truth"))


def time_batches(df: DataFrame, ts: str, every: str = "1 day") -> DataFrame:
    """Adds batch_start, the window of the event time that a row falls into."""
    return df.withColumn("batch_start", F.window(F.col(ts).cast("timestamp"), every)["start"])


def order_part(orders: DataFrame, lineitem: DataFrame) -> tuple[DataFrame, DataFrame]:
    """Nodes and edges of the order-part graph: finished orders are class 0, open ones class 1, pending ones and parts unknown."""
    edges = bipartite_edges(lineitem, "l_orderkey", "l_partkey", F.col("l_quantity"))
    truth = F.when(F.col("o_orderstatus") == "F", 0).when(F.col("o_orderstatus") == "O", 1)
    nodes = orders.select((F.col("o_orderkey") * 2).alias("node_id"), truth.cast("int").alias("truth"))
    parts = lineitem.select((F.col("l_partkey") * 2 + 1).alias("node_id")).distinct().withColumn("truth", F.lit(None).cast("int"))
    return nodes.unionByName(parts), edges
