"""Connected components of an edge table (u, v): hook and jump, star rounds, contraction by random priority, and one task.

All return (node_id, comp_id) with comp_id the smallest id of the component; nodes without edges are their own component.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from labelflow.plans.joins import BROADCAST_ROWS, lookup, salts_for
from labelflow.plans.packed import Packed, components, run_packed
from labelflow.plans.stage import materialise, release

MAX_ROUNDS = 200


def _arcs(edges: DataFrame) -> DataFrame:
    e = edges.select(F.col("u").cast("long").alias("u"), F.col("v").cast("long").alias("v")).filter("u != v")
    return e.unionByName(e.select(F.col("v").alias("u"), F.col("u").alias("v")))


def _with_isolated(found: DataFrame, nodes: DataFrame | None) -> DataFrame:
    if nodes is None:
        return found
    ids = nodes.select(F.col("node_id").cast("long").alias("node_id")).distinct()
    return ids.join(found, "node_id", "left").select("node_id", F.coalesce("comp_id", "node_id").alias("comp_id"))


def hook_round(parents: DataFrame, arcs: DataFrame) -> DataFrame:
    """(node_id, par): the least of a node's parent and its neighbours' parents."""
    seen = lookup(arcs, parents.select(F.col("node_id").alias("v"), F.col("par").alias("far")), ["v"], "inner", "u")
    least = seen.groupBy("u").agg(F.min("far").alias("low"))
    return parents.join(least.withColumnRenamed("u", "node_id"), "node_id", "left").select("node_id", F.least("par", F.coalesce("low", "par")).alias("par"))


def jump_round(parents: DataFrame) -> DataFrame:
    """(node_id, par): the parent's parent."""
    up = parents.select(F.col("node_id").alias("par"), F.col("par").alias("top"))
    return lookup(parents, up, ["par"], "left", "node_id").select("node_id", F.coalesce("top", "par").alias("par"))


def hook_jump(edges: DataFrame, trace: list[DataFrame] | None = None) -> DataFrame:
    """Alternates hooking and jumping until nothing moves. A hook looks at the neighbours' parents, not at their ids: on the
    path 2-9-1-8-0 ids alone would stall with three roots. `trace` collects the parents after each hook and each jump."""
    arcs = materialise(_arcs(edges).distinct(), "cc-arcs")
    par = materialise(arcs.select(F.col("u").alias("node_id")).distinct().withColumn("par", F.col("node_id")), "cc-par")
    for _ in range(MAX_ROUNDS):
        hooked = materialise(hook_round(par, arcs), "cc-hook")
        jumped = materialise(jump_round(hooked), "cc-jump")
        if trace is not None:
            trace += [hooked, jumped]
        moved = jumped.join(par.withColumnRenamed("par", "was"), "node_id").filter("par != was").limit(1).count()
        release(par) if trace is None else None
        par = jumped
        if not moved:
            break
    return par.withColumnRenamed("par", "comp_id")


def stars(edges: DataFrame) -> DataFrame:
    """Large-star and small-star rounds until the edge set stays the same: O(log^2 n) rounds, no growth of the edge set."""
    e = materialise(_arcs(edges).filter("u > v").distinct(), "cc-star")
    all_ids = materialise(_arcs(edges).select(F.col("u").alias("node_id")).distinct(), "cc-ids")
    mark = None
    for _ in range(MAX_ROUNDS):
        both = e.unionByName(e.select(F.col("v").alias("u"), F.col("u").alias("v")))
        low = materialise(both.groupBy("u").agg(F.least(F.min("v"), F.first("u")).alias("m")), "cc-low")
        large = materialise(lookup(both, low, ["u"], "inner", "v").filter("v > u").select(F.col("v").alias("u"), F.col("m").alias("v")).filter("u != v").distinct(), "cc-large")
        down = large.select(F.greatest("u", "v").alias("u"), F.least("u", "v").alias("v"))
        low2 = materialise(down.groupBy("u").agg(F.min("v").alias("m")), "cc-low")
        small = lookup(down, low2, ["u"], "inner", "v").select(F.explode(F.array(F.struct(F.col("v").alias("u"), F.col("m").alias("v")), F.struct(F.col("u").alias("u"), F.col("m").alias("v")))).alias("x")).select("x.*").filter("u != v").distinct()
        after = materialise(small, "cc-star")
        sign = tuple(after.agg(F.count("*"), F.sum(F.xxhash64("u", "v").cast("decimal(38,0)"))).first())
        release(e, low, large, low2)
        e = after
        if sign == mark:
            break
        mark = sign
    found = e.select(F.col("u").alias("node_id"), F.col("v").alias("comp_id"))
    return all_ids.join(found, "node_id", "left").select("node_id", F.coalesce("comp_id", "node_id").alias("comp_id"))


def contract(edges: DataFrame) -> DataFrame:
    """Every node moves to its neighbour (or itself) of least random priority and the graph is contracted to the places moved
    to, until no edge is left: a constant share of nodes goes each round whatever the ids. Moves are then composed backwards."""
    e = materialise(_arcs(edges).filter("u > v").distinct(), "cc-edges")
    all_ids = materialise(_arcs(edges).select(F.col("u").alias("node_id")).distinct(), "cc-ids")
    moves: list[DataFrame] = []
    for turn in range(MAX_ROUNDS):
        if e.isEmpty():
            break
        both = e.unionByName(e.select(F.col("v").alias("u"), F.col("u").alias("v")))
        rank = lambda c: F.struct(F.xxhash64(F.col(c), F.lit(turn)).alias("h"), F.col(c).alias("id"))
        best = both.groupBy("u").agg(F.min(rank("v")).alias("far"), F.min(rank("u")).alias("own"))
        move = materialise(best.select("u", F.least("far", "own")["id"].alias("to")), "cc-move")
        moves.append(move)
        salts = salts_for(e, "u", "v") if move.count() > BROADCAST_ROWS else 1  # a side that is broadcast needs none
        left = lookup(e, move, ["u"], "inner", "v", salts=salts).select(F.col("to").alias("a"), "v")
        ends = lookup(left, move.select(F.col("u").alias("v"), F.col("to").alias("b")), ["v"], "inner", "a", salts=salts)
        after = materialise(ends.filter("a != b").select(F.greatest("a", "b").alias("u"), F.least("a", "b").alias("v")).distinct(), "cc-edges")
        release(e)
        e = after
    if not moves:
        return all_ids.withColumn("comp_id", F.col("node_id"))
    total = moves[-1]
    for move in reversed(moves[:-1]):  # where a node's place moved on to, or the place itself
        onward = total.select(F.col("u").alias("to"), F.col("to").alias("top"))
        salts = salts_for(move, "to") if onward.count() > BROADCAST_ROWS else 1
        total = materialise(lookup(move, onward, ["to"], "left", "u", salts=salts).select("u", F.coalesce("top", "to").alias("to")), "cc-total")
    least = materialise(total.groupBy("to").agg(F.min("u").alias("comp_id")), "cc-least")
    salts = salts_for(total, "to") if least.count() > BROADCAST_ROWS else 1
    out = materialise(lookup(total, least, ["to"], "inner", "u", salts=salts).select(F.col("u").alias("node_id"), "comp_id"), "components")
    release(all_ids, least, *moves)
    return out


#: Edges that one task may label on its own: about 50 MB of them.
ONE_TASK_EDGES = 2_000_000


def label_block(group: pa.Table) -> pa.Table:
    """Smallest reachable id by repeated minimum and pointer jumping on arrays."""
    u, v = group["u"].to_numpy(), group["v"].to_numpy()
    ids, place = np.unique(np.concatenate([u, v]), return_inverse=True)
    a, b = place[: len(u)], place[len(u) :]
    par = np.arange(len(ids))
    while True:
        before = par.copy()
        low = np.minimum(par[a], par[b])
        np.minimum.at(par, par[a], low)
        np.minimum.at(par, par[b], low)
        while True:
            up = par[par]
            if np.array_equal(up, par):
                break
            par = up
        if np.array_equal(par, before):
            return pa.table({"node_id": ids, "comp_id": ids[par]})


def one_task(edges: DataFrame) -> DataFrame:
    """All components in one task, for edge sets that the caller has found to be small."""
    e = edges.select(F.lit(0).alias("k"), F.col("u").cast("long").alias("u"), F.col("v").cast("long").alias("v")).filter("u != v")
    return e.groupBy("k").applyInArrow(lambda t: label_block(t), "node_id long, comp_id long")


METHODS = {"hook_jump": hook_jump, "stars": stars, "contract": contract, "one_task": one_task}


def packed_task(packed: Packed) -> DataFrame:
    """All components in one task on the packed layout, which holds more edges than one_task can."""
    return run_packed(packed, packed.places.select("node_id"), lambda rows, _: pa.table({"node_id": rows.ids, "comp_id": components(rows)}), "node_id long, comp_id long", "components")


def connected_components(edges: DataFrame, nodes: DataFrame | None = None, method: str = "auto", packed: Packed | None = None) -> DataFrame:
    """(node_id, comp_id = smallest id of the component). `nodes` adds those without edges; `packed` holds both packed.

    `auto` takes the packed graph, else counts the edges: up to ONE_TASK_EDGES one task labels them, beyond that the graph is contracted by
    distributed rounds."""
    if method == "auto":
        if packed is not None:
            return packed_task(packed)
        edges = materialise(edges.select("u", "v"), "cc-input")
        method = "one_task" if edges.count() <= ONE_TASK_EDGES else "contract"
    return _with_isolated(METHODS[method](edges), nodes)


def densify(components: DataFrame) -> DataFrame:
    """Renumbers component ids from 0: roots are sorted over ranges, counted per range, and offset by the ranges before."""
    roots = components.select("comp_id").distinct()
    ranged = materialise(roots.repartitionByRange(max(1, int(roots.sparkSession.conf.get("spark.sql.shuffle.partitions"))), "comp_id").sortWithinPartitions("comp_id").withColumn("part", F.spark_partition_id()), "roots")
    sizes = ranged.groupBy("part").agg(F.count("*").alias("n"))
    before = sizes.select("part", (F.sum("n").over(Window.orderBy("part")) - F.col("n")).alias("before"))  # one row per range
    place = F.row_number().over(Window.partitionBy("part").orderBy("comp_id")) - 1
    dense = ranged.withColumn("place", place).join(F.broadcast(before), "part").select("comp_id", (F.col("place") + F.col("before")).cast("long").alias("dense_id"))
    return lookup(components, materialise(dense, "dense"), ["comp_id"], "inner", "node_id")
