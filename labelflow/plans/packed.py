"""A graph that is packed: unlabelled nodes are numbered, arcs become pairs of four-byte places in blocks that many tasks lay out side by side,
and one task holds the whole of it and runs every superstep, in the arithmetic of plans.local."""

from __future__ import annotations

from collections.abc import Callable, Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from labelflow.plans.joins import BROADCAST_ROWS
from labelflow.plans.local import Rows
from labelflow.plans.stage import arrow_rows, materialise, release

#: Bytes of one task's memory for an arc while it is laid out, and for a node with its labels.
ARC_BYTES, NODE_BYTES = 16, 100
#: Nodes a numbering task sorts, arcs in a block, rows of a result batch.
NODES_PER_BUCKET = 50_000
BLOCK_ARCS = 500_000
OUT_ROWS = 200_000


@dataclass(frozen=True)
class Packed:
    """Blocks (blob) of arcs between places, the places (node_id, place), and how many there are."""

    blocks: DataFrame
    places: DataFrame
    n: int


def number(nodes: DataFrame, n: int) -> DataFrame:
    """(node_id, place): the n distinct nodes counted from 0, sorted and counted per hash bucket and offset by the buckets before."""
    bucket = F.pmod(F.xxhash64("node_id"), F.lit(max(1, -(-n // NODES_PER_BUCKET)))).alias("bucket")
    rows = nodes.select("node_id", bucket)
    sizes = rows.groupBy("bucket").agg(F.count("*").alias("n"))
    before = sizes.select("bucket", (F.sum("n").over(Window.orderBy("bucket")) - F.col("n")).alias("before"))  # one row per bucket
    rank = F.row_number().over(Window.partitionBy("bucket").orderBy("node_id")) - 1
    return rows.withColumn("rank", rank).join(F.broadcast(before), "bucket").select("node_id", (F.col("rank") + F.col("before")).cast("int").alias("place"))


def _blob(table: pa.Table) -> bytes:
    sink = pa.BufferOutputStream()
    with pa.ipc.new_stream(sink, table.schema) as out:
        out.write_table(table)
    return sink.getvalue().to_pybytes()


def _unblob(blob: pa.Scalar) -> pa.Table:
    return pa.ipc.open_stream(blob.as_buffer()).read_all()


def _blocks(batches: Iterator[pa.RecordBatch], most: int, pack: Callable[[pa.Table], bytes]) -> Iterator[pa.RecordBatch]:
    held, rows = [], 0
    for batch in batches:
        held.append(batch)
        rows += batch.num_rows
        if rows >= most:
            yield pa.RecordBatch.from_arrays([pa.array([pack(pa.Table.from_batches(held))], pa.binary())], ["blob"])
            held, rows = [], 0
    if rows:
        yield pa.RecordBatch.from_arrays([pa.array([pack(pa.Table.from_batches(held))], pa.binary())], ["blob"])


def arc_block(t: pa.Table) -> bytes:
    """Arcs (ps, pd, w) as rows: the sources' places, their number of arcs, and far places and weights in that order."""
    ps, pd_, w = (t[c].to_numpy() for c in ("ps", "pd", "w"))
    if len(ps) and np.any(ps[1:] < ps[:-1]):
        by = np.argsort(ps, kind="stable")
        ps, pd_, w = ps[by], pd_[by], w[by]
    if len(w) and -(2**31) <= w.min() and w.max() < 2**31:
        w = w.astype(np.int32)
    first = np.flatnonzero(np.concatenate(([True], ps[1:] != ps[:-1])))
    sizes = np.diff(np.append(first, len(ps)))
    return _blob(pa.table({"src": [ps[first].astype(np.int32)], "size": [sizes.astype(np.int32)], "dst": [pd_.astype(np.int32)], "w": [w]}))


def lay_out(ids: np.ndarray, blocks: list[pa.Table]) -> Rows:
    """Rows of all blocks, which are given up one by one; a node's arcs may lie in several."""
    take = lambda t, c: t[c].combine_chunks().values.to_numpy()
    at = np.zeros(len(ids) + 1, np.int64)
    for t in blocks:
        at[take(t, "src") + 1] += take(t, "size")
    np.cumsum(at, out=at)
    wide = any(take(t, "w").dtype == np.int64 for t in blocks)
    dst, w = np.empty(int(at[-1]), np.int32), np.empty(int(at[-1]), np.int64 if wide else np.int32)
    cursor = at[:-1].copy()
    while blocks:
        t = blocks.pop()
        src, size = take(t, "src"), take(t, "size").astype(np.int64)
        ends = np.cumsum(size)
        to = np.arange(int(ends[-1]) if len(ends) else 0) + np.repeat(cursor[src] - (ends - size), size)
        dst[to], w[to] = take(t, "dst"), take(t, "w")
        cursor[src] += size
    return Rows.packed(ids, at, dst, w)


def pack(arcs: DataFrame, places: DataFrame, n: int) -> Packed:
    """Arcs (ps, pd, w) in blocks."""
    blocks = arcs.select("ps", "pd", "w").mapInArrow(lambda batches: _blocks(batches, BLOCK_ARCS, arc_block), "blob binary")
    return Packed(materialise(blocks, "packed"), places, n)


def components(rows: Rows) -> np.ndarray:
    """Smallest id that each node reaches: roots hook to the least root their members see, then parents are jumped to the root."""
    par, nodes = np.arange(len(rows.ids)), np.arange(len(rows.ids))
    while True:
        low = par.copy()
        for a, b in rows.pieces(nodes):
            lo, hi = rows.at[a], rows.at[b]
            if hi > lo:
                full = np.flatnonzero(rows.at[a + 1 : b + 1] > rows.at[a:b])
                seen = np.minimum.reduceat(par[rows.dst[lo:hi]], rows.at[a:b][full] - lo)
                low[a + full] = np.minimum(low[a + full], seen)
        hooked = par.copy()
        np.minimum.at(hooked, par, low)
        while not np.array_equal(up := hooked[hooked], hooked):
            hooked = up
        if np.array_equal(hooked, par):
            break
        par = hooked
    least = rows.ids.copy()
    np.minimum.at(least, par, rows.ids)
    return least[par]


def run_packed(packed: Packed, nodes: DataFrame, work: Callable[[Rows, dict[str, np.ndarray]], pa.Table], schema: str, label: str) -> DataFrame:
    """Runs `work(rows, columns)` in one task on a packed graph and the columns of its nodes (node_id and more; none null), in the order of
    the places, and writes the rows it returns."""
    columns = [c for c in nodes.columns if c != "node_id"]
    placed = nodes.join(packed.places if packed.n > BROADCAST_ROWS else F.broadcast(packed.places), "node_id").select("place", "node_id", *columns)
    held = materialise(placed.mapInArrow(lambda batches: _blocks(batches, BLOCK_ARCS, _blob), "blob binary"), "packed-nodes")
    n, names = packed.n, ["node_id", *columns]

    def whole(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        cols: dict[str, np.ndarray] = {}
        blocks = []
        for batch in batches:
            for kind, blob in zip(batch["kind"].to_pylist(), batch["blob"], strict=True):
                t = _unblob(blob)
                if kind:
                    blocks.append(t)
                    continue
                place = t["place"].to_numpy()
                for c in names:
                    part = t[c].to_numpy()
                    cols.setdefault(c, np.zeros(n, part.dtype))[place] = part
        if not cols:
            return
        out = work(lay_out(cols["node_id"], blocks), cols)
        yield from out.to_batches(max_chunksize=OUT_ROWS)

    with arrow_rows(nodes.sparkSession, 1):
        both = held.withColumn("kind", F.lit(0)).unionByName(packed.blocks.withColumn("kind", F.lit(1)))
        done = materialise(both.coalesce(1).mapInArrow(whole, schema), label)
    release(held)
    return done
