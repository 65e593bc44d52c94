"""Sparse-inverse harmonic baseline: an l1-penalised approximate inverse, column by column.

On the degree-normalised Laplacian N each column h minimises half the squared residual of N h against the unit vector plus
0.01 gamma times the l1 norm of h, by accelerated proximal gradient steps. Columns are independent, so they are dealt over tasks,
each of which holds the sparse matrix, whose size is checked. A larger gamma is sparser and poorer.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from labelflow.functions.fixed import SCALE
from labelflow.operators.graph import SimilarityGraph
from labelflow.operators.harmonic import CapacityError
from labelflow.operators.propagate import free_state

MOST_ARCS = 500_000
MOST_NODES = 20_000
AT_ONCE = 64


def _columns(ids, w0, w1, w_all, s, d, w, gamma, rounds):
    deg = np.where(w_all > 0, w_all, 1).astype(float)
    off = w / np.sqrt(deg[s] * deg[d])
    penalty = 0.01 * gamma
    root = np.sqrt(deg)

    def mul(x):
        out = x.copy()
        np.subtract.at(out, s, off[:, None] * x[d])
        return out

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            cols = batch.column(0).to_numpy()
            for at in range(0, len(cols), AT_ONCE):
                mine = cols[at : at + AT_ONCE]
                target = np.zeros((len(ids), len(mine)))
                target[mine, np.arange(len(mine))] = 1.0
                x, y, t = np.zeros_like(target), np.zeros_like(target), 1.0
                for _ in range(rounds):  # the squared norm of N is at most 4
                    g = mul(mul(y) - target)
                    new = y - 0.25 * g
                    new = np.sign(new) * np.maximum(np.abs(new) - 0.25 * penalty, 0.0)
                    t2 = (1 + np.sqrt(1 + 4 * t * t)) / 2
                    y, x, t = new + (t - 1) / t2 * (new - x), new, t2
                # symmetric matrix: column i of the inverse serves as row i
                f1, f0 = (x * (w1 / root)[:, None]).sum(0) / root[mine], (x * (w0 / root)[:, None]).sum(0) / root[mine]
                yield pa.RecordBatch.from_arrays([pa.array(ids[mine]), pa.array(f0), pa.array(f1), pa.array((x != 0).sum(0).astype(np.int64))], names=["node_id", "part0", "part1", "nonzero"])

    return run


def harmonic_sparse_inverse(g: SimilarityGraph, gamma: float, readout: str = "raw", rounds: int = 200) -> DataFrame:
    """(node_id, label, nonzero): `raw` is the clipped class-1 part, `ratio` its share of both parts, half where both vanish."""
    state, arcs = free_state(g)
    n, m = state.count(), arcs.count()
    if n > MOST_NODES or m > MOST_ARCS:
        raise CapacityError(f"{n} nodes and {m} arcs are more than each task may hold ({MOST_NODES}, {MOST_ARCS})")
    rows = state.orderBy("node_id").select("node_id", "f", "w0", "w1", "w_all").toArrow()  # bounded by the check above
    links = arcs.toArrow()
    ids, f, w0, w1, w_all = (rows[c].to_numpy() for c in rows.column_names)
    s, d = np.searchsorted(ids, links["src"].to_numpy()), np.searchsorted(ids, links["dst"].to_numpy())
    spark = g.nodes.sparkSession
    cols = spark.range(0, n, 1, max(1, min(64, -(-n // AT_ONCE)))).select(F.col("id"))
    out = cols.mapInArrow(_columns(ids, w0.astype(float), w1.astype(float), w_all, s, d, links["w"].to_numpy().astype(float), gamma, rounds), "node_id long, part0 double, part1 double, nonzero long")
    if readout == "raw":
        label = F.least(F.greatest("part1", F.lit(0.0)), F.lit(1.0))
    else:
        a, b = F.greatest("part0", F.lit(0.0)), F.greatest("part1", F.lit(0.0))
        label = F.when(a + b > 1e-12, b / (a + b)).otherwise(F.lit(0.5))
    return out.select("node_id", label.alias("label"), "nonzero")


def drop_tolerance_inverse(g: SimilarityGraph, tol: float, guard: int = 2_000) -> DataFrame:
    """(node_id, label): the dense inverse without its entries below the tolerance, relative to the largest; a check on the above."""
    from labelflow.operators.harmonic import _check_dense, _one_task, dense_system

    state, arcs = free_state(g)
    _check_dense(state.count(), guard)

    def solve(ids, f, w0, w1, w_all, src, dst, w):
        inverse = np.linalg.pinv(dense_system(ids, w_all, src, dst, w))
        inverse[np.abs(inverse) < tol * np.abs(inverse).max()] = 0.0
        return np.clip(np.where(w_all > 0, inverse @ w1.astype(float), f / SCALE), 0, 1)

    return _one_task(state, arcs, solve)
