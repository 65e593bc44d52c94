"""Harmonic baselines: the closed form, its contracted short-circuit form, and conjugate gradients for what no dense matrix holds."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from labelflow.functions.fixed import SCALE
from labelflow.operators.graph import SimilarityGraph, apply_deletes, apply_inserts
from labelflow.operators.propagate import free_state, split, start_state
from labelflow.plans.joins import lookup, salts_for
from labelflow.plans.local import Rows
from labelflow.plans.packed import run_packed
from labelflow.plans.stage import materialise, release

#: Unlabelled nodes that a dense solve accepts: 8 n^2 bytes of one task's memory.
DENSE_NODES = 5_000


class CapacityError(ValueError):
    """The graph is larger than a method can hold."""


def _check_dense(n: int, guard: int) -> None:
    if n > guard:
        raise CapacityError(f"{n} unlabelled nodes need {8 * n * n / 1e9:.1f} GB for a dense inverse; the guard is {guard}")


def dense_system(ids: np.ndarray, w_all: np.ndarray, src: np.ndarray, dst: np.ndarray, w: np.ndarray) -> np.ndarray:
    """The unlabelled block of the graph Laplacian; nodes without neighbours get a unit row."""
    order = np.argsort(ids)
    s, d = order[np.searchsorted(ids[order], src)], order[np.searchsorted(ids[order], dst)]
    lap = np.zeros((len(ids), len(ids)))
    np.add.at(lap, (s, d), -w.astype(float))
    lap[np.arange(len(ids)), np.arange(len(ids))] += np.where(w_all > 0, w_all, 1).astype(float)
    return lap


def _one_task(state: DataFrame, arcs: DataFrame, solve, extra: str = "") -> DataFrame:
    """Runs `solve(ids, f, w0, w1, w_all, src, dst, w) -> label array` in one task; the caller has checked the size."""

    def run(left: pa.Table, right: pa.Table) -> pa.Table:
        cols = [left[c].to_numpy().copy() for c in ("node_id", "f", "w0", "w1", "w_all")]
        if not len(cols[0]):
            return pa.table({"node_id": pa.array([], pa.int64()), "label": pa.array([], pa.float64())})
        out = solve(*cols, *(right[c].to_numpy() for c in ("src", "dst", "w")))
        return pa.table({"node_id": cols[0], "label": np.asarray(out, float)})

    return state.withColumn("k", F.lit(0)).groupBy("k").cogroup(arcs.withColumn("k", F.lit(0)).groupBy("k")).applyInArrow(run, "node_id long, label double")


def _solve_dense(ids, f, w0, w1, w_all, src, dst, w):
    lap = dense_system(ids, w_all, src, dst, w)
    right = np.where(w_all > 0, w1, f / SCALE).astype(float)
    try:
        return np.linalg.solve(lap, right)
    except np.linalg.LinAlgError:  # a component without ground truth: the solution of least norm
        return np.linalg.lstsq(lap, right, rcond=None)[0]


def harmonic_dense(g: SimilarityGraph, guard: int = DENSE_NODES) -> DataFrame:
    """(node_id, label): the unlabelled Laplacian block solved against the weights to class 1."""
    state, arcs = free_state(g)
    _check_dense(state.count(), guard)
    return _one_task(state, arcs, _solve_dense)


def harmonic_contracted(g: SimilarityGraph, guard: int = DENSE_NODES) -> DataFrame:
    """(node_id, label): each class contracted to one terminal with summed parallel edges, then the inverse of the small graph's block,
    rebuilt for every batch; the label is the share that reaches terminal 1."""
    state, arcs = free_state(g)
    _check_dense(state.count(), guard)

    def solve(ids, f, w0, w1, w_all, src, dst, w):
        lap = dense_system(ids, w_all, src, dst, w)
        inverse = np.linalg.pinv(lap) if np.linalg.matrix_rank(lap) < len(lap) else np.linalg.inv(lap)
        to0, to1 = inverse @ w0.astype(float), inverse @ w1.astype(float)
        total = to0 + to1
        return np.where(total > 1e-12, to1 / np.where(total > 1e-12, total, 1), f / SCALE)

    return _one_task(state, arcs, solve)


def harmonic_cg(g: SimilarityGraph, tol: float = 1e-8, max_rounds: int = 500, plan: str = "auto") -> DataFrame:
    """(node_id, label): conjugate gradients with the degree as preconditioner, the matrix only ever applied as a join over arcs.

    Small graphs run in one task; large ones keep the vectors as columns and send two sums a round to the driver."""
    from labelflow.operators.propagate import _fits

    parts = split(g, plan == "auto")
    state, arcs = start_state(parts), parts.arcs
    if plan == "auto" and _fits(arcs):
        return _one_task(state, arcs, lambda *a: cg_local(*a, tol=tol, rounds=max_rounds * 20))
    if plan == "auto" and parts.packed is not None:

        def solve(rows: Rows, cols: dict[str, np.ndarray]) -> pa.Table:
            label = cg_steps(rows.weighted, cols["f"], cols["w1"], cols["w_all"], tol, max_rounds * 20)
            return pa.table({"node_id": cols["node_id"], "label": label})

        return run_packed(parts.packed, state.select("node_id", "f", "w1", "w_all"), solve, "node_id long, label double", "cg")
    salts = salts_for(arcs, "src")
    x = materialise(state.filter("w_all > 0").select("node_id", "w_all", F.lit(0.5).alias("x"), F.col("w1").cast("double").alias("b")), "cg")

    def apply(v: DataFrame, col: str) -> DataFrame:
        seen = lookup(arcs, v.select(F.col("node_id").alias("dst"), F.col(col).alias("far")), ["dst"], "inner", "src", salts=salts)
        sums = seen.groupBy(F.col("src").alias("node_id")).agg(F.sum(F.col("w") * F.col("far")).alias("s"))
        return v.join(sums, "node_id", "left").withColumn("a", F.col("w_all") * F.col(col) - F.coalesce("s", F.lit(0.0))).drop("s")

    v = apply(x, "x").withColumn("r", F.col("b") - F.col("a")).withColumn("p", F.col("r") / F.col("w_all")).drop("a", "b")
    v = materialise(v, "cg")
    rz = v.agg(F.sum(F.col("r") * F.col("r") / F.col("w_all"))).first()[0] or 0.0
    stop = tol * tol * max(rz, 1e-300)
    for _ in range(max_rounds):
        if rz <= stop:
            break
        a = materialise(apply(v, "p"), "cg")
        alpha = rz / a.agg(F.sum(F.col("p") * F.col("a"))).first()[0]
        nxt = a.withColumn("x", F.col("x") + alpha * F.col("p")).withColumn("r", F.col("r") - alpha * F.col("a")).drop("a")
        new = nxt.agg(F.sum(F.col("r") * F.col("r") / F.col("w_all"))).first()[0]
        fresh = materialise(nxt.withColumn("p", F.col("r") / F.col("w_all") + (new / rz) * F.col("p")), "cg")
        release(v, a)
        v, rz = fresh, new
    lone = state.filter("w_all <= 0").select("node_id", (F.col("f") / SCALE).alias("label"))
    return v.select("node_id", F.col("x").alias("label")).unionByName(lone)


def cg_local(ids, f, w0, w1, w_all, src, dst, w, tol: float = 1e-10, rounds: int = 10_000):
    """The same iteration on arrays."""
    order = np.argsort(ids)
    s, d = order[np.searchsorted(ids[order], src)], order[np.searchsorted(ids[order], dst)]
    wt = w.astype(float)
    return cg_steps(lambda x: np.bincount(s, wt * x[d], len(ids)), f, w1, w_all, tol, rounds)


def cg_steps(weighted, f, w1, w_all, tol: float, rounds: int):
    """The same, given the sums of a vector over the neighbours by weight."""
    deg = np.where(w_all > 0, w_all, 1).astype(float)
    mul = lambda x: deg * x - weighted(x)
    b = np.where(w_all > 0, w1, f / SCALE).astype(float)
    x = np.full(len(f), 0.5)
    r = b - mul(x)
    p = r / deg
    rz = float(r @ (r / deg))
    stop = tol * tol * max(rz, 1e-300)
    for _ in range(rounds):
        if rz <= stop:
            break
        a = mul(p)
        alpha = rz / float(p @ a)
        x += alpha * p
        r -= alpha * a
        new = float(r @ (r / deg))
        p = r / deg + (new / rz) * p
        rz = new
    return x


def recompute_update(g: SimilarityGraph, ins: DataFrame | None = None, ins_edges: DataFrame | None = None, dels: DataFrame | None = None, solver: str = "dense") -> tuple[SimilarityGraph, DataFrame]:
    """Recompute-all baseline: applies the batch, then solves the whole graph anew."""
    if dels is not None:
        g = apply_deletes(g, dels)[0]
    if ins is not None:
        g = apply_inserts(g, ins, ins_edges)[0]
    return g, {"dense": harmonic_dense, "contracted": harmonic_contracted, "cg": harmonic_cg}[solver](g)


def eliminate(arcs: DataFrame, node_id: int) -> DataFrame:
    """Star-mesh elimination: the node leaves, every pair of its neighbours gains w_ui w_uj / sum w_ux; harmonic values of the rest stay.

    Weights become doubles. The pairs are of one node's neighbours, deg^2 of them: this is for retiring nodes of small degree."""
    own = materialise(arcs.filter(F.col("src") == node_id).select("dst", F.col("w").cast("double").alias("w")), "star")
    total = own.agg(F.sum("w")).first()[0] or 1.0
    a, b = own.select(F.col("dst").alias("src"), F.col("w").alias("wa")), own.select("dst", F.col("w").alias("wb"))
    mesh = a.join(F.broadcast(b), F.col("src") != F.col("dst")).select("src", "dst", (F.col("wa") * F.col("wb") / total).alias("w"))
    rest = arcs.filter((F.col("src") != node_id) & (F.col("dst") != node_id)).select("src", "dst", F.col("w").cast("double").alias("w"))
    return rest.unionByName(mesh).groupBy("src", "dst").agg(F.sum("w").alias("w"))
