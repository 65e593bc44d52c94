"""In-task kernels over a compressed row layout: the end of a long run, or one block of a large graph.

They compute exactly what the distributed superstep computes, in the same whole numbers, for as many steps as are left, inside one
task whose input is bounded by the caller.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np

SCALE = 1_000_000_000
#: Moves too small to accelerate.
FEW_UNITS = 16
#: Arcs that a kernel spreads out at once.
PIECE = 2_000_000


class Rows:
    """Arcs of unlabelled nodes sorted by source, with node ids replaced by places in the node table."""

    def __init__(self, node_ids: np.ndarray, src: np.ndarray, dst: np.ndarray, w: np.ndarray):
        order = np.argsort(node_ids)
        self.ids = node_ids[order]
        self.order = order
        s, d = np.searchsorted(self.ids, src), np.searchsorted(self.ids, dst)
        by = np.argsort(s, kind="stable")
        self.dst, self.w = d[by], w[by]
        self.at = np.searchsorted(s[by], np.arange(len(self.ids) + 1))

    @classmethod
    def packed(cls, ids: np.ndarray, at: np.ndarray, dst: np.ndarray, w: np.ndarray) -> Rows:
        """From a layout that is there: ids in the order of their places, row bounds, far places and weights."""
        rows = cls.__new__(cls)
        rows.ids, rows.order, rows.at, rows.dst, rows.w = ids, np.arange(len(ids)), at, dst, w
        return rows

    def pieces(self, nodes: np.ndarray) -> Iterator[tuple[int, int]]:
        """Bounds of runs of the nodes, each of at most PIECE arcs or one node."""
        ends = np.cumsum(self.at[nodes + 1] - self.at[nodes])
        a = 0
        while a < len(nodes):
            b = max(a + 1, int(np.searchsorted(ends, (ends[a - 1] if a else 0) + PIECE, "right")))
            yield a, b
            a = b

    def spread(self, nodes: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Arc places of the nodes' rows, and where each node's run starts among them."""
        size = self.at[nodes + 1] - self.at[nodes]
        ends = np.cumsum(size)
        starts = ends - size
        places = np.arange(int(ends[-1]) if len(ends) else 0) - np.repeat(starts, size) + np.repeat(self.at[nodes], size)
        return places, starts

    def weighted(self, x: np.ndarray) -> np.ndarray:
        """Sums of a vector of doubles over each node's neighbours by weight."""
        out = np.zeros(len(self.ids))
        for a, b in self.pieces(np.arange(len(self.ids))):
            lo, hi = self.at[a], self.at[b]
            if hi > lo:
                full = np.flatnonzero(self.at[a + 1 : b + 1] > self.at[a:b])
                out[a + full] = np.add.reduceat(self.w[lo:hi] * x[self.dst[lo:hi]], self.at[a:b][full] - lo)
        return out

    def sums(self, nodes: np.ndarray, f: np.ndarray) -> np.ndarray:
        """Weighted neighbour labels of each node."""
        out = np.zeros(len(nodes), np.int64)
        for a, b in self.pieces(nodes):
            part = nodes[a:b]
            places, starts = self.spread(part)
            if len(places):
                full = self.at[part + 1] > self.at[part]
                out[a:b][full] = np.add.reduceat(self.w[places] * f[self.dst[places]], starts[full])
        return out


def relaxed(rows: Rows, nodes: np.ndarray, f: np.ndarray, w1: np.ndarray, w_all: np.ndarray) -> np.ndarray:
    """The weighted average of a node's neighbours, rounded half up."""
    num = rows.sums(nodes, f) + w1[nodes] * SCALE
    den = w_all[nodes]
    return (2 * num + den) // (2 * den)


def frontier_steps(rows: Rows, f: np.ndarray, w1: np.ndarray, w_all: np.ndarray, hot: np.ndarray, delta: int, most: int, commit_small: bool = False, schedule: str = "sync", halo: np.ndarray | None = None) -> list[tuple[int, int, int, int]]:
    """Runs supersteps on f in place until no node is hot, or one of `halo` is, whose rows are not all here; per step: hot nodes, committed nodes, arcs touched, largest change.

    `two_phase` updates even ids first and lets odd ones see the result, which is nearer to updating in place."""
    steps = []
    while len(steps) < most:
        if halo is not None and np.any(hot & halo):
            break
        live = np.flatnonzero(hot & (w_all > 0))
        if not len(live):
            hot[:] = False
            break
        moved_parts, top, touched = [], 0, 0
        groups = [live] if schedule == "sync" else [live[rows.ids[live] % 2 == k] for k in (0, 1)]
        for nodes in groups:
            if not len(nodes):
                continue
            new = relaxed(rows, nodes, f, w1, w_all)
            change = np.abs(new - f[nodes])
            big = change > delta
            take = change > 0 if commit_small else big
            f[nodes[take]] = new[take]
            moved_parts.append(nodes[big])
            top = max(top, int(change.max()))
            touched += int((rows.at[nodes + 1] - rows.at[nodes]).sum())
        moved = np.concatenate(moved_parts) if moved_parts else live[:0]
        steps.append((len(live), len(moved), touched, top))
        hot[:] = False
        hot[moved] = True
        for a, b in rows.pieces(moved):
            places, _ = rows.spread(moved[a:b])
            hot[rows.dst[places]] = True
    return steps


def sweep_steps(rows: Rows, f: np.ndarray, w1: np.ndarray, w_all: np.ndarray, delta: int, most: int, accel: float | str = 0.0) -> list[tuple[int, int, int, int]]:
    """Full sweeps over all nodes until the largest change is at most delta.

    `accel` is a bound in (0, 1) of the sweep's spectral radius, or 'cheby', which takes the share of all weight that lies between
    unlabelled nodes (the Rayleigh quotient of the constant vector, so never too high); sweeps are combined by the Chebyshev recurrence. The averaging matrix has real eigenvalues below 1 in size,
    so a bound that is too low only slows it. Moves of a few units are left to plain sweeps, whose rounding settles."""
    nodes = np.flatnonzero(w_all > 0)
    steps, before, omega = [], f[nodes].copy(), 1.0
    rho = min(0.9999, float(rows.w.sum()) / max(1.0, float(w_all[nodes].sum()))) if accel == "cheby" else float(accel)
    if not 0 <= rho < 1:
        raise ValueError("accel is 'cheby' or a number from 0 up to 1")
    arcs = len(rows.dst)
    while len(steps) < most and len(nodes):
        now = f[nodes].copy()
        new = relaxed(rows, nodes, f, w1, w_all)
        if rho and np.abs(new - now).max() > FEW_UNITS:
            omega = 1 / (1 - rho * rho / 2) if omega == 1.0 else 1 / (1 - rho * rho * omega / 4)
            new = np.clip(np.rint(before + omega * (new - before)).astype(np.int64), 0, SCALE)
        change = np.abs(new - now)
        before = now
        f[nodes] = new
        top = int(change.max())
        steps.append((len(nodes), int((change > delta).sum()), arcs, top))
        if top <= delta:
            break
    return steps
