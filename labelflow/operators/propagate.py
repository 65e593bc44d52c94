"""Label iteration: the per-vertex update, full sweeps, and the frontier loop.

State is (node_id, f, w1, w_all) of unlabelled nodes, labels in whole units; arcs_free are the arcs whose both ends are unlabelled.
Ground truth enters through w1 and w_all only. These plans reach the same labels:

* `sync`    one distributed step at a time, one join and one pre-summed aggregation each. Arcs lie in folders by the hash of their
  source, of which a step reads those that hold hot nodes; it writes the labels that changed, as a small table over the written
  state, which takes them in when they have become many;
* `tail`    where all arcs fit TAIL_ARCS, one task finishes the run on a compressed row layout;
* `packed`  where all arcs are beyond that, but fit one task as four-byte places (PACKED_TIMES), many tasks pack them and one finishes the run;
* `ball`    where the rows of the hot nodes and of some rings around them fit, one task runs supersteps on them until the frontier
  reaches a node whose row it does not hold: the same labels, many supersteps for one pass over the arcs;
* `blocked` nodes are cut into blocks by hash; a stage sweeps every block several times against frozen outside values.

`auto` takes the tail when the whole graph is small enough, packed where the caller has it packed, else the ball when the frontier is small enough, else a step in sync.
"""

from __future__ import annotations

import time
from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from labelflow.functions.fixed import HALF, SCALE, rounded_div, units
from labelflow.operators.classweights import class_sums
from labelflow.operators.graph import SimilarityGraph
from labelflow.plans.joins import BROADCAST_ROWS, SALTS, lookup, salts_for, without
from labelflow.plans.local import Rows, frontier_steps, relaxed, sweep_steps
from labelflow.plans.packed import ARC_BYTES, NODE_BYTES, Packed, number, pack, run_packed
from labelflow.plans.stage import materialise, release

#: Arcs that one task may finish on its own: about 100 MB of them.
TAIL_ARCS = 2_000_000
#: Bytes of a packed graph that one task may hold, for each arc of the tail: 900 MB.
PACKED_TIMES = 450
MAX_STEPS = 100_000
#: Most rings of neighbours that a ball takes in around the frontier.
RINGS = 6
#: A node of more arcs makes a join key that is worth salting.
HUB_ARCS = 1_000_000
#: Arcs a folder is meant to hold, and the most folders.
ARCS_PER_BUCKET = 250_000
MOST_BUCKETS = 4_096
#: Changed labels beside the state, at most, before they are merged into it.
MOST_CHANGES = BROADCAST_ROWS


@dataclass
class Run:
    """Labels and the record of how they came about."""

    state: DataFrame
    steps: list[tuple[int, int, int, int]] = field(default_factory=list)  # frontier, committed, arcs touched, largest change
    seconds: float = 0.0
    plan: str = "sync"
    converged: bool = True
    hot: DataFrame | None = None  # (node_id) of the frontier that a next superstep would take; none of a full sweep

    @property
    def iterations(self) -> int:
        return len(self.steps)

    @property
    def updates(self) -> int:
        return sum(s[0] for s in self.steps)

    @property
    def arcs_touched(self) -> int:
        return sum(s[2] for s in self.steps)


def average_form(num: Column, f: Column, w1: Column, w_all: Column) -> Column:
    """The weighted average of the neighbours."""
    return rounded_div(num + w1 * SCALE, w_all)


def adjust_form(num: Column, f: Column, w1: Column, w_all: Column) -> Column:
    """The old label plus the weighted differences to the neighbours: f + (w0 (0 - f) + w1 (1 - f) + sum w (fv - f)) / w_all, the weights
    of all three kinds of neighbours adding up to w_all."""
    pull = (num + w1 * SCALE) - w_all * f
    shifted = rounded_div(pull + w_all * SCALE, w_all) - SCALE  # shifted so that the division is of a non-negative number
    return f + shifted


FORMS = {"average": average_form, "adjust": adjust_form}


def arc_counts(arcs: DataFrame) -> DataFrame:
    """(node_id, degree) of nodes with arcs; one aggregation, pre-summed per task."""
    return arcs.groupBy(F.col("src").alias("node_id")).agg(F.count("*").alias("degree"))


def hub_salts(degrees: DataFrame) -> int:
    """Salts that joins on the arcs' ends need: one where no node is a hub."""
    return SALTS if (degrees.agg(F.max("degree")).first()[0] or 0) > HUB_ARCS else 1


class Bucketed:
    """Arcs in folders by the hash of their source."""

    def __init__(self, arcs: DataFrame, n_arcs: int):
        self.buckets = max(1, min(MOST_BUCKETS, -(-n_arcs // ARCS_PER_BUCKET)))
        rows = arcs.select("src", "dst", "w", self._bucket("src").alias("bucket"))
        self.arcs = materialise(rows.repartition(self.buckets, "bucket").sortWithinPartitions("bucket", "src"), "bucketed-arcs", by="bucket")

    def _bucket(self, c: str) -> Column:
        return F.pmod(F.xxhash64(c), F.lit(self.buckets)).cast("int")

    def of(self, nodes: DataFrame) -> DataFrame:
        """The arcs in the folders of some nodes (node_id); at most MOST_BUCKETS folder numbers are collected."""
        held = [r.bucket for r in nodes.select(self._bucket("node_id").alias("bucket")).distinct().collect()]
        return (self.arcs if len(held) == self.buckets else self.arcs.filter(F.col("bucket").isin(held))).drop("bucket")


class Labels:
    """A written state and, over it, a small table of the labels that changed since."""

    def __init__(self, state: DataFrame):
        self.state, self.changes = state, None

    def view(self) -> DataFrame:
        if self.changes is None:
            return self.state
        return lookup(self.state, self.changes, ["node_id"], "left", "node_id", salts=1).select("node_id", F.coalesce("fresh", "f").alias("f"), "w0", "w1", "w_all")

    def put(self, fresh: DataFrame) -> None:
        """Takes in new labels (node_id, fresh)."""
        fresh = materialise(fresh.select("node_id", "fresh"), "fresh")
        was = self.changes
        self.changes = fresh if was is None else materialise(without(was, fresh.select("node_id"), ["node_id"]).unionByName(fresh), "changes")
        if was is not None:
            release(was, fresh)
        if self.changes.count() > MOST_CHANGES:
            self.state, spent = materialise(self.view(), "merged"), self.changes
            self.changes = None
            release(spent)


@dataclass(frozen=True)
class Split:
    """What a graph's labels depend on: unlabelled nodes (node_id), their weights (node_id, w0, w1, w_all, known: arcs to labelled nodes), arcs
    between unlabelled ones, and these packed where they were asked for and one task can hold them."""

    free: DataFrame
    weights: DataFrame
    arcs: DataFrame
    packed: Packed | None


def split(g: SimilarityGraph, packing: bool = False) -> Split:
    """Both ends of all arcs are looked up once. With `packing` the unlabelled nodes are numbered on the way, if the graph is too large for the tail."""
    if g.split is not None:
        return g.split
    free = materialise(g.nodes.filter("truth is null").select("node_id"), "free")
    n, n_arcs = free.count(), g.arcs.count() if packing else 0
    packing = TAIL_ARCS < n_arcs and n * NODE_BYTES < PACKED_TIMES * TAIL_ARCS
    numbered = materialise(number(free, n), "places") if packing else free.withColumn("place", F.lit(None).cast("int"))
    known = g.nodes.filter("truth is not null").select("node_id", F.col("truth").cast("int").alias("truth"), F.lit(False).alias("free"), F.lit(None).cast("int").alias("place"))
    ends = materialise(numbered.select("node_id", F.lit(None).cast("int").alias("truth"), F.lit(True).alias("free"), "place").unionByName(known), "ends")
    large = ends.count() > BROADCAST_ROWS
    salts = salts_for(g.arcs, "src") if large else 1  # both directions are there; a side that is broadcast needs none
    own = lookup(g.arcs.select("src", "dst", "w"), numbered.select(F.col("node_id").alias("src"), F.col("place").alias("ps")), ["src"], "inner", "dst", salts=salts)
    seen = lookup(own, ends.withColumnRenamed("node_id", "dst").withColumnRenamed("place", "pd"), ["dst"], "left", "src", salts=salts)
    seen = materialise(seen, "seen") if large else seen
    weights = materialise(class_sums(seen, F.count("truth").alias("known")), "weights")
    arcs = seen.filter("free").select("src", "dst", "w", "ps", "pd")
    packing = packing and TAIL_ARCS < (m := arcs.count()) and n * NODE_BYTES + m * ARC_BYTES <= PACKED_TIMES * TAIL_ARCS
    arcs = arcs if packing else materialise(arcs, "arcs-free")  # packed ones are read once
    return Split(free, weights, arcs.select("src", "dst", "w"), pack(arcs, numbered, n) if packing else None)


def start_state(parts: Split, f0: DataFrame | None = None, default: int = HALF) -> DataFrame:
    """State of a graph; f0 (node_id, f0) gives starting labels, others start at the default."""
    state = parts.free.join(parts.weights, "node_id", "left")
    if f0 is not None:
        state = state.join(f0.select("node_id", "f0"), "node_id", "left")
    else:
        state = state.withColumn("f0", F.lit(None).cast("long"))
    return materialise(state.select("node_id", F.coalesce("f0", F.lit(default)).cast("long").alias("f"), F.coalesce("w0", F.lit(0)).cast("long").alias("w0"), F.coalesce("w1", F.lit(0)).cast("long").alias("w1"), F.coalesce("w_all", F.lit(0)).cast("long").alias("w_all")), "state")


def free_state(g: SimilarityGraph, f0: DataFrame | None = None, default: int = HALF) -> tuple[DataFrame, DataFrame]:
    """(state, arcs_free) of a graph."""
    parts = split(g)
    return start_state(parts, f0, default), parts.arcs


def neighbour_sums(arcs: DataFrame, state: DataFrame, hot: DataFrame | None = None, weighted: bool = True, salts: int = SALTS) -> DataFrame:
    """(node_id, num): weighted neighbour labels of the hot nodes, of all where hot is None."""
    part = arcs if hot is None else lookup(arcs, hot.select(F.col("node_id").alias("src")), ["src"], "inner", "dst", salts=salts)
    seen = lookup(part, state.select(F.col("node_id").alias("dst"), F.col("f").alias("far")), ["dst"], "inner", "src", salts=salts)
    return seen.groupBy(F.col("src").alias("node_id")).agg(F.sum((F.col("w") if weighted else F.lit(1)) * F.col("far")).alias("num"))


def relax(state: DataFrame, arcs: DataFrame, hot: DataFrame | None = None, form: str = "average", salts: int = SALTS) -> DataFrame:
    """(state columns, new): the updated label of hot nodes, null for others and for nodes without neighbours."""
    sums = neighbour_sums(arcs, state, hot, salts=salts)
    rows = state.join(sums, "node_id", "left")
    if hot is not None:
        rows = rows.join(hot.select("node_id", F.lit(True).alias("is_hot")), "node_id", "left")
    else:
        rows = rows.withColumn("is_hot", F.lit(True))
    num = F.coalesce("num", F.lit(0))
    new = F.when(F.col("is_hot") & (F.col("w_all") > 0), FORMS[form](num, F.col("f"), F.col("w1"), F.col("w_all")))
    return rows.withColumn("new", new).drop("num", "is_hot")


def advance_frontier(arcs: DataFrame, committed: DataFrame, salts: int = SALTS) -> DataFrame:
    """Nodes that moved and their unlabelled neighbours."""
    near = lookup(arcs, committed.select(F.col("node_id").alias("src")), ["src"], "inner", "dst", salts=salts).select(F.col("dst").alias("node_id"))
    return committed.select("node_id").unionByName(near).distinct()


def _tail(state: DataFrame, arcs: DataFrame, hot: DataFrame | None, run) -> tuple[DataFrame, DataFrame, list]:
    """Finishes in one task and returns labels, the hot nodes it ended with, and the steps; the caller has checked that state and arcs are within TAIL_ARCS."""
    nodes = state if hot is None else state.join(hot.select("node_id", F.lit(True).alias("hot")), "node_id", "left")
    nodes = nodes.select(F.lit(0).alias("k"), "node_id", "f", "w0", "w1", "w_all", (F.coalesce("hot", F.lit(False)) if hot is not None else F.lit(True)).alias("hot"))
    links = arcs.select(F.lit(0).alias("k"), "src", "dst", "w")

    def finish(left: pa.Table, right: pa.Table) -> pa.Table:
        ids, f, w0, w1, w_all = (left[c].to_numpy().copy() for c in ("node_id", "f", "w0", "w1", "w_all"))
        if not len(ids):
            return pa.table({c: pa.array([], pa.int64()) for c in ("node_id", "f", "w0", "w1", "w_all", "a", "b", "c", "d")} | {"hot": pa.array([], pa.bool_())})
        rows = Rows(ids, *(right[c].to_numpy() for c in ("src", "dst", "w")))
        o = rows.order
        f, w0, w1, w_all, flags = f[o], w0[o], w1[o], w_all[o], left["hot"].to_numpy(zero_copy_only=False)[o]
        steps = run(rows, f, w1, w_all, flags)
        pad = [None] * len(ids)
        cols = [[*pad, *(s[i] for s in steps)] for i in range(4)]
        n = len(steps)
        ext = lambda x: pa.array([*x.tolist(), *([None] * n)], pa.int64())
        return pa.table({"node_id": ext(rows.ids), "f": ext(f), "w0": ext(w0), "w1": ext(w1), "w_all": ext(w_all), **{c: pa.array(v, pa.int64()) for c, v in zip("abcd", cols, strict=True)}, "hot": pa.array([*flags.tolist(), *([None] * n)], pa.bool_())})

    out = nodes.groupBy("k").cogroup(links.groupBy("k")).applyInArrow(finish, "node_id long, f long, w0 long, w1 long, w_all long, a long, b long, c long, d long, hot boolean")
    done = materialise(out, "tail")
    steps = [tuple(r) for r in done.filter("node_id is null").select("a", "b", "c", "d").collect()]  # one row a superstep
    return done.filter("node_id is not null").select("node_id", "f", "w0", "w1", "w_all"), done.filter("hot").select("node_id"), steps


def _packed(packed: Packed, state: DataFrame, hot: DataFrame | None, run) -> tuple[DataFrame, DataFrame, list]:
    """The same on a packed graph."""
    nodes = state if hot is None else state.join(hot.select("node_id", F.lit(True).alias("hot")), "node_id", "left")
    nodes = nodes.select("node_id", "f", "w0", "w1", "w_all", (F.coalesce("hot", F.lit(False)) if hot is not None else F.lit(True)).alias("hot"))

    def finish(rows: Rows, cols: dict[str, np.ndarray]) -> pa.Table:
        steps = run(rows, cols["f"], cols["w1"], cols["w_all"], cols["hot"])
        schema = pa.schema([(c, pa.int64()) for c in ("node_id", "f", "w0", "w1", "w_all")] + [("hot", pa.bool_())] + [(c, pa.int64()) for c in ("at", "a", "b", "c", "d")])
        known = pa.table({**cols, **{c: pa.nulls(len(rows.ids), pa.int64()) for c in ("at", "a", "b", "c", "d")}}).select(schema.names).cast(schema)
        taken = {c: pa.array([s[i] for s in steps], pa.int64()) for i, c in enumerate("abcd")} | {"at": pa.array(range(len(steps)), pa.int64())}
        blank = {f.name: pa.nulls(len(steps), f.type) for f in schema if f.name not in taken}
        return pa.concat_tables([known, pa.table({**blank, **taken}).select(schema.names)])

    done = run_packed(packed, nodes, finish, "node_id long, f long, w0 long, w1 long, w_all long, hot boolean, at long, a long, b long, c long, d long", "packed-run")
    steps = [tuple(r) for r in done.filter("node_id is null").orderBy("at").select("a", "b", "c", "d").collect()]  # one row a superstep
    return done.filter("node_id is not null").select("node_id", "f", "w0", "w1", "w_all"), done.filter("hot").select("node_id"), steps


def _fits(arcs: DataFrame) -> bool:
    return arcs.count() <= TAIL_ARCS


def _ball(stored: Bucketed, degrees: DataFrame, hot: DataFrame, salts: int) -> tuple[DataFrame, DataFrame] | None:
    """(inner nodes, all their arcs): the hot nodes and up to RINGS rings around them, as far as the arcs stay within TAIL_ARCS, which
    the degrees tell before any arc is read; None where not even the hot nodes' own arcs do."""
    inner, held = hot.select("node_id"), None
    for _ in range(RINGS):
        if (lookup(degrees, inner, ["node_id"], "inner", "node_id", salts=1).agg(F.sum("degree")).first()[0] or 0) > TAIL_ARCS:
            break
        rows = materialise(lookup(stored.of(inner), inner.select(F.col("node_id").alias("src")), ["src"], "inner", "dst", salts=salts).select("src", "dst", "w"), "ball")
        if held is not None:
            release(held[1])
        held = inner, rows
        wider = materialise(inner.unionByName(rows.select(F.col("dst").alias("node_id"))).distinct(), "ring")
        if wider.count() == inner.count():
            break
        inner = wider
    return held


def _ball_steps(state: DataFrame, ball: tuple[DataFrame, DataFrame], hot: DataFrame, run) -> tuple[DataFrame, DataFrame, list]:
    """Runs supersteps inside a ball; returns its changed labels (node_id, f), the hot nodes it ended with, and the steps."""
    inner, rows = ball
    members = materialise(inner.unionByName(rows.select(F.col("dst").alias("node_id"))).distinct(), "members")
    nodes = lookup(state, members, ["node_id"], "inner", "node_id", salts=1).join(hot.select("node_id", F.lit(True).alias("hot")), "node_id", "left").join(inner.select("node_id", F.lit(True).alias("inner")), "node_id", "left")
    nodes = nodes.select(F.lit(0).alias("k"), "node_id", "f", "w1", "w_all", F.coalesce("hot", F.lit(False)).alias("hot"), F.coalesce("inner", F.lit(False)).alias("inner"))

    def work(left: pa.Table, right: pa.Table) -> pa.Table:
        place = Rows(left["node_id"].to_numpy(), *(right[c].to_numpy() for c in ("src", "dst", "w")))
        f, w1, w_all = (left[c].to_numpy()[place.order] for c in ("f", "w1", "w_all"))
        flags, whole = (left[c].to_numpy(zero_copy_only=False)[place.order] for c in ("hot", "inner"))
        before, flags = f.copy(), flags.copy()
        steps = run(place, f, w1, w_all, flags, ~whole)
        out = np.flatnonzero((f != before) | flags)
        pad, n = [None] * len(out), len(steps)
        blank = [None] * n
        cols = {c: pa.array([*pad, *(s[i] for s in steps)], pa.int64()) for i, c in enumerate("abcd")}
        at = pa.array([*pad, *range(n)], pa.int64())
        return pa.table({"node_id": pa.array([*place.ids[out].tolist(), *blank], pa.int64()), "f": pa.array([*f[out].tolist(), *blank], pa.int64()), "hot": pa.array([*flags[out].tolist(), *blank], pa.bool_()), "at": at, **cols})

    links = rows.select(F.lit(0).alias("k"), "src", "dst", "w")
    done = materialise(nodes.groupBy("k").cogroup(links.groupBy("k")).applyInArrow(work, "node_id long, f long, hot boolean, at long, a long, b long, c long, d long"), "ball-steps")
    release(members)
    steps = [tuple(r) for r in done.filter("node_id is null").orderBy("at").select("a", "b", "c", "d").collect()]  # one row a superstep
    return done.filter("node_id is not null").select("node_id", "f"), done.filter("hot").select("node_id"), steps


def frontier_loop(state: DataFrame, arcs: DataFrame, hot: DataFrame, delta: float = 1e-4, plan: str = "auto", max_steps: int = MAX_STEPS, commit_small: bool = False, schedule: str = "sync", form: str = "average", packed: Packed | None = None) -> Run:
    """Re-averages hot nodes; a move above delta is committed and makes the node and its neighbours hot. Ends with no hot node, or after
    max_steps, which the run reports as not converged. `packed` holds the same arcs packed."""
    start, limit = time.monotonic(), units(delta)
    hot = materialise(lookup(hot.select("node_id").distinct(), state.filter("w_all > 0").select("node_id"), ["node_id"], "inner", "node_id", salts=1), "hot")
    steps: list[tuple[int, int, int, int]] = []
    used, degrees, salts, held, stored = "sync", None, SALTS, Labels(state), None
    if plan in ("auto", "tail") and _fits(arcs):
        state, hot, steps = _tail(state, arcs, hot, lambda rows, f, w1, w_all, flags: frontier_steps(rows, f, w1, w_all, flags, limit, max_steps, commit_small, schedule))
        return Run(state, steps, time.monotonic() - start, "tail", len(steps) < max_steps or not steps or steps[-1][1] == 0, hot)
    if plan == "auto" and packed is not None:
        state, hot, steps = _packed(packed, state, hot, lambda rows, f, w1, w_all, flags: frontier_steps(rows, f, w1, w_all, flags, limit, max_steps, commit_small, schedule))
        return Run(state, steps, time.monotonic() - start, "packed", len(steps) < max_steps or not steps or steps[-1][1] == 0, hot)
    if plan == "tail":
        raise ValueError(f"more than {TAIL_ARCS} arcs: the tail plan is for what one task can hold")
    while len(steps) < max_steps:
        n_hot = hot.count()
        if not n_hot:
            break
        if degrees is None:
            degrees = materialise(arc_counts(arcs), "degrees")
            total, most = degrees.agg(F.sum("degree"), F.max("degree")).first()
            salts = SALTS if (most or 0) > HUB_ARCS else 1
            stored = Bucketed(arcs, total or 0)
        ball = _ball(stored, degrees, hot, salts) if plan in ("auto", "ball") and schedule == "sync" else None
        if ball is not None:
            left = max_steps - len(steps)
            changed, hot, more = _ball_steps(held.view(), ball, hot, lambda rows, f, w1, w_all, flags, halo: frontier_steps(rows, f, w1, w_all, flags, limit, left, commit_small, "sync", halo))
            release(ball[1])
            steps += more
            used = "ball" if used == "ball" or len(steps) == len(more) else "sync+ball"
            held.put(changed.withColumnRenamed("f", "fresh"))
            continue
        moved, top = None, 0
        touched = lookup(degrees, hot, ["node_id"], "inner", "node_id", salts=1).agg(F.sum("degree")).first()[0] or 0
        for colour in (None,) if schedule == "sync" else (0, 1):
            part = hot if colour is None else materialise(hot.filter(F.pmod("node_id", F.lit(2)) == colour), "colour")
            now = held.view()
            sums = neighbour_sums(stored.of(part), now, part, salts=salts)
            rows = lookup(now, part, ["node_id"], "inner", "node_id", salts=1).join(sums, "node_id", "left")
            new = F.when(F.col("w_all") > 0, FORMS[form](F.coalesce("num", F.lit(0)), F.col("f"), F.col("w1"), F.col("w_all")))
            change = F.abs(F.col("new") - F.col("f"))
            stepped = materialise(rows.withColumn("new", new).select("node_id", F.col("new").alias("fresh"), change.alias("change")).filter("fresh is not null"), "step")
            held.put(stepped.filter(F.col("change") > (0 if commit_small else limit)))
            m = stepped.filter(F.col("change") > limit).select("node_id")
            moved = m if moved is None else moved.unionByName(m)
            top = max(top, stepped.agg(F.max("change")).first()[0] or 0)
        moved = materialise(moved, "moved")
        n_moved = moved.count()
        steps.append((n_hot, n_moved, int(touched), int(top)))
        hot = materialise(advance_frontier(stored.of(moved), moved, salts), "hot")
        if not n_moved:
            break
    done = held.state if held.changes is None else materialise(held.view(), "labels")
    return Run(done, steps, time.monotonic() - start, used, not steps or steps[-1][1] == 0 or len(steps) < max_steps, hot)


def full_sweep(state: DataFrame, arcs: DataFrame, delta: float = 1e-4, plan: str = "auto", max_steps: int = MAX_STEPS, form: str = "average", accel: float | str = 0.0, blocks: int | None = None, inner: int = 8, block_width: int | None = None, packed: Packed | None = None) -> Run:
    """Every node is re-averaged every round until no move exceeds delta. `accel` combines sweeps by the Chebyshev recurrence (tail plan only).

    Blocks are cut by hash, or by runs of `block_width` ids, which keeps neighbours together where ids follow arrival."""
    start, limit = time.monotonic(), units(delta)
    if plan == "blocked":
        return _blocked(state, arcs, limit, max_steps, blocks or 8, inner, start, block_width)
    if plan in ("auto", "tail") and _fits(arcs):
        state, _, steps = _tail(state, arcs, None, lambda rows, f, w1, w_all, _: sweep_steps(rows, f, w1, w_all, limit, max_steps, accel))
        return Run(state, steps, time.monotonic() - start, "tail", not steps or steps[-1][3] <= limit)
    if plan == "auto" and packed is not None:
        state, _, steps = _packed(packed, state, None, lambda rows, f, w1, w_all, _: sweep_steps(rows, f, w1, w_all, limit, max_steps, accel))
        return Run(state, steps, time.monotonic() - start, "packed", not steps or steps[-1][3] <= limit)
    if plan == "tail" or accel:
        raise ValueError(f"more than {TAIL_ARCS} arcs: neither the tail plan nor acceleration applies")
    steps = []
    n, n_arcs = state.filter("w_all > 0").count(), arcs.count()
    salts = hub_salts(arc_counts(arcs)) if n else SALTS
    while len(steps) < max_steps and n:
        rows = relax(state, arcs, None, form, salts)
        stepped = materialise(rows.select("node_id", F.coalesce("new", "f").alias("f"), "w0", "w1", "w_all", F.abs(F.col("new") - F.col("f")).alias("change")), "sweep")
        top, moved = stepped.agg(F.max("change"), F.count(F.when(F.col("change") > limit, 1))).first()
        state = stepped.drop("change")
        steps.append((n, moved, n_arcs, int(top or 0)))
        if (top or 0) <= limit:
            break
    return Run(state, steps, time.monotonic() - start, "sync", not steps or steps[-1][3] <= limit)


def _blocked(state: DataFrame, arcs: DataFrame, limit: int, max_steps: int, blocks: int, inner: int, start: float, block_width: int | None) -> Run:
    """Sweeps each block `inner` times in one task against the labels that other blocks had; then labels are exchanged."""

    def block(left: pa.Table, right: pa.Table) -> pa.Table:
        ids, f, w0, w1, w_all = (left[c].to_numpy().copy() for c in ("node_id", "f", "w0", "w1", "w_all"))
        if not len(ids):
            return pa.table({c: pa.array([], pa.int64()) for c in ("node_id", "f", "w0", "w1", "w_all", "change")})
        src, dst, w, far = (right[c].to_numpy() for c in ("src", "dst", "w", "far"))
        inside = np.isin(dst, ids)
        rows = Rows(ids, src[inside], dst[inside], w[inside])
        o = rows.order
        f, w0, w1, w_all = f[o], w0[o], w1[o], w_all[o]
        frozen = np.zeros(len(ids), np.int64)
        np.add.at(frozen, np.searchsorted(rows.ids, src[~inside]), w[~inside] * far[~inside])
        before, live = f.copy(), np.flatnonzero(w_all > 0)
        for _ in range(inner):
            num = rows.sums(live, f) + w1[live] * SCALE + frozen[live]
            f[live] = (2 * num + w_all[live]) // (2 * w_all[live])
        return pa.table({"node_id": rows.ids, "f": f, "w0": w0, "w1": w1, "w_all": w_all, "change": np.abs(f - before)})

    steps, n_arcs = [], arcs.count()
    place = (lambda c: F.xxhash64(c)) if block_width is None else (lambda c: F.floor(F.col(c) / block_width))
    key = lambda c: F.pmod(place(c), F.lit(blocks)).cast("int").alias("b")
    while len(steps) < max_steps:
        seen = lookup(arcs, state.select(F.col("node_id").alias("dst"), F.col("f").alias("far")), ["dst"], "inner", "src").withColumn("b", key("src"))
        out = state.withColumn("b", key("node_id")).groupBy("b").cogroup(seen.groupBy("b")).applyInArrow(lambda a, b: block(a, b), "node_id long, f long, w0 long, w1 long, w_all long, change long")
        stepped = materialise(out, "blocked")
        top, n = stepped.agg(F.max("change"), F.count("*")).first()
        state = stepped.drop("change")
        steps.append((n, n, inner * n_arcs, int(top or 0)))
        if (top or 0) <= limit:
            break
    return Run(state, steps, time.monotonic() - start, "blocked", not steps or steps[-1][3] <= limit)


def unweighted(arcs: DataFrame) -> DataFrame:
    """The same arcs with weight one."""
    return arcs.withColumn("w", F.lit(1).cast("long"))


def classify(labels: DataFrame, cutoff: float = 0.5, rule: str = "cutoff") -> DataFrame:
    """Adds `class`: 1 from the cutoff up. `mass` moves the cutoff to the mean label, for graphs whose labels pile up at one value."""
    if rule == "mass":
        mean = labels.agg(F.avg("f")).first()[0] or 0.0
        return labels.withColumn("class", F.when(F.col("f") >= mean, 1).otherwise(0))
    return labels.withColumn("class", F.when(F.col("f") >= units(cutoff), 1).otherwise(0))


def all_labels(g: SimilarityGraph, state: DataFrame) -> DataFrame:
    """(node_id, f, truth) of every node, the ground truth pinned."""
    pins = g.nodes.filter("truth is not null").select("node_id", (F.col("truth") * SCALE).cast("long").alias("f"), F.col("truth").cast("int").alias("truth"))
    return pins.unionByName(state.select("node_id", "f", F.lit(None).cast("int").alias("truth")))


__all__ = ["Run", "advance_frontier", "all_labels", "classify", "free_state", "frontier_loop", "full_sweep", "neighbour_sums", "relax", "relaxed", "release", "unweighted", "without"]
