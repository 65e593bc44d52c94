"""K-d tree sharding: recursive splits at distributed weighted medians along the widest metadata dimension.

Rows become points of long metadata dimensions with a weight, their bytes. A node of k leaves is split at the weighted quantile
that leaves whole leaves on both sides (the median where k is even), along the dimension of the widest range relative to the whole.
The quantile is found without sorting: the value range is cut into bins, weights are summed per bin in each task and
merged, and the bin that holds the cut is refined until it is small or a single value. Copies of one value are told apart
by the hash of the text, and copies of one text by the hash of the id, so equal texts stay together except where a cut must run
through them to keep the sizes near equal. All nodes of a level are refined by the same jobs.

Slots number a shard's rows from 0 without gaps: rows are dealt over slices by hash, numbered inside their slice, and offset by
the slices before.

Defined results: null texts have no bytes; null dimensions are the smallest value; fewer rows than shards leave shards empty;
rows that repeat stay rows of their own; other columns are ignored.
"""

from __future__ import annotations

import math
from dataclasses import dataclass, field

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from labelflow.llm.common import materialise, release

SHARDS = 24
BINS = 1024
#: A cut bin is refined until it holds less than this share of a leaf's bytes.
TOLERANCE = 0.0005
#: Copies of one text are not cut while they hold less than this share of a leaf's bytes.
GROUP_TOLERANCE = 0.02
ROW_OVERHEAD = 8
ROWS_PER_SLICE = 200_000
MOST_PASSES = 40


@dataclass
class Node:
    """A node of the tree: its leaves, and once split the dimension and the composite cut (rows below it go left)."""

    id: int
    first: int
    leaves: int
    dim: int = 0
    cut: list[int] = field(default_factory=list)  # per level of (dimension, text hash, id hash): the least key that goes right
    low: int = 0
    high: int = 0
    width: int = 1
    want: float = 0.0
    below: float = 0.0
    rows: int = 0  # rows between low and high that agree with the cut so far
    open: bool = False


def points(docs: DataFrame, dims: dict[str, Column]) -> DataFrame:
    """rid, doc_id, size, text_crc32, dimensions d0.., and the two hashes that break ties."""
    text = F.coalesce(F.col("text"), F.lit(""))
    smallest = F.lit(-(1 << 62))
    out = docs.select(
        F.monotonically_increasing_id().alias("rid"),
        F.col("doc_id").cast("long").alias("doc_id"),
        (F.octet_length(text) + ROW_OVERHEAD).cast("long").alias("size"),
        F.crc32(text.cast("binary")).alias("text_crc32"),
        F.shiftright(F.xxhash64(text), 2).alias("k1"),
        F.shiftright(F.xxhash64(F.col("doc_id").cast("long"), text), 2).alias("k2"),
        *[F.coalesce(c.cast("long"), smallest).alias(f"d{i}") for i, c in enumerate(dims.values())],
    )
    return out


def _case(nodes: list[Node], value, otherwise=None) -> Column:
    """A value per node id."""
    out = None
    for n in nodes:
        out = F.when(F.col("node") == n.id, value(n)) if out is None else out.when(F.col("node") == n.id, value(n))
    return out.otherwise(F.lit(otherwise))


def _key(n: Node, level: int) -> str:
    return f"d{n.dim}" if level == 0 else f"k{level}"


def _goes_left(n: Node, within: str = "") -> Column:
    """Lexicographic comparison of a row's composite key with the node's cut."""
    out = F.lit(False)
    for level in reversed(range(len(n.cut))):
        key = F.col(within + _key(n, level))
        out = (key < n.cut[level]) | ((key == n.cut[level]) & out)
    return out


def _prefix(n: Node) -> Column:
    """Rows whose key agrees with what is fixed of the cut so far."""
    out = F.lit(True)
    for level, v in enumerate(n.cut):
        out = out & (F.col(_key(n, level)) == v)
    return out


def _assign(rows: DataFrame, tree: dict[int, Node], live: list[int]) -> DataFrame:
    """The node of each row among the live ones, by walking the tree in one expression."""

    def walk(i: int) -> Column:
        n = tree.get(i)
        if n is None or not n.cut or n.open:
            return F.lit(i)
        return F.when(_goes_left(n), walk(2 * i)).otherwise(walk(2 * i + 1))

    return rows.withColumn("node", walk(1))


def _refine(rows: DataFrame, nodes: list[Node], leaf_bytes: float) -> None:
    """Finds the cuts of all nodes of a level together; a pass narrows every open one by a factor of BINS, or, once no more
    than BINS rows are left of it, weighs every value of its own."""
    for _ in range(MOST_PASSES):
        todo = [n for n in nodes if n.open]
        if not todo:
            return
        for n in todo:
            n.width = 1 if n.rows <= BINS else max(1, -(-(n.high - n.low + 1) // BINS))
        value = _case(todo, lambda n: F.col(_key(n, len(n.cut))))
        low, width = _case(todo, lambda n: F.lit(n.low)), _case(todo, lambda n: F.lit(n.width))
        inside = _case(todo, lambda n: _prefix(n) & (F.col(_key(n, len(n.cut))) >= n.low) & (F.col(_key(n, len(n.cut))) <= n.high), False)
        bins = rows.filter(F.col("node").isin([n.id for n in todo])).filter(inside).select("node", ((value - low) - F.pmod(value - low, width)).alias("step"), "size")
        found = bins.groupBy("node", "step").agg(F.sum("size").alias("size"), F.count("*").alias("rows")).collect()  # at most BINS rows a node
        by: dict[int, list] = {}
        for r in found:
            by.setdefault(r.node, []).append((r.step, r.size, r.rows))
        for n in todo:
            total, steps = n.below, sorted(by.get(n.id, []))
            if not steps:
                n.cut, n.open = [*n.cut, n.low], False
                continue
            for step, size, count in steps:
                if total + size >= n.want or step == steps[-1][0]:
                    break
                total += size
            at, stop = n.low + step, n.low + step + n.width - 1
            single = n.width == 1
            if total + size - n.want <= TOLERANCE * leaf_bytes and total + size >= n.want:
                n.cut, n.open = [*n.cut, stop + 1], False  # the whole bin goes left
            elif n.want - total <= TOLERANCE * leaf_bytes:
                n.cut, n.open = [*n.cut, at], False  # the whole bin goes right
            elif not single:
                n.low, n.high, n.below, n.rows = at, stop, total, count
            elif len(n.cut) == 1 and size <= GROUP_TOLERANCE * leaf_bytes:  # copies of one text, few enough to stay together
                n.cut, n.open = [*n.cut, at if n.want - total < total + size - n.want else at + 1], False
            elif len(n.cut) < 2:
                n.cut, n.below, n.rows = [*n.cut, at], total, count  # one value: go on by the next tie-breaker
                n.low, n.high = -(1 << 61), (1 << 61) - 1
            else:
                n.cut, n.open = [*n.cut, at if n.want - total < total + size - n.want else at + 1], False
    raise RuntimeError("a cut did not settle")


def build_tree(rows: DataFrame, n_dims: int, shards: int) -> dict[int, Node]:
    """Cuts of the K-d tree over (size, d0.., k1, k2). A few small aggregates a level; nothing is sorted or collected by row."""
    names = [f"d{i}" for i in range(n_dims)]
    tree = {1: Node(1, 0, shards)}
    span = None
    while True:
        level = [n for n in tree.values() if n.leaves > 1 and not n.cut]
        if not level:
            return tree
        here = _assign(rows, tree, [n.id for n in level])
        stats = {r.node: r for r in here.groupBy("node").agg(F.sum("size").alias("size"), F.count("*").alias("rows"), *[f(c).alias(f"{k}_{c}") for c in names for k, f in (("lo", F.min), ("hi", F.max))]).collect()}
        if span is None:
            root = stats.get(1)
            if root is None:
                return {}
            span = [max(1, root[f"hi_{c}"] - root[f"lo_{c}"]) for c in names]
            leaf_bytes = root["size"] / shards
        for n in level:
            s = stats.get(n.id)
            if s is None:  # no rows: any cut will do
                n.cut = [0]
            else:
                n.dim = max(range(n_dims), key=lambda i: (s[f"hi_{names[i]}"] - s[f"lo_{names[i]}"]) / span[i])
                n.low, n.high = s[f"lo_{names[n.dim]}"], s[f"hi_{names[n.dim]}"]
                n.want, n.rows, n.open = s["size"] * (n.leaves // 2) / n.leaves, s["rows"], True
            left = n.leaves // 2
            tree[2 * n.id] = Node(2 * n.id, n.first, left)
            tree[2 * n.id + 1] = Node(2 * n.id + 1, n.first + left, n.leaves - left)
        _refine(here, level, leaf_bytes)


def shard_column(tree: dict[int, Node], within: str = "") -> Column:
    def walk(i: int) -> Column:
        n = tree[i]
        if n.leaves == 1:
            return F.lit(n.first)
        return F.when(_goes_left(n, within), walk(2 * i)).otherwise(walk(2 * i + 1))

    return walk(1) if tree else F.lit(0)


def with_slots(rows: DataFrame, shard: str = "shard", key: str = "rid") -> DataFrame:
    """Adds `slot`: a gapless number from 0 inside the shard. `key` is unique; slices keep one hot shard out of one task."""
    spark = rows.sparkSession
    slices = max(1, -(-rows.count() // ROWS_PER_SLICE), int(spark.conf.get("spark.sql.shuffle.partitions")))
    cut = rows.withColumn("_slice", F.pmod(F.xxhash64(key), F.lit(slices)).cast("int"))
    counts = cut.groupBy(shard, "_slice").agg(F.count("*").alias("n"))
    before = counts.select(shard, "_slice", (F.sum("n").over(Window.partitionBy(shard).orderBy("_slice")) - F.col("n")).alias("_before"))  # a row per shard and slice
    inner = F.row_number().over(Window.partitionBy("_slice", shard).orderBy(key)) - 1
    return cut.withColumn("_inner", inner).join(F.broadcast(before), [shard, "_slice"]).withColumn("slot", (F.col("_inner") + F.col("_before")).cast("long")).drop("_slice", "_inner", "_before")


def default_dims() -> dict[str, Column]:
    """Dimensions taken from the text (bytes, code points per byte, first letters), so that copies lie on one point."""
    text = F.coalesce(F.col("text"), F.lit(""))
    start = F.conv(F.substring(F.hex(F.encode(F.substring(text, 1, 4), "UTF-8")), 1, 8), 16, 10).cast("long")
    return {"bytes": F.octet_length(text), "density": F.length(text).cast("long") * 1_000_000 / F.greatest(F.octet_length(text), F.lit(1)), "start": start}


def kd_shards(docs: DataFrame, shards: int = SHARDS, dims: dict[str, Column] | None = None) -> DataFrame:
    """doc_id, size, text_crc32, shard, slot. Pass dimensions such as source or date ranks to shard by those."""
    dims = dims or default_dims()
    rows = materialise(points(docs, dims), "points")
    tree = build_tree(rows, len(dims), shards)
    placed = materialise(rows.withColumn("shard", shard_column(tree)).select("rid", "doc_id", "size", "text_crc32", "shard"), "placed")
    release(rows)
    return with_slots(placed)


def assign_shards(docs: DataFrame, shards: int = SHARDS, dims: dict[str, Column] | None = None) -> DataFrame:
    """The documents with a column _shard: the tree is applied as one expression, and no text is moved."""
    dims = dims or default_dims()
    rows = materialise(points(docs, dims), "points")
    tree = build_tree(rows, len(dims), shards)
    release(rows)
    text = F.coalesce(F.col("text"), F.lit(""))
    keys = {"k1": F.shiftright(F.xxhash64(text), 2), "k2": F.shiftright(F.xxhash64(F.col("doc_id").cast("long"), text), 2)} | {f"d{i}": F.coalesce(c.cast("long"), F.lit(-(1 << 62))) for i, c in enumerate(dims.values())}
    return docs.withColumn("_key", F.struct(*[c.alias(k) for k, c in keys.items()])).withColumn("_shard", shard_column(tree, "_key.")).drop("_key")


def shards_for(docs: DataFrame, target_bytes: int) -> int:
    """Leaves so that each holds about the target bytes."""
    total = docs.agg(F.sum(F.coalesce(F.octet_length("text"), F.lit(0)) + ROW_OVERHEAD)).first()[0] or 0
    return max(1, math.ceil(total / target_bytes))
