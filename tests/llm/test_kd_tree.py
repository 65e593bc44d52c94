"""The K-d tree against a walk over all rows in plain Python: widest dimension, order across each cut, bytes on each side."""

from __future__ import annotations

import random

import pytest

from labelflow.llm import sharding


def _key(row, node) -> tuple:
    return (row[f"d{node.dim}"], row["k1"], row["k2"])


def _walk(tree, node, rows, span, leaf_bytes, out):
    """Checks a node and its subtrees; out gets the shard of each rid."""
    if node.leaves == 1:
        out.update({r["rid"]: node.first for r in rows})
        return
    if rows:
        width = [(max(r[f"d{i}"] for r in rows) - min(r[f"d{i}"] for r in rows)) / s for i, s in enumerate(span)]
        assert width[node.dim] == max(width)
    cut = tuple(node.cut)
    left = [r for r in rows if _key(r, node)[: len(cut)] < cut]
    right = [r for r in rows if _key(r, node)[: len(cut)] >= cut]
    if rows:
        want = sum(r["size"] for r in rows) * (node.leaves // 2) / node.leaves
        got = sum(r["size"] for r in left)
        # the best cut by brute force: between any two rows in the order of the whole key
        best, at = abs(want), 0
        for r in sorted(rows, key=lambda r: _key(r, node)):
            at += r["size"]
            best = min(best, abs(want - at))
        assert abs(want - got) <= best + sharding.GROUP_TOLERANCE * leaf_bytes + 1
    _walk(tree, tree[2 * node.id], left, span, leaf_bytes, out)
    _walk(tree, tree[2 * node.id + 1], right, span, leaf_bytes, out)


@pytest.mark.parametrize(("shards", "bins"), [(2, sharding.BINS), (7, 32), (24, sharding.BINS)])
def test_tree_equals_a_walk_over_all_rows(spark, monkeypatch, shards, bins):
    monkeypatch.setattr(sharding, "BINS", bins)
    rng = random.Random(shards)
    words = ["alpha", "beta", "gamma", "été", "日本", "x"]
    docs = [(i, " ".join(rng.choices(words, k=rng.choice([0, 1, 5, 40, 300])))) for i in range(500)]
    docs += [(1000 + i, "the same passage, again and again") for i in range(300)] + [(2000, None), (2000, None), (None, "x")]
    dims = sharding.default_dims()
    rows = sharding.points(spark.createDataFrame(docs, "doc_id long, text string"), dims).cache()
    held = [r.asDict() for r in rows.collect()]
    tree = sharding.build_tree(rows, len(dims), shards)
    span = [max(1, max(r[f"d{i}"] for r in held) - min(r[f"d{i}"] for r in held)) for i in range(len(dims))]
    want: dict = {}
    _walk(tree, tree[1], held, span, sum(r["size"] for r in held) / shards, want)
    got = {r.rid: r.shard for r in rows.withColumn("shard", sharding.shard_column(tree)).collect()}
    assert got == want and set(got.values()) <= set(range(shards))
