"""Near-duplicate components against all-pairs brute force."""

from itertools import combinations

import numpy as np
import xxhash
from pyspark.sql import functions as F

from labelflow.llm import simhash

SF = "/root/testdata/sf0.001"


def brute_print(text, k=4):
    words = [w for w in __import__("re").split(r"[\x20\x09-\x0D]+", (text or "").translate({c: c + 32 for c in range(65, 91)})) if w]
    if not words:
        return 0
    grams = [" ".join(words[i : i + k]) for i in range(max(1, len(words) - k + 1))]
    hs = [xxhash.xxh64_intdigest(g.encode(), 42) for g in grams]
    return sum(1 << b for b in range(64) if 2 * sum(h >> b & 1 for h in hs) > len(hs))


def brute_components(prints, radius=4):
    root = {i: i for i in prints}

    def find(x):
        while root[x] != x:
            x = root[x]
        return x

    for a, b in combinations(sorted(prints), 2):
        if bin(prints[a] ^ prints[b]).count("1") <= radius:
            x, y = sorted((find(a), find(b)))
            root[y] = x
    return {i: find(i) for i in prints}


def test_documents_against_brute_force(spark):
    docs = spark.read.parquet(f"{SF}/documents.parquet")
    want = {r.doc_id: brute_print(r.text) for r in docs.collect()}
    comps = brute_components(want)
    got = {r.doc_id: (r.fingerprint, r.component_id) for r in simhash.near_duplicates(docs, slices=2).collect()}
    assert got == {i: (f"{want[i]:016x}", comps[i]) for i in want}


def test_hash_is_that_of_spark(spark):
    row = spark.range(1).select(F.xxhash64(F.lit("a b c d")).alias("h")).first()
    assert row.h & (2**64 - 1) == xxhash.xxh64_intdigest(b"a b c d", 42)


def test_planted_distances(spark):
    rng = np.random.default_rng(5)
    prints, nid = [], 0
    for _ in range(30):
        base = int(rng.integers(0, 2**63))
        for flips in (0, 1, 2, 3, 4, 5, 8):
            bits = rng.choice(64, flips, replace=False)
            x = base
            for b in bits:
                x ^= 1 << int(b)
            prints.append(x)
    signed = [(x - (1 << 64) if x >= 1 << 63 else x,) for x in set(prints)]
    nodes = spark.createDataFrame(signed, "print long")
    got = {r.print: r.root for r in simhash.joined_prints(nodes).collect()}
    want = brute_components({s[0] & (2**64 - 1): s[0] & (2**64 - 1) for s in signed})
    as_sets = lambda m: {frozenset(k & (2**64 - 1) for k in m if m[k] == r) for r in set(m.values())}
    assert as_sets(got) == as_sets(want)


def test_links_of_a_dense_group_are_linear(spark):
    """Prints within two flips of one base: all pairs are within the radius; the first pass leaves one root, later ones no link."""
    rng = np.random.default_rng(9)
    rows = {}
    for size in (100, 400):
        base, prints = int(rng.integers(0, 2**62)), set()
        while len(prints) < size:
            x = base
            for b in rng.choice(64, 2, replace=False):
                x ^= 1 << int(b)
            prints.add(x - (1 << 64) if x >= 1 << 63 else x)
        state = spark.createDataFrame([(x, x) for x in prints], "print long, root long").repartition(8)
        made = []
        for k, space in enumerate(simhash.spaces(4)):
            links = simhash._pass(state, size, 4, space)
            made.append(links.count())
            if k < 2:
                state = simhash._contracted(state, links)
        assert state.select("root").distinct().count() == 1 and made[2:] == [0] * 4
        rows[size] = sum(made)
    assert rows[100] <= 4 * 100 and rows[400] <= 4 * 400


def test_edge_cases(spark):
    rows = [(1, None, "x"), (2, "", "x"), (3, " \n", "x"), (None, "one two", "x"), (5, "one two", "x"), (5, "one two", "x"), (6, "ONE\ttwo", None), (7, "w " * 50_000, None)]
    docs = spark.createDataFrame(rows, "doc_id long, text string, print string")
    got = simhash.near_duplicates(docs).collect()
    assert len(got) == len(rows)
    by = {r.doc_id: r for r in got}
    assert by[1].fingerprint == by[2].fingerprint == by[3].fingerprint == "0" * 16 and by[3].component_id == 1
    assert by[5].fingerprint == by[6].fingerprint and by[6].component_id == 5
    assert simhash.near_duplicates(docs.limit(0)).count() == 0
