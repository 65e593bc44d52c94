"""Near copies against the Jaccard similarity of all pairs."""

from itertools import combinations

import corpus_pipeline
import pytest

from labelflow.llm import near_copies
from labelflow.plans.stage import materialise

SF = "/root/testdata/sf0.001"


def shingles(text, k=5):
    words = [w for w in (text or "").encode().lower().split()]
    return {tuple(words[i : i + k]) for i in range(max(1, len(words) - k + 1))} if words else set()


def brute_gone(texts):
    """Ids that are not the least of their component of pairs of at least 0.8."""
    sets, root = {i: shingles(t) for i, t in texts.items()}, {i: i for i in texts}

    def find(x):
        while root[x] != x:
            x = root[x]
        return x

    for a, b in combinations(sorted(sets), 2):
        both = len(sets[a] & sets[b])
        if both and 9 * both >= 4 * (len(sets[a]) + len(sets[b])):
            x, y = sorted((find(a), find(b)))
            root[y] = x
    return {i: find(i) for i in root if find(i) != i}


def edited(n, every, tag):
    """n words, of which one in `every` is a word of this text alone."""
    return " ".join(f"{tag}x{i}" if every and i % every == every - 1 else f"w{i}" for i in range(n))


@pytest.mark.parametrize("block", [4096, 3])
def test_against_all_pairs(spark, block):
    rows = [(r.doc_id, r.text) for r in spark.read.parquet(f"{SF}/documents.parquet").collect()]
    rows += [(10_000 + k, edited(200, every, f"t{k}")) for k, every in enumerate((0, 0, 50, 70, 60, 80, 90, 100, 120, 150, 199, 40, 30))]
    rows += [(20_000, "a b"), (20_001, "A  b"), (20_002, None), (20_003, " "), (20_004, "a b c")]
    docs = spark.createDataFrame(rows, "doc_id long, text string").repartition(8)
    got = {r.doc_id: r.component_id for r in near_copies.near_copies(docs, block=block).collect()}
    want = brute_gone(dict(rows))
    assert got == want and 20_001 in want and 10_003 in want


def test_pipeline_leaves_no_pair_of_four_fifths(spark):
    docs = spark.read.parquet(f"{SF}/documents.parquet")
    for name, stage in corpus_pipeline.STAGES:
        docs = materialise(stage(spark, docs, SF), f"near-test-{name}")
        if name == "decontamination":
            break
    assert not brute_gone({r.doc_id: r.text for r in docs.collect()})
