"""Neighbour lists over all candidates and all terms, against brute force."""

from collections import defaultdict

from labelflow.core_queries import text_graph
from labelflow.operators import similarity
from labelflow.plans.stage import materialise
from labelflow.sources.tables import read

SF = "/root/testdata/sf0.001"


def test_heavy_buckets_lose_no_candidates(spark):
    """The registered planes and tables; buckets of over 20 rows are split, and nothing changes."""
    q = materialise(similarity.quantised(read(spark, SF, "embeddings")), "q")
    lists = lambda rows: {(r.u, r.v, r.sim) for r in rows}
    split = lists(similarity.lsh_knn(q, 5, planes=3, tables=16, bucket_rows=20).collect())
    assert split == lists(similarity.lsh_knn(q, 5, planes=3, tables=16, bucket_rows=1 << 30).collect())
    exact = lists(similarity.knn(similarity.dense_pairs(q), 5).collect())
    assert len(split & exact) >= 0.95 * len(exact)


def test_text_graph_is_the_neighbours_over_all_terms(spark):
    """All pairs of documents compared; the same when dealt over many blocks."""
    terms = materialise(similarity.tfidf(read(spark, SF, "documents").select("doc_id", "text")), "tfidf")
    vectors = defaultdict(dict)
    for r in terms.collect():
        vectors[r.node_id][r.term] = r.weight
    want, best = {}, {}
    for u, a in vectors.items():
        sims = sorted((-sum(x * b[t] for t, x in a.items() if t in b), v) for v, b in vectors.items() if v != u)
        best[u] = [-s for s, _ in sims[:5]]
        want |= {(min(u, v), max(u, v)): -s for s, v in sims[:5] if s < 0}
    got = {(r.src, r.dst): r.w for r in text_graph(spark, SF)[0].arcs.filter("src < dst").collect()}
    split = {(r.u, r.v): r.w for r in similarity.knn_edges(similarity.cosine_knn(terms, 5, block=30, columns=500), 5).collect()}
    assert got == split
    for pair in set(got) ^ set(want):  # only ties at the fifth place, within rounding
        s = got.get(pair, 0) / 1e6 or want[pair]
        assert any(abs(s - best[n][-1]) < 3e-6 for n in pair)
    assert all(abs(got[p] / 1e6 - want[p]) < 2e-6 for p in set(got) & set(want)) and len(set(got) & set(want)) > 0.95 * len(want)
