"""The pipeline stage by stage on the smallest tables, each judged on its own input."""

import re
from collections import Counter

import corpus_pipeline
from labelflow.llm import toxicity
from labelflow.plans.stage import materialise
from tests.llm.test_near_copies import brute_gone

SF = "/root/testdata/sf0.001"


def words(text):
    low = (text or "").translate({c: c + 32 for c in range(65, 91)})
    return re.findall(r"[^\x00-\x2F\x3A-\x60\x7B-\x7F]+", low)


def test_stages(spark):
    docs = spark.read.parquet(f"{SF}/documents.parquet")
    outs = {}
    for name, stage in corpus_pipeline.STAGES:
        before, docs = docs, materialise(stage(spark, docs, SF), f"test-{name}")
        outs[name] = (before, docs)
        if name != "sharding":
            assert docs.columns == corpus_pipeline.COLUMNS
    before, after = outs["toxicity"]
    model = toxicity.train(before, spark.read.parquet(f"{SF}/labels.parquet"))
    scores = {r.doc_id: r._score for r in toxicity.score(before, model).collect()}
    assert {r.doc_id for r in after.collect()} == {i for i, s in scores.items() if s < 0.3}
    before, after = outs["near_duplicates"]
    texts = {r.doc_id: r.text for r in before.collect()}
    assert {r.doc_id for r in after.collect()} == set(texts) - set(brute_gone(texts))
    before, after = outs["decontamination"]
    grams = set()
    for r in spark.read.parquet(f"{SF}/benchmark.parquet").collect():
        w = words(r.text)
        grams |= {tuple(w[i : i + 10]) for i in range(max(1, len(w) - 9))} if w else set()
    leaks = {r.doc_id for r in before.collect() if any(tuple(w[i : i + n]) in grams for w in [words(r.text)] for n in {len(g) for g in grams} for i in range(len(w) - n + 1))}
    assert {r.doc_id for r in after.collect()} == {r.doc_id for r in before.collect()} - leaks
    before, after = outs["mixing"]
    had, has = {r.doc_id for r in before.collect()}, Counter(r.doc_id for r in after.collect())
    assert set(has) <= had and abs(sum(has.values()) - len(had)) < 5 * len(had) ** 0.5
    before, after = outs["sharding"]
    rows = after.collect()
    assert Counter(r.doc_id for r in rows) == Counter(r.doc_id for r in before.collect())
    assert {r.shard for r in rows} <= set(range(24))


def test_rows_that_repeat_an_id(spark):
    text = "one two three four five six seven eight nine ten eleven"
    docs = spark.createDataFrame([(1, text, "en", "a", 1), (1, text, "en", "a", 1), (2, text, "en", "a", 1), (None, text, "en", "a", 1), (3, None, None, None, None)], "doc_id long, text string, lang string, source string, n_chars long")
    kept = corpus_pipeline.drop_near_duplicates(spark, docs, SF).collect()
    assert sorted((r.doc_id is None, r.doc_id or 0) for r in kept) == [(False, 1), (False, 3), (True, 0)]
    assert corpus_pipeline.drop_near_duplicates(spark, docs.limit(0), SF).count() == 0
