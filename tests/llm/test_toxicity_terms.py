"""The toxicity model keeps every token that passes the tests, however many common ones there are."""

import numpy as np
import pyarrow as pa
import pytest

from labelflow.llm import toxicity


@pytest.fixture(scope="module")
def labelled(spark):
    rng = np.random.default_rng(3)
    rows, marks = [], []
    for i in range(600):
        words = [f"w{k}" for k in rng.choice(60, 50)]
        if i % 4 == 0:
            words[int(rng.integers(0, 50))] = "vile"
        rows.append((i, " ".join(words)))
        marks.append((i, int(i % 4 == 0)))
    return spark.createDataFrame(rows, "doc_id long, text string"), spark.createDataFrame(marks, "doc_id long, toxic int")


def test_common_words_do_not_crowd_out_a_rare_toxic_one(labelled):
    """60 words are more frequent in toxic documents than the one that tells."""
    whole = toxicity.train(*labelled)
    wide = toxicity.train(*labelled, shared_terms=20)
    assert b"vile" in whole.odds and wide == whole


def test_too_many_terms_are_refused(labelled):
    with pytest.raises(ValueError, match="tokens are selected"):
        toxicity.train(*labelled, most_terms=0)


def test_scoring_holds_few_texts_at_once_and_sends_each_once(labelled):
    docs = labelled[0]
    model = toxicity.ToxicityModel(odds={b"vile": 6.0}, weights=(-2.0, 1.0, 1.0, 1.0))
    batch = pa.table({"doc_id": list(range(2_500)), "text": [None, "vile words", "plain words"] * 833 + ["vile"]}).combine_chunks().to_batches()[0]
    out = list(toxicity._score_rows(model, "text", False)(iter([batch])))
    assert [b.num_rows for b in out] == [1_000, 1_000, 500]
    done = pa.Table.from_batches(out)
    assert done.select(["doc_id", "text"]) == pa.Table.from_batches([batch])
    assert len(set(done["_score"].to_pylist()[0::3][:-1])) == 1 and done["_score"][1].as_py() > done["_score"][2].as_py() == done["_score"][0].as_py()
    assert "_raw" not in toxicity.score(docs, model)._jdf.queryExecution().toString()
