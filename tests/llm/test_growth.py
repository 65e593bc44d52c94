"""Rows and memory of the operators' Python stages follow the input."""

import numpy as np
import pyarrow as pa

from labelflow.llm import near_copies, toxicity, window_index
from labelflow.plans.stage import ARROW_KEY


def test_near_copies_sends_few_rows_at_once_and_restores_the_setting(spark, monkeypatch):
    before, seen = spark.conf.get(ARROW_KEY), []
    monkeypatch.setattr(near_copies, "_near_copies", lambda docs, *_: seen.append(spark.conf.get(ARROW_KEY)))
    near_copies.near_copies(spark.range(1))
    assert seen == [str(near_copies.ROWS_AT_ONCE)] and spark.conf.get(ARROW_KEY) == before


def test_sources_are_packed_by_part():
    """3,000 sources in one batch make a row per part, and each source's hashes come once."""
    n = 3_000
    h = np.arange(n, dtype=np.uint64).repeat(2)
    docs = [(i, h[2 * i : 2 * i + 2].tobytes(), np.array([i, i], np.int64).tobytes()) for i in range(n)]
    batch = window_index._arrow(docs, window_index.FLAGS)
    rows = list(window_index._sources(8)(iter([batch, batch])))
    assert [r.num_rows for r in rows] == [8, 8]
    got = {}
    for k in range(8):
        group = pa.Table.from_batches(rows).filter(pa.compute.equal(pa.Table.from_batches(rows)["part"], k))
        for r in window_index._by_source((pa.scalar(k),), group).to_pylist():
            got[r["doc_id"]] = np.frombuffer(r["hashes"], np.uint64).tolist()
    assert got == {i: [i] for i in range(n)}


def test_equal_questions_of_a_batch_are_asked_once():
    """Twenty copies ask one source for the same words."""
    words = [f"w{k}".encode() for k in range(15)]
    h = window_index.window_hashes(window_index.word_hashes(words), 13)
    work = [{"hashes": h.tobytes(), "sources": np.zeros(len(h), np.int64).tobytes()}]
    one = pa.RecordBatch.from_pylist([{"key": i, "raw": b" ".join(words), "work": work} for i in range(1, 21)])
    rows = pa.Table.from_batches(list(window_index._digests(13, 16, 64)(iter([one])))).to_pylist()
    assert sum(len(r["hashes"]) // 8 for r in rows) == len(h)


def test_tokens_of_other_documents_are_counted_whatever_the_candidates():
    batch = pa.RecordBatch.from_arrays([pa.array([b"alpha beta", b"alpha"], pa.binary())], names=["_raw"])
    got = {r["token"]: r["n"] for out in toxicity._count_other(iter([batch])) for r in out.to_pylist()}
    assert got == {b"": 3, b"alpha": 2, b"^alph": 2, b"beta": 1}


def test_long_sets_that_differ_are_parted_before_they_travel():
    """Two sets of 6,000 hashes without a common one fill 2,048 bits; four bits a hash part them, and fold to a smaller width."""
    rng = np.random.default_rng(5)
    a, b = (rng.integers(0, 1 << 63, 6_000, dtype=np.uint64) for _ in range(2))
    near = np.concatenate([a[:5_700], b[:300]])
    sets = pa.RecordBatch.from_arrays([pa.array([1, 2, 3]), pa.array([x.tobytes() for x in (a, b, near)], pa.binary())], names=["sid", "hashes"])
    tall = {r["sid"]: r["tall"] for out in near_copies._tall(iter([sets])) for r in out.to_pylist()}
    pairs = pa.RecordBatch.from_pylist([{"u": u, "v": v, "x": tall[u], "y": tall[v], "both": 12_000} for u, v in ((1, 2), (1, 3))])
    wide = [near_copies.parity(x, near_copies.WIDE) for x in (a, b)]
    assert 9 * np.bitwise_count(wide[0] ^ wide[1]).sum(dtype=np.int64) <= 12_000
    assert [(r["u"], r["v"]) for out in near_copies._tall_alike(iter([pairs])) for r in out.to_pylist()] == [(1, 3)]
    assert (near_copies.folded(np.frombuffer(tall[1], np.int64), near_copies.WIDE // 64) == wide[0]).all()


def test_answers_carry_digests_alone_and_still_part_sources():
    """An answer takes 16 bytes a window and a question 24; the words of another source, or other words of the source, confirm nothing."""
    words = [f"w{k}".encode() for k in range(14)]
    h = window_index.window_hashes(window_index.word_hashes(words), 13)
    ask = lambda source: [{"hashes": h.tobytes(), "sources": np.full(len(h), source).tobytes()}]
    answer = [{"hashes": h.tobytes(), "sources": None}]
    text = b" ".join(words)

    def odd(*docs) -> list[bytes]:
        one = pa.RecordBatch.from_pylist([{"key": i, "raw": raw, "work": work} for i, raw, work in docs])
        rows = pa.Table.from_batches(list(window_index._digests(13, 1, 64)(iter([one]))))
        assert sum(len(r["hashes"] or b"") + len(r["digests"]) for r in rows.to_pylist()) == sum((24 if work is not answer else 16) * len(h) for _, raw, work in docs if raw == text)
        return [r["hashes"] for r in window_index._confirm((pa.scalar(0),), rows).to_pylist()]

    assert odd((5, text, ask(3)), (3, text, answer)) == []
    assert odd((5, text, ask(3)), (4, text, answer)) == [np.sort(h).tobytes()]
    assert odd((5, text, ask(3)), (3, b" ".join(words[::-1]), answer)) == [np.sort(h).tobytes()]
