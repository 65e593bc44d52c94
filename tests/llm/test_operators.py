"""Training-data operators against brute force, round trips and odd inputs: nulls, empty and long texts, ties, repeats, empty
tables, and extra columns whose names clash."""

import hashlib
import io
import re
import zlib
from collections import Counter, defaultdict

import numpy as np
import pytest
import xxhash
from pyspark.sql import functions as F

from labelflow.llm import chat_format, decontaminate, exact_dedup, language_id, mixing, sharding, toxicity, web_archive, window_index

SF = "/root/testdata/sf0.001"
DOCS = "doc_id long, text string, lang string, source string, n_chars long, extra string"
SPACE = "[\x20\x09-\x0d]"


def docs_of(spark, rows):
    full = [(i, t, "en", "src0", None if t is None else len(t), "x") for i, t in rows]
    return spark.createDataFrame(full, DOCS)


# ---- exact dedup ----------------------------------------------------------------------------------------------------


def test_chunk_hashes_combine():
    rng = np.random.default_rng(1)
    data = rng.integers(0, 256, 300_001, dtype=np.uint8).tobytes()
    whole = exact_dedup.fingerprint(data)
    for cut in (0, 1, 65_535, 65_536, 123_456, len(data)):
        parts = []
        for piece in (data[:cut], data[cut:]):
            h = (0, 0)
            for at in range(0, len(piece), exact_dedup.CHUNK):
                p = piece[at : at + exact_dedup.CHUNK]
                h = exact_dedup.combine(h, exact_dedup.chunk_hash(p), len(p))
            parts.append(h)
        assert exact_dedup.pack(exact_dedup.combine(parts[0], parts[1], len(data) - cut)) == whole
    assert exact_dedup.fingerprint(b"\x00") != exact_dedup.fingerprint(b"\x00\x00")


def test_exact_dedup_odd_rows(spark):
    rows = [(1, "a b"), (2, "ab"), (3, " ab \n"), (4, None), (5, ""), (6, " \t"), (7, "x" * 200_000), (8, "x" * 100_000 + "\n" + "x" * 100_000), (None, "ab"), (9, "q"), (9, "q"), (10, "é b"), (11, "éb")]
    got = exact_dedup.exact_dedup(docs_of(spark, rows)).collect()
    assert len(got) == len(rows)
    groups = defaultdict(list)
    for r in got:
        groups[r.text_sha256].append(r)
    for sha, members in groups.items():
        assert all(m.group_size == len(members) for m in members) and sum(m.kept for m in members) == 1
    by = {r.doc_id: r for r in got}
    assert by[1].keep_id == by[2].keep_id == by[None].keep_id == 3
    assert by[4].keep_id == by[5].keep_id == 6 and by[7].keep_id == 8 and by[11].keep_id == 10
    assert by[2].text_sha256 == hashlib.sha256(b"ab").hexdigest()
    assert exact_dedup.exact_dedup(docs_of(spark, rows[:1]).limit(0)).count() == 0


def test_huge_documents_go_in_parallel(spark):
    text = "abc é\n" * 50_000
    rows = spark.createDataFrame([(1, text), (2, text + "z")], "rid long, text string")
    got = {r.rid: r.print_of_parts for r in exact_dedup.parallel_fingerprints(rows, 70_001).collect()}
    norm = lambda t: re.sub(SPACE, "", t).encode()
    assert got == {1: exact_dedup.fingerprint(norm(text)), 2: exact_dedup.fingerprint(norm(text + "z"))}


def test_collisions_split_into_groups(spark, monkeypatch):
    """With every fingerprint the same, the chunk comparison alone must find the groups."""
    docs = docs_of(spark, [(1, "aa"), (2, "bb"), (3, "aa"), (4, "cc"), (5, "bb")])
    real = exact_dedup.fingerprints
    monkeypatch.setattr(exact_dedup, "fingerprints", lambda d: real(d).withColumn("print", F.lit(7).cast("long")))
    got = {r.doc_id: r.keep_id for r in exact_dedup.exact_dedup(docs).collect()}
    assert got == {1: 1, 2: 2, 3: 1, 4: 4, 5: 2}


# ---- substring dedup ------------------------------------------------------------------------------------------------


def brute_removed(rows, width):
    seen, out = {}, {}
    for i, t in rows:
        words = [w for w in re.split(SPACE + "+", t or "") if w]
        for a in range(len(words) - width + 1):
            seen.setdefault(tuple(words[a : a + width]), set()).add(i)
    for i, t in rows:
        words = [w for w in re.split(SPACE + "+", t or "") if w]
        gone = set()
        for a in range(len(words) - width + 1):
            if min(seen[tuple(words[a : a + width])]) < i:
                gone |= set(range(a, a + width))
        out[i] = (len(words), len(gone), hashlib.sha256(" ".join(w for k, w in enumerate(words) if k not in gone).encode()).hexdigest())
    return out


@pytest.mark.parametrize("batches", [1, 3])
def test_windows_against_brute_force(spark, batches):
    rng = np.random.default_rng(4)
    vocab = [f"w{k}" for k in range(3)]
    rows = [(int(i), " ".join(rng.choice(vocab, int(rng.integers(0, 60))))) for i in rng.permutation(40)]
    rows += [(100, None), (101, ""), (102, "w0 " * 4000), (103, "W0 w0\tw1\nw2")]
    got = {r.doc_id: (r.n_words, r.n_removed, r.kept_sha256) for r in window_index.substring_dedup(docs_of(spark, rows), batches, 5).collect()}
    assert got == brute_removed(rows, 5)


def test_index_compacts_and_reopens(spark):
    rng = np.random.default_rng(6)
    rows = [(i, " ".join(rng.choice(["a", "b"], 30))) for i in range(24)]
    index = window_index.WindowIndex(spark, 16, 6, fanout=2)
    flags = None
    for b in range(4):
        part = index.ingest(docs_of(spark, rows[6 * b : 6 * b + 6]))
        index = window_index.WindowIndex.open(spark, index.path, index.manifest()) if b == 1 else index
        index.fanout = 2
        flags = part if flags is None else flags.unionByName(part)
    assert len(index.runs) <= 2 and index.compactions >= 1
    sure = window_index.verified(docs_of(spark, rows), flags, 16, 6)
    got = {r.doc_id: (r.n_words, r.n_removed, r.kept_sha256) for r in window_index.remove_flagged(docs_of(spark, rows), sure, 6).collect()}
    assert got == brute_removed(rows, 6)
    index.drop()


@pytest.mark.parametrize("bits", [3, 7])
def test_equal_hashes_of_other_words(spark, bits):
    """Few hash bits: most matches are of other words, and the words alone must decide."""
    rng = np.random.default_rng(11)
    rows = [(i, " ".join(rng.choice(["a", "b", "c"], int(rng.integers(0, 25))))) for i in range(40)]
    got = {r.doc_id: (r.n_words, r.n_removed, r.kept_sha256) for r in window_index.substring_dedup(docs_of(spark, rows), 4, 5, bits=bits).collect()}
    assert got == brute_removed(rows, 5)


def test_the_registered_number_of_batches_compacts(spark, monkeypatch):
    """`substring_dedup` with its defaults merges runs before its last batch."""
    made = []
    real = window_index.WindowIndex.compact
    monkeypatch.setattr(window_index.WindowIndex, "compact", lambda self: (real(self), made.append(self.compactions)))
    rows = [(i, f"x{i} " + "to be or not to be that is the question now " * (i % 3)) for i in range(40)]
    got = {r.doc_id: r.n_removed for r in window_index.substring_dedup(docs_of(spark, rows)).collect()}
    assert made == [1] and got == {i: n for i, (_, n, _) in brute_removed(rows, 13).items()}


def test_windows_of_null_and_repeated_ids(spark):
    text = "one two three four five six"
    rows = [(None, text), (3, text), (3, text + " seven"), (5, "zero " + text), (None, text), (6, None), (7, "three four five six seven")]
    got = sorted(((r.doc_id is not None, r.doc_id or 0, r.n_words, r.n_removed) for r in window_index.substring_dedup(docs_of(spark, rows), 2, 4).collect()))
    assert got == [(False, 0, 6, 0), (False, 0, 6, 0), (True, 3, 6, 6), (True, 3, 7, 6), (True, 5, 7, 6), (True, 6, 0, 0), (True, 7, 5, 5)]
    assert window_index.substring_dedup(docs_of(spark, rows).limit(0)).count() == 0


def test_a_repeated_attempt_leaves_the_run_that_is_there(tmp_path):
    path = f"file://{tmp_path}/run"
    h, d = np.array([1, 5, 9], np.uint64), np.array([7, 3, 4], np.int64)
    for _ in range(2):
        window_index._write_run(path, 0, h, d)
    assert [x.tolist() for x in window_index._read_run(path, 0)] == [h.tolist(), d.tolist()]
    assert len(list((tmp_path / "run").iterdir())) == 1


def test_settle_names_the_smallest_document():
    h, d = np.array([5, 5, 5, 9], np.uint64), np.array([7, 3, 4, 8], np.int64)
    uh, ud, beaten, sources = window_index.settle(h, d)
    assert (uh.tolist(), ud.tolist()) == ([5, 9], [3, 8]) and sorted(zip(beaten.tolist(), sources.tolist(), strict=True)) == [(0, 3), (2, 3)]
    hit, old = window_index.present(uh, np.array([5, 6], np.uint64), np.array([2, 3]))
    assert hit.tolist() == [True, False] and old.tolist() == [2]



# ---- decontamination ------------------------------------------------------------------------------------------------


def test_decontamination_odd_rows(spark):
    items = spark.createDataFrame([(1, "One two three"), (2, None), (3, "..."), (11, "a b c d e f g h i j k l"), (12, "a b c d e f g h i j"), (None, "zz yy")], "item_id long, text string")
    rows = [(1, "x ONE, two; three y"), (2, "one two"), (3, None), (4, ""), (5, "a b c d e f g h i j k l a b c d e f g h i j"), (6, "!!one two three one two three!"), (7, "b c d e f g h i j k"), (7, "none"), (None, "zz yy"), (8, "É one two three É")]
    docs = docs_of(spark, rows)
    got = decontaminate.decontaminate(docs, items).collect()
    assert len(got) == len(rows)
    tell = {(r.doc_id, r.n_words): (r.n_hit, r.n_items, list(r["items"])) for r in got}
    assert tell[(1, 5)] == (3, 1, ["1"]) and tell[(2, 2)] == (0, 0, []) and tell[(3, 0)] == (0, 0, [])
    assert tell[(5, 22)] == (22, 2, ["11", "12"]) and tell[(6, 6)] == (6, 1, ["1"]) and tell[(7, 10)] == (10, 1, ["11"])
    assert tell[(7, 1)] == (0, 0, []) and tell[(None, 2)][0] == 2 and tell[(8, 5)] == (3, 1, ["1"])
    assert decontaminate.decontaminate(docs.limit(0), items).count() == 0
    assert decontaminate.decontaminate(docs, items.limit(0)).filter("contaminated").count() == 0


def test_proximity(spark):
    docs = docs_of(spark, [(1, "red a b blue c green"), (2, "red " + "x " * 20 + "blue green"), (3, "Green blue RED"), (4, None)])
    queries = spark.createDataFrame([(7, "red blue green"), (8, "absent red")], "query_id long, text string")
    got = {(r.query_id, r.doc_id): r.n for r in decontaminate.proximity_matches(decontaminate.build_index(docs), queries, 6).collect()}
    assert got == {(7, 1): 1, (7, 3): 1}


def test_proximity_against_brute_force(spark):
    """One index answers two query sets; places of the rarest term that lie in a run of `span` words with all others."""
    rng = np.random.default_rng(8)
    rows = [(i, " ".join(rng.choice(list("abcdefgh"), int(rng.integers(0, 60)), p=[0.3, 0.2, 0.2, 0.1, 0.1, 0.05, 0.03, 0.02]))) for i in range(30)]
    index = decontaminate.build_index(docs_of(spark, rows))
    texts = {i: t.split() for i, t in rows}
    total = Counter(w for t in texts.values() for w in t)
    for asked, span in (({1: "a h", 2: "c d e", 3: "f"}, 4), ({4: "a b c d g", 5: "h absent"}, 9)):
        queries = spark.createDataFrame(list(asked.items()), "query_id long, text string")
        got = {(r.query_id, r.doc_id): r.n for r in decontaminate.proximity_matches(index, queries, span).collect()}
        want = Counter()
        for q, words in ((q, t.split()) for q, t in asked.items()):
            rarest = min(words, key=lambda w: (total[w], words.index(w)))  # noqa: B023
            for i, t in texts.items():
                for p in (p for p, w in enumerate(t) if w == rarest):
                    want[q, i] += any(set(words) <= set(t[max(s, 0) : s + span]) for s in range(p - span + 1, p + 1))
        assert got == {k: n for k, n in want.items() if n}


# ---- archives -------------------------------------------------------------------------------------------------------


@pytest.mark.parametrize("zip64", [False, True])
def test_packages_are_zip_files(zip64):
    import zipfile

    raw = io.BytesIO()
    w = web_archive.PackageWriter(raw, zip64)
    for name, body in (("a/x", b"12345"), ("b/é", b""), ("c", b"abc" * 1000)):
        w.begin(name)
        w.write(body)
        w.end()
    w.close()
    with zipfile.ZipFile(io.BytesIO(raw.getvalue())) as z:
        assert z.testzip() is None and z.read("c") == b"abc" * 1000
    p = web_archive.PackageReader(raw, len(raw.getvalue()))
    assert p.read("a/x") == b"12345" and p.read("c", 3, 3) == b"abc" and set(p.members) == {"a/x", "b/é", "c"}


def test_reads_archives_of_others():
    import zipfile

    raw = io.BytesIO()
    with zipfile.ZipFile(raw, "w", zipfile.ZIP_STORED) as z:
        z.writestr("archive/data.warc.gz", web_archive.warc_record(5, "http://x/", "00", 2, "response", None, b"hi"))
        z.comment = b"a comment"
    p = web_archive.PackageReader(raw, len(raw.getvalue()))
    head, _, body = web_archive.parse_record(p.read("archive/data.warc.gz"))
    assert body == b"hi" and head["WARC-Target-URI"] == "http://x/"


def test_round_trip_of_pages(spark):
    big = "<p>é" * 400
    rows = [(1, "http://a/", big), (2, "http://b/", big), (3, None, big), (4, "http://c/\n d", None), (5, "u", ""), (6, "u", "small"), (7, "u", "small"), (None, None, big + "z")]
    pages = spark.createDataFrame([(*r, "x") for r in rows], "page_id long, url string, html string, payload string")
    got = {r.page_id: r for r in web_archive.round_trip(pages).collect()}
    assert len(got) == len(rows)
    for i, _, html in rows:
        raw = (html or "").encode()
        assert got[i].payload_bytes == len(raw) and got[i].payload_digest == hashlib.sha1(raw).hexdigest()
    assert {i: (r.record_type, r.refers_to) for i, r in got.items() if i in (1, 2, 3)} == {1: ("revisit", 3), 2: ("revisit", 3), 3: ("response", None)}
    assert all(got[i].record_type == "response" for i in (4, 5, 6, 7, None))
    assert web_archive.round_trip(pages.limit(0)).count() == 0


# ---- sharding -------------------------------------------------------------------------------------------------------


def test_shards_hold_near_equal_bytes(spark):
    docs = spark.read.parquet("/root/testdata/sf0.01/documents.parquet")
    hot = docs.limit(1).select("text").crossJoin(spark.range(5000, 5500)).select(F.col("id").alias("doc_id"), "text")
    rows = docs.select("doc_id", "text").unionByName(hot).collect()
    got = sharding.kd_shards(spark.createDataFrame(rows, "doc_id long, text string"), 7).collect()
    want = {r.doc_id: r.text or "" for r in rows}
    assert sorted(r.doc_id for r in got) == sorted(want)
    size, slots = Counter(), defaultdict(list)
    for r in got:
        raw = want[r.doc_id].encode()
        assert r["size"] == len(raw) + 8 and r.text_crc32 == zlib.crc32(raw)
        size[r.shard] += r["size"]
        slots[r.shard].append(r.slot)
    assert set(size) == set(range(7)) and max(size.values()) < 1.05 * min(size.values())
    assert all(sorted(s) == list(range(len(s))) for s in slots.values())


def test_shards_of_odd_tables(spark):
    docs = docs_of(spark, [(1, None), (1, None), (None, ""), (2, "abc"), (3, "y" * 100_000)])
    got = sharding.kd_shards(docs, 4).collect()
    assert len(got) == 5 and all(0 <= r.shard < 4 for r in got)
    assert sharding.kd_shards(docs.limit(0), 4).count() == 0
    assert sharding.assign_shards(docs, 4).count() == 5


# ---- mixing ---------------------------------------------------------------------------------------------------------


def test_mix_meets_its_weights(spark):
    docs = spark.range(20_000).select(F.col("id").alias("doc_id"), F.when(F.col("id") % 3 == 0, "hot").when(F.col("id") % 3 == 1, "cold").alias("source"))
    weights = spark.createDataFrame([("hot", 1.0), ("cold", 3.0), (None, 1.0)], "source string, weight double")
    got = {r.source: r["count"] for r in mixing.mix(docs, weights, 50_000).groupBy("source").count().collect()}
    for source, want in (("hot", 10_000), ("cold", 30_000), (None, 10_000)):
        assert abs(got[source] - want) < 5 * want**0.5
    one = mixing.mix(docs, weights, 400.0 * 20_000).filter("doc_id = 7").count()  # a rate beyond one inversion
    again = mixing.mix(docs, weights, 400.0 * 20_000).filter("doc_id = 7").count()
    assert one == again and abs(one - 720) < 5 * 720**0.5


def test_mix_of_odd_tables(spark):
    docs = spark.createDataFrame([(1, "a", "t"), (1, "a", "t"), (None, None, None), (2, "none", "u")], "doc_id long, source string, text string")
    got = mixing.mix(docs, spark.createDataFrame([("a", 1.0), ("none", -1.0)], "source string, weight double"), 40.0).collect()
    assert {r.source for r in got} == {"a"} and set(Counter(r._copy for r in got).values()) == {2}
    assert mixing.mix(docs.limit(0)).count() == 0


# ---- scoring --------------------------------------------------------------------------------------------------------


def test_segments_against_brute_force():
    """The definition: best segments by recursion, each the best of what lies left and right of the best."""
    rng = np.random.default_rng(2)

    def best(scores, off):
        top, spot = 0.0, None
        for a in range(len(scores)):
            total = 0.0
            for b in range(a, len(scores)):
                total += scores[b]
                if total > top + 1e-12:
                    top, spot = total, (a, b)
        if spot is None:
            return []
        a, b = spot
        return [*best(scores[:a], off), (off + a, off + b, round(top, 6)), *best(scores[b + 1 :], off + b + 1)]

    for _ in range(60):
        n = int(rng.integers(1, 25))
        hits = [(i, float(rng.integers(1, 90)) / 7) for i in range(n) if rng.random() < 0.4]
        scores = [-1.3] * n
        for i, s in hits:
            scores[i] = s
        got = [(a, b, round(s, 6)) for a, b, s in toxicity.maximal_segments(hits, 1.3)]
        assert got == best(scores, 0)


def test_toxicity_learns_and_takes_odd_rows(spark):
    rng = np.random.default_rng(8)
    plain = [f"word{k}" for k in range(200)]
    rows, marks = [], []
    for i in range(400):
        words = list(rng.choice(plain, 40))
        bad = i % 5 == 0
        if bad:
            for _ in range(4):
                words[int(rng.integers(0, 40))] = str(rng.choice(["vilest", "rotten", "filthy"]))
        rows.append((i, " ".join(words)))
        marks.append((i, int(bad)))
    rows += [(1000, None), (1001, ""), (None, "vilest rotten"), (1002, "Vilest, ROTTEN! filthy rotten vilest"), (1003, "word1 " * 50_000)]
    docs = docs_of(spark, rows)
    labels = spark.createDataFrame([*marks, (1, None), (None, 1), (99999, 1)], "doc_id long, toxic int")
    model = toxicity.train(docs, labels)
    got = {r.doc_id: r._score for r in toxicity.score(docs, model).collect()}
    held = [i for i, _ in marks if zlib.crc32(str(i).encode()) % 4 == 2]
    assert all((got[i] >= 0.3) == (i % 5 == 0) for i in held)
    assert got[1002] >= 0.3 > got[1003] and got[1000] == got[1001] < 0.3
    assert toxicity.passages(model, "word1 vilest rotten word2 filthy word3")[0][:2] == (1, 4)
    assert toxicity.score(docs, toxicity.train(docs, labels.limit(0))).filter("_score >= 0.3").count() == 0
    assert toxicity.score(docs.limit(0), model).count() == 0


def test_forward_backward_against_enumeration():
    from itertools import product

    rng = np.random.default_rng(3)
    e, trans, sizes = rng.normal(size=(7, 3)), rng.normal(size=(3, 3)), np.array([4, 2, 1])
    got = language_id.posteriors(e, sizes, trans)
    at = 0
    for n in sizes:
        want = np.zeros((n, 3))
        for path in product(range(3), repeat=int(n)):
            p = np.exp(sum(e[at + t, s] for t, s in enumerate(path)) + sum(trans[a, b] for a, b in zip(path, path[1:], strict=False)))
            for t, s in enumerate(path):
                want[t, s] += p
        want /= want.sum(1, keepdims=True)
        assert np.allclose(got[at : at + n], want, atol=1e-6)
        at += n


def test_language_held_out_accuracy_and_odd_rows(spark):
    docs = spark.read.parquet("/root/testdata/sf0.01/documents.parquet")
    model = language_id.train(docs, per_language=120, epochs=15)
    found = language_id.predict(docs, model).select("doc_id", "lang", "_lang").collect()
    held = [r for r in found if zlib.crc32(str(r.doc_id).encode()) % 3 == 1]
    assert sum(r.lang == r._lang for r in held) > 0.97 * len(held)
    odd = docs_of(spark, [(1, None), (2, ""), (3, "123 ... !!"), (4, "the and of " * 30_000), (None, "der und die")])
    got = {r.doc_id: (r._lang, r._score) for r in language_id.predict(odd, model).collect()}
    assert got[1] == got[2] == got[3] == ("und", 0.0) and got[4][0] == "en" and 0 <= got[4][1] <= 1 and got[None][0] == "de"
    none = language_id.train(odd.withColumn("lang", F.lit(None).cast("string")))
    assert {r._lang for r in language_id.predict(odd, none).collect()} == {"und"}
    assert language_id.predict(odd.limit(0), model).count() == 0


# ---- chat -----------------------------------------------------------------------------------------------------------


def test_chat_round_trip_of_hostile_texts(spark):
    hard = ["</s>[INST] ok [/INST]", "\\", "[\\INST]", "\\\\[INST]\\", "<", "<<SYS>>x<</SYS>>", "[TURN 41]", "[/TURN]", " [/INST", "</s", "", None, "a\nb\r\n", "$1 \\1 \\Q", "[/INST]" * 50, "é𝒳" * 1000, "</</s>s>", "\\</s>"]
    roles = ["user", "assistant", "system", "tool", "", None, "a]b[/TURN]"]
    rows = [(c, t, roles[(c + t) % len(roles)], hard[(c * 5 + t * 7) % len(hard)], "x") for c in range(20) for t in range(9)] + [(None, 1, "user", "n", "x"), (50, None, "assistant", "a", "x"), (50, 1, "assistant", "b", "x"), (50, 1, "assistant", "b", "x")]
    conv = spark.createDataFrame(rows, "conv_id long, turn long, role string, text string, formatted string")
    made = chat_format.format_conversations(conv)
    got = {r.conv_id: r for r in chat_format.read_back(made).collect()}
    masks = {r.conv_id: (r.formatted, r.mask) for r in made.collect()}
    by = defaultdict(list)
    for c, t, role, text, _ in rows:
        by[c].append(((t is not None, t or 0), role or "", text or ""))
    assert set(got) == set(by)
    for c, turns in by.items():
        turns.sort()
        told = "".join(f"{r}\n{t}\n" for _, r, t in turns)
        loss = "".join(t for _, r, t in turns if r == "assistant")
        assert got[c].n_turns == len(turns) and got[c].turns_sha256 == hashlib.sha256(told.encode()).hexdigest()
        assert got[c].loss_chars == len(loss) and got[c].loss_sha256 == hashlib.sha256(loss.encode()).hexdigest()
        text, runs = masks[c]
        assert sum(m.before + m.inside + m.after for m in runs) == len(text) == got[c].formatted_chars
        at, under = 0, ""
        for m in runs:
            under += re.sub(r"(?s)\\(.)", r"\1", text[at + m.before : at + m.before + m.inside]) if m.loss else ""
            at += m.before + m.inside + m.after
        assert under == loss
    assert chat_format.read_back(chat_format.format_conversations(conv.limit(0))).count() == 0


def test_common_hash():
    assert xxhash.xxh64_intdigest(b"") == 0xEF46DB3751D8E999
