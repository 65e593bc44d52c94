"""Log-structured index of window fingerprints, and substring deduplication over it.

A window is `width` consecutive words of one document. Each ingested batch is cut into sorted runs of (64-bit hash, smallest
document), dealt over hash buckets, merge-joined inside a bucket with each other and with the sorted immutable runs of
earlier batches, and what is new is written as one more run. Once `fanout` runs exist they are compacted into one before the
next batch. A match names the document that its window comes from, and is verified on the words: both documents digest the
13 words in question (128 bits of BLAKE2), digests meet by hash, and a hash with any failed match is settled for all documents
by (hash, digest), so equal hashes of other words neither remove a word nor hide a repeat.

Before anything is shuffled each task keeps one row per distinct window of its own documents and settles the others there,
so a passage that a third of all documents share costs a row per task, not a row per document.

Defined results: null and empty texts have no words; a document of fewer words than `width` has no window and stays whole;
rows that share a doc_id are one document for the rule "starts in a document with a smaller doc_id"; a null doc_id is
smaller than any other; other columns are ignored.
"""

from __future__ import annotations

import hashlib
import json
import os
from collections.abc import Iterator
from functools import reduce

import numpy as np
import pyarrow as pa
import xxhash
from pyarrow import fs as pafs
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from labelflow.llm.common import binary_text, id_column, materialise, new_path, partitions_for, release, remove_path, shuffle_cleanup
from labelflow.plans.joins import lookup

WIDTH = 13
CHUNK_WORDS = 1_000_000
WINDOWS_PER_BUCKET = 4_000_000
LEAST_BUCKETS = 256
FANOUT = 3
BYTES_PER_WORD = 6
ROWS = "bucket int, kind int, base long, hashes binary, docs binary"
FLAGS = "doc_id long, hashes binary, sources binary"
#: Hashes with a failed match that one round settles.
ODD_AT_ONCE = 1_000_000
NO_ID = int(np.iinfo(np.int64).min)
_rng = np.random.default_rng(20240607)
#: Odd multipliers by place in the window; derived from a fixed seed.
_FACTORS = _rng.integers(1, 1 << 63, size=256, dtype=np.uint64) * np.uint64(2) + np.uint64(1)


def word_hashes(words: list[bytes]) -> np.ndarray:
    return np.fromiter(map(xxhash.xxh64_intdigest, words), np.uint64, len(words))


def _mix(h: np.ndarray) -> np.ndarray:
    h = h ^ (h >> np.uint64(29))
    h *= np.uint64(0xBF58476D1CE4E5B9)
    return h ^ (h >> np.uint64(32))


def window_hashes(words: np.ndarray, width: int, bits: int = 64) -> np.ndarray:
    """Hash of each run of `width` word hashes; fewer `bits` than 64 make collisions, for tests."""
    n = len(words) - width + 1
    if n <= 0:
        return np.empty(0, np.uint64)
    h = np.zeros(n, np.uint64)
    for j in range(width):
        h += words[j : j + n] * _FACTORS[j]
    return _mix(h) if bits == 64 else _mix(h) >> np.uint64(64 - bits) << np.uint64(64 - bits)


def window_digests(words: list[bytes], starts: np.ndarray, width: int) -> np.ndarray:
    """(n, 2) words of a 128-bit digest of the words of each window; a word has no white space, so one space joins them apart."""
    flat = b"".join(hashlib.blake2b(b" ".join(words[i : i + width]), digest_size=16).digest() for i in starts.tolist())
    return np.frombuffer(flat, np.uint64).reshape(-1, 2)


def of_source(digests: np.ndarray, sources: np.ndarray) -> np.ndarray:
    """Digests of words as a source has them: equal for equal words and source; others are equal with a chance of 2^-128 as before."""
    s = sources.view(np.uint64)
    return digests ^ np.column_stack([_mix(s), _mix(s + _FACTORS[0])])


def settle(h: np.ndarray, d: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """Distinct sorted hashes with their smallest document; and the rows (as indices) that a smaller document beats, with that document."""
    if not len(h):
        return h, d, np.empty(0, np.int64), d
    order = np.argsort(h)
    hs, ds = h[order], d[order]
    first = np.concatenate(([True], hs[1:] != hs[:-1]))
    at = np.flatnonzero(first)
    least = np.minimum.reduceat(ds, at)
    source = least[np.cumsum(first) - 1]
    beaten = ds > source
    return hs[at], least, order[beaten], source[beaten]


def present(h: np.ndarray, old_h: np.ndarray, old_d: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Which of the sorted hashes a sorted run holds, and the document each of these has there."""
    if not len(old_h):
        return np.zeros(len(h), bool), old_d[:0]
    at = np.minimum(np.searchsorted(old_h, h), len(old_h) - 1)
    hit = old_h[at] == h
    return hit, old_d[at[hit]]


def _by_doc(ids: np.ndarray, *columns: np.ndarray) -> Iterator[tuple]:
    """(id, bytes of each column) for each id."""
    if len(ids):
        order = np.argsort(ids, kind="stable")
        ids, columns = ids[order], [c[order] for c in columns]
        cut = np.flatnonzero(np.concatenate(([True], ids[1:] != ids[:-1])))
        for a, b in zip(cut, np.append(cut[1:], len(ids)), strict=True):
            yield (int(ids[a]), *(c[a:b].tobytes() for c in columns))


def _arrow(rows: list[tuple], schema: str) -> pa.RecordBatch:
    kinds = {"int": pa.int32(), "long": pa.int64(), "binary": pa.binary(), "boolean": pa.bool_()}
    fields = [f.split() for f in schema.split(", ")]
    cols = list(zip(*rows, strict=True)) if rows else [[]] * len(fields)
    return pa.RecordBatch.from_arrays([pa.array(c, kinds[k]) for c, (_, k) in zip(cols, fields, strict=True)], names=[n for n, _ in fields])


def _narrow(d: np.ndarray) -> tuple[int, bytes]:
    """Document ids as offsets from their smallest, in the fewest bytes."""
    base = int(d.min())
    span = int(d.max()) - base
    kind = np.uint16 if span < 1 << 16 else np.uint32 if span < 1 << 32 else np.uint64
    return base, (d.astype(np.uint64) - np.uint64(base & 0xFFFFFFFFFFFFFFFF)).astype(kind).tobytes()


def _widen(base: int, raw: bytes, n: int) -> np.ndarray:
    kind = {2: np.uint16, 4: np.uint32, 8: np.uint64}[len(raw) // n]
    return (np.frombuffer(raw, kind).astype(np.uint64) + np.uint64(base & 0xFFFFFFFFFFFFFFFF)).astype(np.int64)


def bucket_edges(buckets: int) -> np.ndarray:
    return (np.arange(1, buckets, dtype=np.float64) * (2.0**64 / buckets)).astype(np.uint64)


def _runs_of(width: int, buckets: int, bits: int):
    """Map side: sorted runs of distinct windows by bucket, and what is already settled among the task's own documents."""
    edges = bucket_edges(buckets)

    def flush(parts: list[np.ndarray], ids: list[int]) -> pa.RecordBatch:
        words = np.concatenate(parts)
        ends = np.cumsum([len(p) for p in parts])
        owner = np.repeat(np.arange(len(parts)), [len(p) for p in parts])
        h = window_hashes(words, width, bits)
        start = np.arange(len(h))
        valid = start + width <= ends[owner[: len(h)]]
        h, d = h[valid], np.asarray(ids, np.int64)[owner[: len(valid)][valid]]
        uh, ud, beaten, sources = settle(h, d)
        rows = []
        cuts = np.concatenate(([0], np.searchsorted(uh, edges), [len(uh)]))
        for b in range(buckets):
            lo, hi = cuts[b], cuts[b + 1]
            if hi > lo:
                base, docs = _narrow(ud[lo:hi])
                rows.append((b, 0, base, uh[lo:hi].tobytes(), docs))
        for doc, hashes, raw in _by_doc(d[beaten], h[beaten], sources):
            rows.append((xxhash.xxh64_intdigest(doc.to_bytes(8, "little", signed=True)) % buckets, 1, doc, hashes, raw))
        return _arrow(rows, ROWS)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        parts, ids, held = [], [], 0
        for batch in batches:
            for doc, raw in zip(id_column(batch).tolist(), batch.column(1).to_pylist(), strict=True):
                words = raw.split()
                if len(words) >= width:
                    parts.append(word_hashes(words))
                    ids.append(doc)
                    held += len(words)
                if held >= CHUNK_WORDS:
                    yield flush(parts, ids)
                    parts, ids, held = [], [], 0
        if parts:
            yield flush(parts, ids)

    return run


def _read_run(path: str, bucket: int) -> tuple[np.ndarray, np.ndarray]:
    store, root = pafs.FileSystem.from_uri(path)
    name = f"{root}/{bucket:08d}.run"
    if store.get_file_info(name).type == pafs.FileType.NotFound:
        return np.empty(0, np.uint64), np.empty(0, np.int64)
    with store.open_input_file(name) as f:
        raw = f.read()
    n, base = np.frombuffer(raw, np.int64, 2).tolist()
    return np.frombuffer(raw, np.uint64, n, offset=16), _widen(base, raw[16 + 8 * n :], n)


def _write_run(path: str, bucket: int, h: np.ndarray, d: np.ndarray) -> None:
    """One bucket of an immutable run: how many, the smallest document, the hashes, the documents less the smallest.

    Every attempt of a task writes the same bytes, under a name of its own first. The first to move its file in place wins; a
    later one finds the file there and drops its own."""
    if not len(h):
        return
    store, root = pafs.FileSystem.from_uri(path)
    store.create_dir(root, recursive=True)
    name = f"{root}/{bucket:08d}.run"
    there = lambda: store.get_file_info(name).type != pafs.FileType.NotFound
    if there():
        return
    held = f"{root}/.{bucket:08d}.{os.urandom(8).hex()}"
    base, docs = _narrow(d)
    with store.open_output_stream(held) as f:
        f.write(np.array([len(h), base], np.int64).tobytes())
        f.write(h.tobytes())
        f.write(docs)
    try:
        store.move(held, name)
    except OSError:
        if not there():
            raise
        store.delete_file(held)


def _merge_bucket(history: list[str], target: str):
    """Reduce side: merge-join of the new runs of a bucket with each other and with the older runs."""

    def run(key: tuple, group: pa.Table) -> pa.Table:
        bucket = key[0].as_py()
        hs, ds, out = [], [], []
        for kind, base, rh, rd in zip(*(group[c].to_pylist() for c in ("kind", "base", "hashes", "docs")), strict=True):
            if kind == 1:
                out.append((base, rh, rd))
            else:
                hs.append(np.frombuffer(rh, np.uint64))
                ds.append(_widen(base, rd, len(hs[-1])))
        if hs:
            h, d = np.concatenate(hs), np.concatenate(ds)
            uh, ud, beaten, sources = settle(h, d)
            out += _by_doc(d[beaten], h[beaten], sources)
            fresh = np.ones(len(uh), bool)
            for path in history:
                hit, sources = present(uh, *_read_run(path, bucket))
                out += _by_doc(ud[hit], uh[hit], sources)
                fresh &= ~hit
            _write_run(target, bucket, uh[fresh], ud[fresh])
        return pa.Table.from_batches([_arrow(out, FLAGS)])

    return run


def _compact_bucket(sources: list[str], target: str):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for bucket in batch.column(0).to_pylist():
                runs = [_read_run(p, bucket) for p in sources]
                h, d, _, _ = settle(np.concatenate([r[0] for r in runs]), np.concatenate([r[1] for r in runs]))
                _write_run(target, bucket, h, d)
            yield batch

    return run


class WindowIndex:
    """Sorted immutable runs of the windows seen so far, in a folder that all executors share."""

    def __init__(self, spark: SparkSession, buckets: int, width: int = WIDTH, path: str | None = None, fanout: int = FANOUT, bits: int = 64):
        self.spark, self.width, self.buckets, self.fanout, self.bits = spark, width, buckets, fanout, bits
        self.path = path or new_path(spark, "windows")
        self.runs: list[str] = []
        self.made = self.compactions = 0

    def _next(self) -> str:
        self.made += 1
        return f"{self.path}/run-{self.made:05d}"

    def manifest(self) -> str:
        """What to keep beside the runs in order to open the index again."""
        return json.dumps({"width": self.width, "buckets": self.buckets, "fanout": self.fanout, "bits": self.bits, "runs": self.runs, "made": self.made})

    @classmethod
    def open(cls, spark: SparkSession, path: str, manifest: str) -> WindowIndex:
        held = json.loads(manifest)
        out = cls(spark, held["buckets"], held["width"], path, held["fanout"], held["bits"])
        out.runs, out.made = held["runs"], held["made"]
        return out

    def ingest(self, docs: DataFrame) -> DataFrame:
        """Adds a batch of (doc_id, text) whose ids are all larger than those before; returns (doc_id, hashes, sources): the
        windows of a document whose hash started in a smaller one, and that one. Compacts first where the log has grown to `fanout` runs."""
        if len(self.runs) >= self.fanout:
            self.compact()
        target = self._next()
        rows = docs.select(F.col("doc_id").cast("long").alias("doc_id"), binary_text().alias("raw")).mapInArrow(_runs_of(self.width, self.buckets, self.bits), ROWS)
        flags = materialise(rows.groupBy("bucket").applyInArrow(_merge_bucket(list(self.runs), target), FLAGS), "flags")
        self.runs.append(target)
        return flags

    def compact(self) -> None:
        """Merges all runs into one; the old ones go once the new one is whole."""
        if len(self.runs) < 2:
            return
        target, old = self._next(), list(self.runs)
        ids = self.spark.range(0, self.buckets, 1, min(self.buckets, max(self.spark.sparkContext.defaultParallelism, self.buckets // 8)))
        with shuffle_cleanup(self.spark):
            ids.mapInArrow(_compact_bucket(old, target), "id long").count()
        self.runs = [target]
        self.compactions += 1
        for path in old:
            remove_path(self.spark, path)

    def drop(self) -> None:
        remove_path(self.spark, self.path)
        self.runs = []


#: Questions, with their hashes, and answers, without: a digest tells both the words, and so the hash, and the source.
WORK = "bucket int, hashes binary, digests binary"
WANTED = "part int, hashes binary, sources binary"


def _sources(parts: int):
    """Of flags: the hashes that sources must show the words of, packed by part of the sources, so a batch makes a row per part at most."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            if batch.num_rows:
                h, s = (np.frombuffer(b"".join(batch.column(k).to_pylist()), t) for k, t in ((1, np.uint64), (2, np.int64)))
                part = (_mix(s.view(np.uint64)) % np.uint64(parts)).astype(np.int32)
                h, s, part = _distinct(h, s, part)
                cut = np.searchsorted(part, np.arange(parts + 1)).tolist()
                yield _arrow([(k, h[x:y].tobytes(), s[x:y].tobytes()) for k, (x, y) in enumerate(zip(cut[:-1], cut[1:], strict=True)) if y > x], WANTED)

    return run


def _distinct(*columns: np.ndarray) -> list[np.ndarray]:
    """Distinct rows of columns, sorted by the last column first."""
    order = np.lexsort(columns)
    columns = [c[order] for c in columns]
    new = np.ones(len(order), bool)
    new[1:] = np.any([c[1:] != c[:-1] for c in columns], axis=0)
    return [c[new] for c in columns]


def _by_source(key: tuple, group: pa.Table) -> pa.Table:
    """Of a part: for each source the hashes wanted of it, once."""
    h, s = _distinct(*(np.frombuffer(b"".join(group[c].to_pylist()), t) for c, t in (("hashes", np.uint64), ("sources", np.int64))))
    return pa.Table.from_batches([_arrow([(doc, hashes, None) for doc, hashes in _by_doc(s, h)], FLAGS)])


def _windows_among(words: list[bytes], wanted: np.ndarray, width: int, bits: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Starts, hashes and digests of the windows whose hash is among the sorted wanted ones."""
    h = window_hashes(word_hashes(words), width, bits)
    at = np.minimum(np.searchsorted(wanted, h), len(wanted) - 1)
    starts = np.flatnonzero(wanted[at] == h) if len(h) else np.empty(0, np.int64)
    return starts, h[starts], window_digests(words, starts, width)


def _digests(width: int, buckets: int, bits: int):
    """Of documents with flags and wanted hashes: by bucket, the digests that are asked of sources and those that answer, each once a batch."""
    edges = bucket_edges(buckets)

    def out(asked: bool, parts: list[tuple[np.ndarray, ...]]) -> list[tuple]:
        h, s, g = (np.concatenate(c) for c in zip(*parts, strict=True))
        g = of_source(g, s)
        g1, g0, h = _distinct(g[:, 1], g[:, 0], h)
        g = np.column_stack([g0, g1])
        cuts = np.concatenate(([0], np.searchsorted(h, edges), [len(h)])).tolist()
        return [(b, h[x:y].tobytes() if asked else None, g[x:y].tobytes()) for b, (x, y) in enumerate(zip(cuts[:-1], cuts[1:], strict=True)) if y > x]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            asks, answers = [], []
            for doc, raw, work in zip(*(batch.column(k).to_pylist() for k in range(3)), strict=True):
                mine = [(np.frombuffer(w["hashes"], np.uint64), np.frombuffer(w["sources"], np.int64)) for w in work if w["sources"] is not None]
                asked = [np.frombuffer(w["hashes"], np.uint64) for w in work if w["sources"] is None]
                words = raw.split()
                _, h, g = _windows_among(words, np.unique(np.concatenate([*(m[0] for m in mine), *asked])), width, bits)
                each = np.unique(np.column_stack([h, g]), axis=0)  # sorted by hash
                h, g = np.ascontiguousarray(each[:, 0]), each[:, 1:]
                if mine:
                    flag, source = (np.concatenate(c) for c in zip(*mine, strict=True))
                    low, high = np.searchsorted(h, flag), np.searchsorted(h, flag, "right")
                    n = high - low
                    at = np.repeat(low, n) + np.arange(n.sum()) - np.repeat(np.cumsum(n) - n, n)
                    asks.append((h[at], np.repeat(source, n), g[at]))
                if asked:
                    at = np.flatnonzero(np.isin(h, np.concatenate(asked)))
                    answers.append((h[at], np.full(len(at), doc, np.int64), g[at]))
            rows = [r for asked, parts in ((True, asks), (False, answers)) if parts for r in out(asked, parts)]
            if rows:
                yield _arrow(rows, WORK)

    return run


def _confirm(key: tuple, group: pa.Table) -> pa.Table:
    """Of a bucket: the hashes with a match whose source does not have these words."""
    asks, answers = [], []
    for rh, rg in zip(*(group[c].to_pylist() for c in ("hashes", "digests")), strict=True):
        g = np.frombuffer(rg, np.uint64).reshape(-1, 2)
        if rh is None:
            answers.append(g)
        else:
            asks.append((np.frombuffer(rh, np.uint64), g))
    if not asks:
        return pa.Table.from_batches([_arrow([], "hashes binary")])
    h, g = (np.concatenate(c) for c in zip(*asks, strict=True))
    same = np.zeros(len(h), bool)
    if answers:
        ag = np.concatenate(answers)
        ag = ag[np.argsort(ag[:, 0])]
        names, mine = np.ascontiguousarray(ag[:, 0]), g[:, 0]
        low = np.searchsorted(names, mine)
        todo = np.flatnonzero(low < len(names))
        while len(todo):
            todo = todo[names[low[todo]] == mine[todo]]
            hit = ag[low[todo], 1] == g[todo, 1]
            same[todo[hit]] = True
            todo = todo[~hit]
            low[todo] += 1
            todo = todo[low[todo] < len(names)]
    odd = np.unique(h[~same])
    return pa.Table.from_batches([_arrow([(odd.tobytes(),)] * bool(len(odd)), "hashes binary")])


def _less(odd: np.ndarray):
    """Flags without the sorted odd hashes."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            rows = []
            for doc, raw in zip(id_column(batch).tolist(), batch.column(1).to_pylist(), strict=True):
                h = np.frombuffer(raw, np.uint64)
                left = h[~np.isin(h, odd)]
                if len(left):
                    rows.append((doc, left.tobytes()))
            yield _arrow(rows, "doc_id long, hashes binary")

    return run


def _odd_windows(odd: np.ndarray, width: int, bits: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            rows = set()
            for doc, raw in zip(id_column(batch).tolist(), batch.column(1).to_pylist(), strict=True):
                _, h, g = _windows_among(raw.split(), odd, width, bits)
                rows |= {(doc, x.tobytes(), y.tobytes()) for x, y in zip(h, g, strict=True)}
            yield _arrow(list(rows), "doc_id long, hashes binary, digests binary")

    return run


def _settled(docs: DataFrame, flags: DataFrame, odd: DataFrame, width: int, bits: int) -> DataFrame:
    """Flags (doc_id, hashes, digests): those of other hashes as they are; those of hashes with a failed match from the digests of all their windows."""
    hashes = materialise(odd.selectExpr("explode(transform(sequence(0, cast(length(hashes) / 8 as int) - 1), i -> substring(hashes, i * 8 + 1, 8))) as h").distinct(), "odd")
    n, out = hashes.count(), []
    rounds = -(-n // ODD_AT_ONCE)
    sure = flags.select("doc_id", "hashes")
    for k in range(rounds):
        some = hashes.filter(F.pmod(F.xxhash64("h"), F.lit(rounds)) == k) if rounds > 1 else hashes
        held = np.sort(np.frombuffer(b"".join(bytes(r.h) for r in some.collect()), np.uint64))  # about ODD_AT_ONCE, by the number of rounds
        sure = sure.mapInArrow(_less(held), "doc_id long, hashes binary")
        rows = materialise(docs.select(F.col("doc_id").cast("long").alias("doc_id"), binary_text().alias("raw")).mapInArrow(_odd_windows(held, width, bits), "doc_id long, hashes binary, digests binary"), "odd-windows")
        firsts = materialise(rows.groupBy("hashes", "digests").agg(F.min("doc_id").alias("least")), "odd-firsts")
        out.append(materialise(lookup(rows, firsts, ["hashes", "digests"], "inner", "doc_id").filter("doc_id > least").select("doc_id", "hashes", "digests"), "odd-flags"))
        release(rows, firsts)
    return reduce(DataFrame.unionByName, out, sure.withColumn("digests", F.lit(None).cast("binary")))


def verified(docs: DataFrame, flags: DataFrame, buckets: int, width: int = WIDTH, bits: int = 64) -> DataFrame:
    """(doc_id, hashes, digests): flags whose words have been compared; digests only where a hash stands for several windows. It reads `flags` again."""
    parts = partitions_for(docs.sparkSession, 0, 1)
    wanted = flags.mapInArrow(_sources(parts), WANTED).groupBy("part").applyInArrow(_by_source, FLAGS)
    work = flags.unionByName(wanted)
    work = work.groupBy(F.col("doc_id").alias("key")).agg(F.collect_list(F.struct("hashes", "sources")).alias("work"))
    rows = docs.select(F.coalesce(F.col("doc_id").cast("long"), F.lit(NO_ID)).alias("key"), binary_text().alias("raw"))
    both = rows.join(work, "key").select("key", "raw", "work").mapInArrow(_digests(width, buckets, bits), WORK)
    odd = materialise(both.groupBy("bucket").applyInArrow(_confirm, "hashes binary"), "odd-matches")
    if odd.isEmpty():
        return flags.select("doc_id", "hashes", F.lit(None).cast("binary").alias("digests"))
    return _settled(docs, flags, odd, width, bits)


def _remove(width: int, bits: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            n_words, n_removed, kept_text = [], [], []
            for raw, flags in zip(batch.column(1).to_pylist(), batch.column(2).to_pylist(), strict=True):
                words = raw.split()
                n_words.append(len(words))
                gone = 0
                if flags:
                    h = window_hashes(word_hashes(words), width, bits)
                    known = np.sort(np.frombuffer(b"".join(f["hashes"] for f in flags), np.uint64))
                    starts = np.flatnonzero(known[np.minimum(np.searchsorted(known, h), len(known) - 1)] == h)
                    digests = {f["hashes"] + f["digests"] for f in flags if f["digests"] is not None}
                    if digests:  # of a hash with digests, only those windows
                        odd = {x[:8] for x in digests}
                        mine = [i for i in starts.tolist() if h[i].tobytes() in odd]
                        shown = window_digests(words, np.array(mine, np.int64), width)
                        wrong = [i for i, g in zip(mine, shown, strict=True) if h[i].tobytes() + g.tobytes() not in digests]
                        starts = np.setdiff1d(starts, wrong)
                    edge = np.zeros(len(words) + 1, np.int64)
                    np.add.at(edge, starts, 1)
                    np.add.at(edge, starts + width, -1)
                    keep = np.cumsum(edge[:-1]) == 0
                    gone = int(len(words) - keep.sum())
                    words = [w for w, k in zip(words, keep.tolist(), strict=True) if k]
                n_removed.append(gone)
                kept_text.append(b" ".join(words))
            yield pa.RecordBatch.from_arrays(
                [batch.column(0), pa.array(n_words, pa.int64()), pa.array(n_removed, pa.int64()), pa.array([hashlib.sha256(k).hexdigest() for k in kept_text], pa.string()), pa.array(kept_text, pa.binary())],
                names=["doc_id", "n_words", "n_removed", "kept_sha256", "kept"],
            )

    return run


def remove_flagged(docs: DataFrame, flags: DataFrame, width: int = WIDTH, bits: int = 64) -> DataFrame:
    """Documents without the words that verified flags cover: doc_id, n_words, n_removed, kept_sha256, kept (UTF-8)."""
    mine = flags.groupBy(F.col("doc_id").alias("key")).agg(F.collect_list(F.struct("hashes", "digests")).alias("flags"))
    rows = docs.select(F.col("doc_id").cast("long").alias("doc_id"), binary_text().alias("raw"))
    rows = rows.withColumn("key", F.coalesce("doc_id", F.lit(NO_ID))).join(mine, "key", "left")
    return rows.select("doc_id", "raw", "flags").mapInArrow(_remove(width, bits), "doc_id long, n_words long, n_removed long, kept_sha256 string, kept binary")


def buckets_for(docs: DataFrame, expected_growth: int = 1) -> int:
    """Buckets of a new index, so that one holds about WINDOWS_PER_BUCKET windows of the expected corpus."""
    size = docs.agg(F.sum(F.octet_length("text"))).first()[0] or 0
    return max(LEAST_BUCKETS, partitions_for(docs.sparkSession, size * expected_growth // BYTES_PER_WORD, WINDOWS_PER_BUCKET))


def substring_dedup(docs: DataFrame, batches: int = 4, width: int = WIDTH, bits: int = 64) -> DataFrame:
    """Ingests the documents by rising id in `batches` batches and removes what an earlier document already has."""
    spark = docs.sparkSession
    cuts = sorted(set(docs.select(F.col("doc_id").cast("double").alias("d")).approxQuantile("d", [i / batches for i in range(1, batches)], 0.001))) if batches > 1 else []
    index = WindowIndex(spark, buckets_for(docs), width, bits=bits)
    low, parts = None, []
    for high in [*cuts, None]:
        part = docs
        if low is not None:
            part = part.filter(F.col("doc_id") > int(low))
        if high is not None:
            part = part.filter((F.col("doc_id") <= int(high)) | F.col("doc_id").isNull() if low is None else F.col("doc_id") <= int(high))
        elif low is None:
            part = docs
        parts.append(index.ingest(part))
        low = high
    index.drop()
    sure = verified(docs, reduce(DataFrame.unionByName, parts), index.buckets, width, bits)
    out = materialise(remove_flagged(docs, sure, width, bits).drop("kept"), "kept")
    release(*parts)
    return out
