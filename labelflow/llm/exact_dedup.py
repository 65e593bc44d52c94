"""Exact deduplication by composable polynomial fingerprints.

A text is normalised by deleting ASCII white space, cut into chunks, and every chunk is hashed on its own as a polynomial
over two prime fields. Chunk hashes combine by length-shifted arithmetic, hash(a + b) = hash(a) * base^len(b) + hash(b),
so the chunks of one huge document can be hashed by different tasks. Rows of equal fingerprint and length are then compared
chunk by chunk with the row that would stay; a row that differs (a collision) starts a group of its own.

Defined results: a null text counts as empty; empty texts are equal to each other; a row whose id is null is kept last among
ties; rows that repeat both id and text are one group of which one row stays; other columns are ignored.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator
from functools import lru_cache

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from labelflow.llm.common import binary_text, join_groups, materialise, release

WHITE = b" \t\n\x0b\x0c\r"
CHUNK = 1 << 16
#: Documents above this many bytes are hashed chunk by chunk in parallel tasks.
HUGE = 8 << 20
#: Two primes under 2^31 and a base for each: fixed values that every stored fingerprint depends on.
PRIMES = (2147483647, 2147483629)
BASES = (1103515245, 1299721861)
ROWS_PER_SALT = 256
MOST_SALTS = 64


@lru_cache(maxsize=4)
def _powers(chunk: int) -> np.ndarray:
    """base^(chunk-1) ... base^0 for both primes, as a (chunk, 2) matrix."""
    out = np.ones((chunk, 2), dtype=np.int64)
    for j, (p, b) in enumerate(zip(PRIMES, BASES, strict=True)):
        filled = 1
        while filled < chunk:  # doubling: the next block is the filled one times base^filled
            step = pow(b, filled, p)
            block = out[:filled, j][: chunk - filled] * step % p
            out[filled : filled + len(block), j] = block
            filled += len(block)
    return out[::-1].copy()


def chunk_hash(data: bytes) -> tuple[int, int]:
    """Polynomial hash of one chunk of at most CHUNK bytes; bytes count from 1, so leading zeros matter."""
    if not data:
        return 0, 0
    x = np.frombuffer(data, dtype=np.uint8).astype(np.int64) + 1
    h = x @ _powers(CHUNK)[CHUNK - len(x) :]
    return int(h[0] % PRIMES[0]), int(h[1] % PRIMES[1])


def combine(left: tuple[int, int], right: tuple[int, int], right_len: int) -> tuple[int, int]:
    """Hash of the concatenation, from the parts' hashes and the length of the right part."""
    return tuple((a * pow(b, right_len, p) + c) % p for a, c, p, b in zip(left, right, PRIMES, BASES, strict=True))


def fingerprint(data: bytes) -> int:
    """62-bit fingerprint of normalised bytes."""
    h = (0, 0)
    for at in range(0, len(data), CHUNK):
        part = data[at : at + CHUNK]
        h = combine(h, chunk_hash(part), len(part))
    return pack(h)


def pack(h: tuple[int, int]) -> int:
    return h[0] << 31 | h[1]


def _hash_rows(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        points, sizes, prints, digests = [], [], [], []
        for raw in batch.column(2).to_pylist():
            data = raw.translate(None, WHITE)
            points.append(len(raw.decode("utf-8", "replace")))
            sizes.append(len(data))
            prints.append(fingerprint(data) if len(raw) <= HUGE else None)
            digests.append(hashlib.sha256(data).hexdigest())
        yield pa.RecordBatch.from_arrays(
            [batch.column(0), batch.column(1), pa.array(points, pa.int64()), pa.array(sizes, pa.int64()), pa.array(prints, pa.int64()), pa.array(digests, pa.string())],
            names=["rid", "doc_id", "n_points", "n_bytes", "print", "text_sha256"],
        )


def _hash_chunks(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        parts = [x.translate(None, WHITE) for x in batch.column(2).to_pylist()]
        hashes = [[chunk_hash(d[i : i + CHUNK]) for i in range(0, len(d), CHUNK)] for d in parts]
        whole = []
        for d, hs in zip(parts, hashes, strict=True):
            h = (0, 0)
            for i, x in enumerate(hs):
                h = combine(h, x, len(d[i * CHUNK : (i + 1) * CHUNK]))
            whole.append(pack(h))
        yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), pa.array(whole, pa.int64()), pa.array(map(len, parts), pa.int64())], names=["rid", "at", "print", "n_bytes"])


def _join_chunks(key: tuple, group: pa.Table) -> pa.Table:
    group = group.sort_by("at")
    h = (0, 0)
    for x, n in zip(group["print"].to_pylist(), group["n_bytes"].to_pylist(), strict=True):
        h = combine(h, (x >> 31, x & 0x7FFFFFFF), n)
    return pa.table({"rid": pa.array([key[0].as_py()], pa.int64()), "print_of_parts": pa.array([pack(h)], pa.int64())})


def parallel_fingerprints(rows: DataFrame, chunk_chars: int = 1 << 20) -> DataFrame:
    """Fingerprints of huge texts (rid, text): chunks are dealt over tasks, hashed, and combined; equals fingerprint()."""
    n = F.greatest(F.lit(1), F.ceil(F.length("text") / chunk_chars)).cast("int")
    parts = rows.select("rid", "text", F.explode(F.sequence(F.lit(0), n - 1)).alias("at")).select("rid", "at", F.expr(f"substring(text, at * {chunk_chars} + 1, {chunk_chars})").cast("binary").alias("part"))
    hashed = parts.repartition("rid", "at").mapInArrow(_hash_chunks, "rid long, at int, print long, n_bytes long")
    return hashed.groupBy("rid").applyInArrow(_join_chunks, "rid long, print_of_parts long")


def fingerprints(docs: DataFrame) -> DataFrame:
    """One row per document: rid (a row number of its own), doc_id, n_points, n_bytes, print, text_sha256. Written once."""
    rows = docs.select(F.monotonically_increasing_id().alias("rid"), F.col("doc_id").cast("long").alias("doc_id"), binary_text().alias("raw"))
    found = materialise(rows.mapInArrow(_hash_rows, "rid long, doc_id long, n_points long, n_bytes long, print long, text_sha256 string"), "prints")
    huge = found.filter("print is null").select(F.col("doc_id").alias("huge_id"), F.col("text_sha256").alias("huge_sha"), F.col("rid").alias("huge_rid"))
    if huge.isEmpty():
        return found
    text = docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text").filter(F.octet_length("text") > HUGE)
    mine = text.withColumn("sha", F.sha2(F.regexp_replace("text", r"[\x20\x09-\x0D]", ""), 256))
    once = mine.dropDuplicates(["doc_id", "sha"])
    texts = once.join(huge, F.col("doc_id").eqNullSafe(F.col("huge_id")) & (F.col("sha") == F.col("huge_sha"))).select(F.col("huge_rid").alias("rid"), "text")
    parts = parallel_fingerprints(texts)
    return materialise(found.join(parts, "rid", "left").withColumn("print", F.coalesce("print", "print_of_parts")).drop("print_of_parts"), "prints")


KEY = ["n_bytes", "print", "round"]


def _with_group(prints: DataFrame) -> DataFrame:
    """Adds the group's size and the row that would stay. Groups are counted before the shuffle; only the rows of large ones are salted."""
    order = F.struct("n_points", F.col("doc_id").isNotNull().alias("has_id"), F.bitwise_not(F.coalesce("doc_id", F.lit(0))).alias("id_down"), F.bitwise_not("rid").alias("rid_down"), "doc_id", "text_sha256", "rid")
    groups = prints.groupBy(*KEY).agg(F.count("*").alias("group_size"), F.max(order).alias("best")).filter("group_size > 1")
    groups = groups.select(*KEY, "group_size", F.col("best.doc_id").alias("keep_id"), F.col("best.rid").alias("keep_rid"), F.col("best.text_sha256").alias("keep_sha"))
    out = join_groups(prints, groups, KEY, "group_size", ["rid"], ROWS_PER_SALT)
    return out.select(
        *prints.columns,
        F.coalesce("group_size", F.lit(1)).alias("group_size"),
        F.when(F.col("group_size").isNull(), F.col("doc_id")).otherwise(F.col("keep_id")).alias("keep_id"),
        F.coalesce("keep_rid", "rid").alias("keep_rid"),
        F.coalesce("keep_sha", "text_sha256").alias("keep_sha"),
    )


def _chunks(docs: DataFrame, wanted: DataFrame) -> DataFrame:
    """Normalised texts of the wanted (doc_id, text_sha256) as rows of one chunk each."""
    ids = wanted.select(F.coalesce("doc_id", F.lit(0)).alias("id"), F.col("doc_id").isNull().alias("no_id")).distinct()
    texts = docs.select(F.coalesce(F.col("doc_id").cast("long"), F.lit(0)).alias("id"), F.col("doc_id").isNull().alias("no_id"), F.coalesce("text", F.lit("")).alias("text"))
    texts = texts.join(ids, ["id", "no_id"], "left_semi").withColumn("text", F.regexp_replace("text", r"[\x20\x09-\x0D]", ""))
    texts = texts.withColumn("sha", F.sha2("text", 256)).dropDuplicates(["id", "no_id", "sha"])
    n = F.greatest(F.lit(1), F.ceil(F.length("text") / CHUNK)).cast("int")
    return texts.withColumn("parts", n).withColumn("at", F.explode(F.sequence(F.lit(0), n - 1))).select("id", "no_id", "sha", "parts", "at", F.expr(f"substring(text, at * {CHUNK} + 1, {CHUNK})").alias("part"))


def compare_chunks(docs: DataFrame, grouped: DataFrame) -> DataFrame:
    """(rid) of the rows whose text differs from that of the row that would stay, found by comparing chunk with chunk."""
    pairs = grouped.filter("group_size > 1 and rid != keep_rid").select("rid", F.coalesce("doc_id", F.lit(0)).alias("id"), F.col("doc_id").isNull().alias("no_id"), F.col("text_sha256").alias("sha"), F.coalesce("keep_id", F.lit(0)).alias("keep"), F.col("keep_id").isNull().alias("keep_null"), "keep_sha", "group_size")
    salts = F.least(F.lit(MOST_SALTS), F.ceil(F.col("group_size") / ROWS_PER_SALT)).cast("int")
    wanted = grouped.filter("group_size > 1")
    chunks = materialise(_chunks(docs, wanted), "chunks")
    mine = pairs.join(chunks, ["id", "no_id", "sha"]).withColumn("salt", F.pmod(F.xxhash64("rid"), salts).cast("int"))
    keeps = pairs.groupBy("keep", "keep_null", "keep_sha").agg(F.max(salts).alias("salts"))
    theirs = chunks.select(F.col("id").alias("keep"), F.col("no_id").alias("keep_null"), F.col("sha").alias("keep_sha"), "at", F.col("part").alias("keep_part"), F.col("parts").alias("keep_parts"))
    theirs = theirs.join(keeps, ["keep", "keep_null", "keep_sha"]).withColumn("salt", F.explode(F.sequence(F.lit(0), F.col("salts") - 1))).drop("salts")
    both = mine.join(theirs, ["keep", "keep_null", "keep_sha", "at", "salt"], "left")
    same = both.select("rid", (F.col("part").eqNullSafe(F.col("keep_part")) & F.col("parts").eqNullSafe(F.col("keep_parts"))).alias("same"))
    out = materialise(same.groupBy("rid").agg(F.bool_and("same").alias("same")).filter("not same").select("rid"), "differ")
    release(chunks)
    return out


def exact_dedup(docs: DataFrame) -> DataFrame:
    """One row per document: doc_id, keep_id, group_size, kept, text_sha256. See the module text for nulls, ties and repeats."""
    prints = fingerprints(docs).withColumn("round", F.lit(0))
    level = 0
    while True:
        grouped = materialise(_with_group(prints), "groups")
        differ = compare_chunks(docs, grouped)
        if differ.isEmpty():
            break
        level += 1  # collisions: what differs forms groups of its own, until all groups are of one text
        moved = differ.withColumn("moved", F.lit(level))
        was, prints = prints, materialise(prints.join(moved, "rid", "left").withColumn("round", F.coalesce("moved", "round")).drop("moved"), "prints")
        release(was, grouped, differ)
    return grouped.select("doc_id", "keep_id", F.col("group_size").cast("long").alias("group_size"), (F.col("rid") == F.col("keep_rid")).alias("kept"), "text_sha256")
