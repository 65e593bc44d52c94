"""Groups of near copies: documents whose sets of five-word shingles have a Jaccard similarity of 0.8 or more, and no others.

A document is the set of its shingles' 64-bit hashes; equal sets count once. Links are found in two passes and each is
verified on the whole sets:

1. Fingerprints of the sets are joined by ball hashing (see `simhash`) and each set is compared with the least of its group:
   linear in a group. Four bits of 64 find a pair of similarity 0.8 rarely, so this is not all.
2. The rest by prefixes: sets whose similarity is 4/5 share one of their first n - ceil(4n/5) + 1 hashes under any order of
   the hashes. The order puts rare ones first, by counts in SLOTS slots; the counts only set the order, so collisions cost
   time and lose nothing. ROUNDS times the sets that meet at a hash are compared with LEADERS random ones of them that are in
   other groups so far, and groups are contracted: linear again, and settles a group of copies of any size. What is then
   still in different groups is compared in blocks of BLOCK sets, so that a hash of any number of sets is dealt over tasks.
   Sizes and parities (128, then WIDE bits) bound a pair's similarity from above; only pairs that they leave possible become rows.
   A parity of four bits a hash then parts long sets before the whole sets travel for each pair.

Defined results: null ids and texts without words take no part; fewer words than a shingle make one shingle of all.
"""

from __future__ import annotations

import zlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from labelflow.llm.common import arrow_rows, binary_text, materialise, partitions_for, release
from labelflow.llm.simhash import closed, joined_prints, majority_bits, shingle_hashes
from labelflow.plans.joins import lookup, without

SLOTS = 1 << 18
CHUNK = 1 << 12
WIDE = 2048
#: Bits of a hash that choose its place in a parity: the upper 24.
MOST_BITS = 1 << 24
#: Sets at one hash that make it worth sending the hash to every task.
HOT = 100_000
ROUNDS = 3
LEADERS = 2
BLOCK = 4096
PAIRS_AT_ONCE = 1 << 20
ROWS_AT_ONCE = 512
MEETING = "h long, sid long, n int, s0 long, s1 long"


def _sets(shingle: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in _slices(batches):
            rows = []
            for i, raw in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist(), strict=True):
                hashes = np.unique(shingle_hashes(raw, shingle))
                if len(hashes):
                    raw_set = hashes.tobytes()
                    rows.append((i, xxhash.xxh64_intdigest(raw_set) - (1 << 63), majority_bits(hashes), len(hashes), parity(hashes, WIDE).tobytes(), raw_set))
            cols = list(zip(*rows, strict=True)) or [[]] * 6
            prints = pa.array(np.array(cols[2], np.uint64).view(np.int64))
            kinds = (pa.int64(), pa.int64(), None, pa.int32(), pa.binary(), pa.binary())
            yield pa.RecordBatch.from_arrays([pa.array(c, t) if t else prints for c, t in zip(cols, kinds, strict=True)], names=["doc_id", "sid", "print", "n", "wide", "hashes"])

    return run


def _slices(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Batches of ROWS_AT_ONCE rows: whole sets are large."""
    for whole in batches:
        for at in range(0, whole.num_rows, ROWS_AT_ONCE):
            yield whole.slice(at, ROWS_AT_ONCE)


def _count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    held = np.zeros(SLOTS, np.int64)
    for batch in _slices(batches):
        flat = b"".join(batch.column(0).to_pylist())
        held += np.bincount((np.frombuffer(flat, np.uint64) % np.uint64(SLOTS)).astype(np.int64), minlength=SLOTS)
    parts = held.reshape(-1, CHUNK)
    used = [i for i in range(len(parts)) if parts[i].any()]
    yield pa.RecordBatch.from_arrays([pa.array(used, pa.int32()), pa.array([zlib.compress(parts[i].tobytes(), 1) for i in used], pa.binary())], names=["chunk", "counts"])


def _add(key: tuple, group: pa.Table) -> pa.Table:
    total = sum(np.frombuffer(zlib.decompress(c), np.int64) for c in group["counts"].to_pylist())
    return pa.table({"chunk": pa.array([key[0].as_py()], pa.int32()), "counts": pa.array([total.tobytes()], pa.binary())})


def _levels(sets: DataFrame) -> np.ndarray:
    """How common the hashes of each slot are, as a power of two."""
    rows = sets.select("hashes").mapInArrow(_count, "chunk int, counts binary").groupBy("chunk").applyInArrow(_add, "chunk int, counts binary")
    counts = np.zeros((SLOTS // CHUNK, CHUNK), np.int64)
    for r in rows.collect():  # SLOTS counts at most
        counts[r.chunk] = np.frombuffer(r.counts, np.int64)
    return np.ceil(np.log2(counts.ravel() + 1)).astype(np.uint8)


def parity(hashes: np.ndarray, bits: int = 128) -> np.ndarray:
    """As words: bit b is set if an odd number of hashes falls on b. Two sets' parities differ in no more bits than the sets in hashes."""
    odd = np.bincount((hashes >> np.uint64(40) & np.uint64(bits - 1)).astype(np.int64), minlength=bits) & 1
    return np.packbits(odd.astype(bool), bitorder="little").view(np.int64)


def _prefixes(levels: np.ndarray):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in _slices(batches):
            out: list[list[np.ndarray]] = [[], [], [], [], []]
            for sid, raw in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist(), strict=True):
                x = np.frombuffer(raw, np.uint64)
                n = len(x)
                take = n - (4 * n + 4) // 5 + 1
                first = x[np.argsort(levels[(x % np.uint64(SLOTS)).astype(np.int64)], kind="stable")[:take]]
                s = parity(x)
                for c, v in zip(out, (first.view(np.int64), np.full(take, sid, np.int64), np.full(take, n, np.int32), np.full(take, s[0]), np.full(take, s[1])), strict=True):
                    c.append(v)
            if out[0]:
                yield pa.RecordBatch.from_arrays([pa.array(np.concatenate(c)) for c in out], names=["h", "sid", "n", "s0", "s1"])

    return run


def _whole(batches: Iterator[pa.RecordBatch]) -> pa.Table | None:
    held = [b for b in batches if b.num_rows]
    return pa.Table.from_batches(held) if held else None


def _meeting(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Of a partition dealt by h: the rows whose h is not alone."""
    t = _whole(batches)
    if t is not None:
        _, at, n = np.unique(t["h"].to_numpy(), return_inverse=True, return_counts=True)
        yield from t.filter(pa.array(n[at] > 1)).to_batches()


def _possible(a: dict, i: np.ndarray, b: dict, j: np.ndarray) -> np.ndarray:
    """Whether sizes and parities leave room for a similarity of 4/5."""
    m, n = a["n"][i].astype(np.int64), b["n"][j].astype(np.int64)
    apart = np.bitwise_count(a["s0"][i] ^ b["s0"][j]).astype(np.int64) + np.bitwise_count(a["s1"][i] ^ b["s1"][j])
    return (5 * np.minimum(m, n) >= 4 * np.maximum(m, n)) & (9 * apart <= m + n)


def _columns(t: pa.Table) -> dict[str, np.ndarray]:
    c = {k: t[k].to_numpy() for k in ("sid", "n", "s0", "s1")}
    return c | {k: c[k].view(np.uint64) for k in ("s0", "s1")}


def _pairs(a: np.ndarray, b: np.ndarray) -> pa.RecordBatch:
    p = np.unique(np.stack([np.minimum(a, b), np.maximum(a, b)], axis=1), axis=0)
    return pa.RecordBatch.from_arrays([pa.array(np.ascontiguousarray(p[:, 0])), pa.array(np.ascontiguousarray(p[:, 1]))], names=["u", "v"])


def _led(turn: int):
    """Of a partition dealt by h: each set with leaders of its h that are in another group."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        t = _whole(batches)
        if t is None:
            return
        c, h, comp = _columns(t), t["h"].to_numpy(), t["comp"].to_numpy()
        for k in range(LEADERS):
            rank = c["sid"].view(np.uint64) * np.uint64(0x9E3779B97F4A7C15 + 2 * (turn * LEADERS + k) * 0x51ED27)
            rank ^= rank >> np.uint64(29)
            order = np.lexsort((rank * np.uint64(0xBF58476D1CE4E5B9), h))
            new = np.concatenate(([True], h[order][1:] != h[order][:-1]))
            lead = order[np.flatnonzero(new)][np.cumsum(new) - 1]
            ok = (comp[order] != comp[lead]) & _possible(c, order, c, lead)
            yield _pairs(c["sid"][order][ok], c["sid"][lead][ok])

    return run


def _across(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Of a partition dealt by h and blocks i, j: possible pairs in different components, of one block or between two."""
    t = _whole(batches)
    if t is None:
        return
    keys = [t[k].to_numpy() for k in ("j", "i", "h")]
    order = np.lexsort(keys)
    c = {k: v[order] for k, v in _columns(t).items()}
    keys = [k[order] for k in keys]
    comp, block, within = t["comp"].to_numpy()[order], t["block"].to_numpy()[order], keys[0] == keys[1]
    wide = np.frombuffer(b"".join(t["wide"].to_pylist()), np.uint64).reshape(len(comp), -1)[order]
    starts = np.flatnonzero(np.concatenate(([True], np.any([k[1:] != k[:-1] for k in keys], axis=0))))
    ends = np.repeat(np.append(starts[1:], len(comp)), np.diff(np.append(starts, len(comp))))
    at, apart, found, held = np.arange(len(comp)), 0, [], 0
    while len(at):
        apart += 1
        at = at[at + apart < ends[at]]
        to = at + apart
        live = (comp[at] != comp[to]) & (c["sid"][at] != c["sid"][to]) & (within[at] | (block[at] != block[to]))
        p, q = at[live], to[live]
        ok = _possible(c, p, c, q)
        p, q = p[ok], q[ok]
        ok = 9 * np.bitwise_count(wide[p] ^ wide[q]).sum(axis=1, dtype=np.int64) <= c["n"][p].astype(np.int64) + c["n"][q]
        found.append((c["sid"][p[ok]], c["sid"][q[ok]]))
        held += int(ok.sum())
        if held > PAIRS_AT_ONCE or not len(at):
            yield _pairs(*(np.concatenate(x) for x in zip(*found, strict=True)))
            found, held = [], 0


def _alike(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Pairs that the wide parities leave possible."""
    for batch in batches:
        if batch.num_rows:
            x, y = (np.frombuffer(b"".join(batch.column(k).to_pylist()), np.uint64).reshape(batch.num_rows, -1) for k in (2, 3))
            ok = 9 * np.bitwise_count(x ^ y).sum(axis=1, dtype=np.int64) <= batch.column(4).to_numpy()
            yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), batch.column(4)], names=["u", "v", "both"]).filter(pa.array(ok))


def _tall(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Parities of at least four bits a hash: those of WIDE bits are full for sets of over some 4,000 hashes and part nothing."""
    for batch in _slices(batches):
        sets = [np.frombuffer(raw, np.uint64) for raw in batch.column(1).to_pylist()]
        tall = [parity(x, min(MOST_BITS, max(WIDE, 1 << (4 * len(x) - 1).bit_length()))).tobytes() for x in sets]
        yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(tall, pa.binary())], names=["sid", "tall"])


def folded(words: np.ndarray, size: int) -> np.ndarray:
    """A parity of fewer bits, from one of more."""
    while len(words) > size:
        words = words[: len(words) // 2] ^ words[len(words) // 2 :]
    return words


def _tall_alike(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Pairs that the tall parities leave possible."""
    for batch in _slices(batches):
        ok = []
        for x, y, both in zip(*(batch.column(k).to_pylist() for k in (2, 3, 4)), strict=True):
            a, b = np.frombuffer(x, np.uint64), np.frombuffer(y, np.uint64)
            size = min(len(a), len(b))
            ok.append(9 * int(np.bitwise_count(folded(a, size) ^ folded(b, size)).sum(dtype=np.int64)) <= both)
        yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1)], names=["u", "v"]).filter(pa.array(ok, pa.bool_()))


def _similar(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for batch in _slices(batches):
        ok = []
        for x, y in zip(batch.column(2).to_pylist(), batch.column(3).to_pylist(), strict=True):
            a, b = np.frombuffer(x, np.uint64), np.frombuffer(y, np.uint64)
            both = len(np.intersect1d(a, b, assume_unique=True))
            ok.append(9 * both >= 4 * (len(a) + len(b)))
        yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1)], names=["u", "v"]).filter(pa.array(ok, pa.bool_()))


def _verified(pairs: DataFrame, sets: DataFrame) -> DataFrame:
    """The pairs whose whole sets have a similarity of 4/5."""
    first = materialise(pairs.distinct(), "near-first")
    a, b = (sets.select(F.col("sid").alias(k), F.col("n").alias(f"n_{k}"), F.col("wide").alias(f"w_{k}")) for k in "uv")
    seen = first.join(a, "u").join(b, "v").select("u", "v", "w_u", "w_v", (F.col("n_u") + F.col("n_v")).cast("long").alias("both"))
    pairs = materialise(seen.mapInArrow(_alike, "u long, v long, both long").distinct(), "near-wide-pairs")
    release(first)
    wanted = materialise(pairs.select(F.explode(F.array("u", "v")).alias("sid")).distinct(), "near-wanted")
    some = materialise(lookup(sets, wanted, ["sid"], "inner", salts=1).select("sid", "hashes"), "near-some")
    tall = materialise(some.mapInArrow(_tall, "sid long, tall binary").dropDuplicates(["sid"]), "near-tall")
    sides = pairs.join(tall.select(F.col("sid").alias("u"), F.col("tall").alias("x")), "u").join(tall.select(F.col("sid").alias("v"), F.col("tall").alias("y")), "v")
    was, pairs = pairs, materialise(sides.select("u", "v", "x", "y", "both").mapInArrow(_tall_alike, "u long, v long"), "near-pairs")
    release(was, tall)
    sides = pairs.join(some.select(F.col("sid").alias("u"), F.col("hashes").alias("x")), "u").join(some.select(F.col("sid").alias("v"), F.col("hashes").alias("y")), "v")
    out = materialise(sides.select("u", "v", "x", "y").mapInArrow(_similar, "u long, v long"), "near-links")
    release(pairs, wanted, some)
    return out


def _by_fingerprint(sets: DataFrame, radius: int) -> DataFrame:
    """Verified links (u, v) of sets with the least set of their fingerprint's group."""
    prints = materialise(sets.groupBy("print").agg(F.min("sid").alias("least"), F.max("sid").alias("most")), "near-prints")
    roots = materialise(prints.join(joined_prints(prints, radius), "print").select("print", "least", "most", "root"), "near-roots")
    groups = roots.groupBy("root").agg(F.min("least").alias("lead"), F.max("most").alias("most")).filter("lead != most").select("root", "lead")
    leads = materialise(lookup(roots, materialise(groups, "near-groups"), ["root"], "inner", "print").select("print", "lead"), "near-leads")
    pairs = lookup(sets.select("sid", "print"), leads, ["print"], "inner", "sid").filter("sid != lead").select(F.col("sid").alias("u"), F.col("lead").alias("v"))
    return _verified(pairs, sets)


def _apart(met: DataFrame, links: DataFrame, block: int = BLOCK) -> DataFrame:
    """The rows of hashes at which different groups meet, with their group and the number of blocks of the hash."""
    comps = materialise(closed(links).select(F.col("node_id").alias("sid"), F.col("comp_id").alias("comp")), "near-comps")
    placed = materialise(lookup(met, comps, ["sid"], "left", salts=1).withColumn("comp", F.coalesce("comp", "sid")), "near-placed")
    live = placed.groupBy("h").agg(F.count("*").alias("m"), F.min("comp").alias("a"), F.max("comp").alias("b")).filter("a != b")
    live = materialise(live.select("h", F.ceil(F.col("m") / block).cast("int").alias("blocks"), "m"), "near-live")
    hot, rest = (live.filter(c).select("h", "blocks") for c in (F.col("m") > HOT, F.col("m") <= HOT))  # one hot hash for HOT rows at most
    out = placed.join(F.broadcast(hot), "h").unionByName(lookup(placed.join(F.broadcast(hot), "h", "left_anti"), rest, ["h"], "inner", salts=1))
    out = materialise(out, "near-apart")
    release(comps, placed, live)
    return out


def near_copies(docs: DataFrame, shingle: int = 5, radius: int = 4, block: int = BLOCK) -> DataFrame:
    """(doc_id, component_id) of the documents that are not the least id of their component."""
    with arrow_rows(docs.sparkSession, ROWS_AT_ONCE):
        return _near_copies(docs, shingle, radius, block)


def _near_copies(docs: DataFrame, shingle: int, radius: int, block: int) -> DataFrame:
    spark = docs.sparkSession
    named = docs.filter("doc_id is not null").select(F.col("doc_id").cast("long").alias("doc_id"), binary_text().alias("raw"))
    rows = materialise(named.mapInArrow(_sets(shingle), "doc_id long, sid long, print long, n int, wide binary, hashes binary"), "near-sets")
    ids = materialise(rows.select("doc_id", "sid"), "near-ids")
    least = materialise(ids.groupBy("sid").agg(F.min("doc_id").alias("doc_id")), "near-least")
    again = materialise(ids.join(least.withColumnRenamed("doc_id", "least"), "sid").filter("doc_id != least").select("doc_id", "sid").distinct(), "near-again")
    sets = without(rows, again, ["doc_id", "sid"])
    links = _by_fingerprint(sets, radius)
    parts = partitions_for(spark, rows.count(), 8_000)
    met = materialise(sets.select("sid", "hashes").mapInArrow(_prefixes(_levels(rows)), MEETING).repartition(parts, "h").mapInArrow(_meeting, MEETING), "near-met")
    for turn in range(ROUNDS):
        placed = _apart(met, links)
        if placed.isEmpty():
            break
        more = _verified(placed.repartition(parts, "h").mapInArrow(_led(turn), "u long, v long"), sets)
        was, links = links, materialise(links.unionByName(more), "near-links")
        release(was, more, placed)
    placed = _apart(met, links, block).withColumn("block", F.pmod(F.xxhash64("sid"), F.col("blocks")).cast("int"))
    placed = placed.withColumn("_to", F.explode(F.sequence(F.lit(0), F.col("blocks") - 1))).withColumn("i", F.least("block", "_to")).withColumn("j", F.greatest("block", "_to"))
    wide = materialise(sets.select("sid", "wide").dropDuplicates(["sid"]), "near-wide")
    placed = lookup(placed, wide, ["sid"], "inner", limit=50_000, salts=1)
    rest = _verified(placed.repartition(parts, "h", "i", "j").mapInArrow(_across, "u long, v long"), sets)
    linked = materialise(closed(materialise(links.unionByName(rest), "near-all-links")).select(F.col("node_id").alias("sid"), "comp_id"), "near-linked")
    known = materialise(lookup(least, linked, ["sid"], "left", salts=1).withColumn("comp", F.coalesce("comp_id", "sid")).select("sid", "comp", "doc_id"), "near-known")
    first = materialise(known.groupBy("comp").agg(F.min("doc_id").alias("component_id")), "near-first")
    named = materialise(lookup(known, first, ["comp"], "inner", "sid").select("sid", "component_id"), "near-named")
    found = ids.join(named, "sid").filter("doc_id != component_id").select("doc_id", "component_id").distinct()
    out = materialise(found, "near-copies")
    release(rows, ids, least, again, met, links, rest, wide, linked, known, first, named)
    return out
