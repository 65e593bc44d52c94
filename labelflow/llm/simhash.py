"""SimHash near-duplicates by meet-in-the-middle ball hashing.

Two fingerprints within `radius` differing bits share a variant that lies within half the radius of both. Every distinct
fingerprint emits all its variants (2,081 for radius 4), variants are dealt over buckets and equal ones meet. Any two
fingerprints that emit one variant are within the radius of each other, so each is linked to the first of them (a distance
that is verified), and the closure loses no link.

Links stay linear in the size of a group. The variant space is cut into passes, two small ones first (1/256 and 15/256 of
it, then `slices` equal parts of the rest); after each small pass the components found so far are contracted, and a variant
carries the root of its fingerprint's component. Whatever meets under one root is settled already and makes no row; what is
left of a chunk or a bucket goes through a union-find and comes out as a star per component, at most one row per root.
Fingerprints travel sorted by root, so that the members of a dense group meet in their chunk first.

The variants travel as sorted packed runs, not as rows, so that disk holds one pass at a time.

Defined results: null and empty texts and texts of white space alone have no words and the fingerprint zero, linked like any
other; fewer words than a shingle make one shingle of all; rows that share a doc_id are scored one by one; a component of
null ids only has a null id; other columns are ignored.
"""

from __future__ import annotations

from collections.abc import Iterator
from functools import lru_cache, reduce
from itertools import combinations

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from labelflow.llm.common import binary_text, materialise, partitions_for, release
from labelflow.operators.components import connected_components, label_block
from labelflow.plans.joins import lookup

SEED = 42
RUN = 2048
SLICES = 4
VARIANTS_PER_BUCKET = 2_000_000
#: A task ships one run per bucket, so buckets of few variants would make more runs than they hold work.
LEAST_IN_BUCKET = 500_000
FEW_LINKS = 10_000
HASHES_AT_ONCE = 1 << 18
#: An odd factor scatters variants over slices and buckets; as a bijection it keeps equality.
SCATTER = 0x9E3779B97F4A7C15
UNSCATTER = pow(SCATTER, -1, 1 << 64)


def majority_bits(hashes: np.ndarray) -> int:
    """64 bits, each 1 if set in over half of the hashes."""
    count = np.zeros(64, np.int64)
    for at in range(0, len(hashes), HASHES_AT_ONCE):
        part = hashes[at : at + HASHES_AT_ONCE]
        count += np.unpackbits(part.view(np.uint8).reshape(-1, 8), axis=1, bitorder="little").sum(axis=0, dtype=np.int64)
    return int(np.packbits(2 * count > len(hashes), bitorder="little").view(np.uint64)[0])


def shingle_hashes(raw: bytes, shingle: int) -> np.ndarray:
    """Hashes of a UTF-8 text's shingles: A-Z lower-cased, words split at ASCII white space, shingles of consecutive words."""
    words = raw.lower().split()
    if not words:
        return np.empty(0, np.uint64)
    text = b" ".join(words)
    if len(words) < shingle:
        return np.array([xxhash.xxh64_intdigest(text, SEED)], np.uint64)
    ends = np.cumsum(np.fromiter(map(len, words), np.int64, len(words)) + 1) - 1
    starts = np.concatenate(([0], ends[:-1] + 1))
    digest = xxhash.xxh64_intdigest
    n = len(words) - shingle + 1
    return np.fromiter((digest(text[a:b], SEED) for a, b in zip(starts[:n].tolist(), ends[shingle - 1 :].tolist(), strict=True)), np.uint64, n)


def simhash(raw: bytes, shingle: int) -> int:
    """Fingerprint of a UTF-8 text; 0 without words."""
    return majority_bits(shingle_hashes(raw, shingle))


def _fingerprint_rows(shingle: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            prints = np.fromiter((simhash(raw, shingle) for raw in batch.column(1).to_pylist()), np.uint64, batch.num_rows)
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(prints.view(np.int64))], names=["doc_id", "print"])

    return run


def fingerprints(docs: DataFrame, shingle: int = 4) -> DataFrame:
    """(doc_id, print as a signed long), one row per row."""
    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), binary_text().alias("raw")).mapInArrow(_fingerprint_rows(shingle), "doc_id long, print long")


@lru_cache(maxsize=4)
def ball(radius: int) -> np.ndarray:
    """All bit masks of at most `radius` bits."""
    masks = [0]
    for k in range(1, radius + 1):
        masks += [sum(1 << b for b in bits) for bits in combinations(range(64), k)]
    return np.array(masks, np.uint64)


def _forest(u: np.ndarray, v: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """A star for each component of the links: (member, least member) of the members that are not the least."""
    if not len(u):
        return np.empty(0, np.int64), np.empty(0, np.int64)
    found = label_block(pa.table({"u": u.view(np.int64), "v": v.view(np.int64)}))
    node, comp = found["node_id"].to_numpy(), found["comp_id"].to_numpy()
    return node[node != comp], comp[node != comp]


def _meetings(keys: np.ndarray, prints: np.ndarray, roots: np.ndarray, radius: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Of entries sorted by variant: the index of the first of each variant, and a forest that joins the roots that meet."""
    first = np.concatenate(([True], keys[1:] != keys[:-1]))
    at = np.flatnonzero(first)
    if len(at) == len(keys):
        return at, *_forest(prints[:0], prints[:0])
    lead = at[np.cumsum(first) - 1]
    other = np.flatnonzero((roots != roots[lead]) & (np.bitwise_count(prints ^ prints[lead]) <= radius))
    return at, *_forest(roots[other], roots[lead[other]])


def spaces(slices: int) -> list[tuple[int, int]]:
    """The passes over the scattered variant space as (first, last): two small ones, then `slices` equal ones."""
    cuts = [0, 1 << 56, 1 << 60, *(((1 << 60) + k * (15 << 60) // slices) for k in range(1, slices)), 1 << 64]
    return [(a, b - 1) for a, b in zip(cuts[:-1], cuts[1:], strict=True)]


def _emit(radius: int, space: tuple[int, int], buckets: int):
    masks = ball(radius // 2)
    low, high = np.uint64(space[0]), np.uint64(space[1])
    edges = np.array([space[0] + (space[1] - space[0]) * b // buckets for b in range(1, buckets)], np.uint64)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            prints, roots = (batch.column(k).to_numpy(zero_copy_only=False).view(np.uint64) for k in range(2))
            for at in range(0, len(prints), RUN):
                mine, root = prints[at : at + RUN], roots[at : at + RUN]
                keys = ((mine[:, None] ^ masks[None, :]) * np.uint64(SCATTER)).ravel()
                spot = np.flatnonzero((keys >= low) & (keys <= high))
                keys = keys[spot]
                order = np.argsort(keys)
                keys, spot = keys[order], spot[order]
                owner = spot // len(masks)
                lead, a, b = _meetings(keys, mine[owner], root[owner], radius)
                keys, owner = keys[lead], owner[lead]
                far = root[owner] != mine[owner]
                marks = (spot[lead] % len(masks)).astype(np.uint16) | (far.astype(np.uint16) << np.uint16(15))
                far_roots, far_before = root[owner][far], np.concatenate(([0], np.cumsum(far)))
                cuts = np.concatenate(([0], np.searchsorted(keys, edges), [len(keys)])).tolist()
                rows = [(k, keys[x:y].tobytes(), marks[x:y].tobytes(), far_roots[far_before[x] : far_before[y]].tobytes(), b"", b"") for k, (x, y) in enumerate(zip(cuts[:-1], cuts[1:], strict=True)) if y > x]
                if len(a):
                    rows.append((int(mine[0] % np.uint64(buckets)), b"", b"", b"", a.tobytes(), b.tobytes()))
                if rows:
                    cols = list(zip(*rows, strict=True))
                    yield pa.RecordBatch.from_arrays([pa.array(cols[0], pa.int32()), *(pa.array(c, pa.binary()) for c in cols[1:])], names=["bucket", "keys", "marks", "roots", "a", "b"])

    return run


def _meet(radius: int):
    masks = ball(radius // 2)

    def run(key: tuple, group: pa.Table) -> pa.Table:
        joined = lambda name, kind: np.frombuffer(b"".join(group[name].to_pylist()), kind)
        keys, marks, u, v = joined("keys", np.uint64), joined("marks", np.uint16), joined("a", np.int64), joined("b", np.int64)
        if len(keys):
            prints = (keys * np.uint64(UNSCATTER)) ^ masks[marks & np.uint16(0x7FFF)]
            roots = prints.copy()
            roots[marks >> np.uint16(15) == 1] = joined("roots", np.uint64)
            order = np.argsort(keys)
            _, more_u, more_v = _meetings(keys[order], prints[order], roots[order], radius)
            u, v = _forest(np.concatenate((u, more_u)), np.concatenate((v, more_v)))
        else:
            u, v = _forest(u, v)
        return pa.table({"u": u, "v": v})

    return run


def _pass(state: DataFrame, n: int, radius: int, space: tuple[int, int]) -> DataFrame:
    """Links between roots that the variants of one pass make."""
    spark = state.sparkSession
    share = n * len(ball(radius // 2)) * (space[1] - space[0] >> 40) >> 24
    buckets = max(1, -(-share // VARIANTS_PER_BUCKET), min(share // LEAST_IN_BUCKET, partitions_for(spark, 0, 1)))
    spread = state.repartitionByRange(partitions_for(spark, n, RUN * 4), "root", "print").sortWithinPartitions("root", "print")
    rows = spread.select("print", "root").mapInArrow(_emit(radius, space, buckets), "bucket int, keys binary, marks binary, roots binary, a binary, b binary")
    return materialise(rows.groupBy("bucket").applyInArrow(_meet(radius), "u long, v long"), "links")


def _contracted(state: DataFrame, links: DataFrame) -> DataFrame:
    """(print, root) after the links between roots are closed."""
    if links.isEmpty():
        return state
    comps = materialise(closed(links).select(F.col("node_id").alias("root"), "comp_id"), "roots")
    out = materialise(lookup(state, comps, ["root"], "left", "print").select("print", F.coalesce("comp_id", "root").alias("root")), "state")
    release(comps, state)
    return out


def closed(links: DataFrame) -> DataFrame:
    """Components of links; a few links are labelled in one task, more by distributed rounds."""
    return connected_components(links, method="one_task" if links.count() <= FEW_LINKS else "contract")


def joined_prints(prints: DataFrame, radius: int = 4, slices: int = SLICES) -> DataFrame:
    """(print, root) of distinct fingerprints (column `print`): equal roots mean linked by steps of at most `radius` bits."""
    state = materialise(prints.select("print", F.col("print").alias("root")), "state")
    n = state.count()
    passes, held = spaces(slices), []
    for k, space in enumerate(passes):
        held.append(_pass(state, n, radius, space))
        if k < 2 or k == len(passes) - 1:
            state = _contracted(state, reduce(DataFrame.unionByName, held))
            release(*held)
            held = []
    return state


def components(docs: DataFrame, shingle: int = 4, radius: int = 4, slices: int = SLICES) -> DataFrame:
    """(doc_id, print, component_id): the smallest doc_id that links lead to."""
    rows = materialise(fingerprints(docs, shingle), "simhash")
    nodes = materialise(rows.groupBy("print").agg(F.min("doc_id").alias("least")), "prints")
    roots = joined_prints(nodes, radius, slices)
    placed = materialise(nodes.join(roots, "print").select("print", "least", "root"), "placed")
    least = placed.groupBy("root").agg(F.min("least").alias("component_id"), F.count("*").alias("n"))
    grouped = materialise(least.filter("n > 1").select("root", "component_id"), "grouped")
    places = materialise(lookup(placed, grouped, ["root"], "left", "print").select("print", F.coalesce("component_id", "least").alias("component_id")), "places")
    release(nodes, roots, placed, grouped)
    return rows.join(places, "print").select("doc_id", "print", "component_id")


def near_duplicates(docs: DataFrame, shingle: int = 4, radius: int = 4, slices: int = SLICES) -> DataFrame:
    """(doc_id, fingerprint as 16 hex digits, component_id)."""
    found = components(docs, shingle, radius, slices)
    return found.select("doc_id", F.lower(F.lpad(F.hex("print"), 16, "0")).alias("fingerprint"), "component_id")
