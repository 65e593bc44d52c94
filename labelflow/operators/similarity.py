"""Similarity graphs from data: TF-IDF and vector cosine, k nearest neighbours, thresholds, and hashing for scale."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from labelflow.operators.graph import canonical
from labelflow.plans.joins import lookup
from labelflow.plans.stage import materialise

#: Whole-number scale of quantised vectors and of similarities.
QUANT = 1000
WORD = r"[^\x00-\x2F\x3A-\x40\x5B-\x60\x7B-\x7F]+"


def tokens(text: Column) -> Column:
    """Lower-case words."""
    return F.regexp_extract_all(F.lower(text), F.lit(f"({WORD})"), F.lit(1))


def tfidf(docs: DataFrame, ident: str = "doc_id", text: str = "text", min_df: int = 2, max_df: float = 1.0, max_terms: int | None = None) -> DataFrame:
    """(node_id, term, weight): counts times log((N + 1) / (df + 1)), scaled to unit length. Terms in fewer than min_df or more than a share
    max_df of documents are left out; max_terms keeps the heaviest of a document."""
    words = docs.select(F.col(ident).alias("node_id"), F.explode(tokens(F.col(text))).alias("term"))
    counts = materialise(words.groupBy("node_id", "term").agg(F.count("*").alias("tf")), "tf")
    n = docs.count()
    df = counts.groupBy("term").agg(F.count("*").alias("df")).filter((F.col("df") >= min_df) & (F.col("df") <= max_df * n))
    idf = materialise(df.select("term", F.log((F.lit(n) + 1) / (F.col("df") + 1)).alias("idf")), "idf")
    rows = lookup(counts, idf, ["term"], "inner", "node_id").select("node_id", "term", (F.col("tf") * F.col("idf")).alias("x")).filter("x > 0")
    if max_terms:
        top = F.row_number().over(Window.partitionBy("node_id").orderBy(F.desc("x"), "term"))
        rows = rows.withColumn("place", top).filter(F.col("place") <= max_terms).drop("place")
    norms = rows.groupBy("node_id").agg(F.sqrt(F.sum(F.col("x") * F.col("x"))).alias("norm"))
    return rows.join(norms, "node_id").select("node_id", "term", (F.col("x") / F.col("norm")).alias("weight"))


def hashed_tfidf(docs: DataFrame, ident: str = "doc_id", text: str = "text", features: int = 1 << 14) -> DataFrame:
    """(node_id, features): TF-IDF as one sparse vector a document, terms hashed, for corpora whose vocabulary is too large."""
    from pyspark.ml.feature import IDF, HashingTF, Normalizer

    words = docs.select(F.col(ident).alias("node_id"), tokens(F.col(text)).alias("words"))
    tf = HashingTF(numFeatures=features, inputCol="words", outputCol="tf").transform(words)
    scaled = IDF(inputCol="tf", outputCol="x", minDocFreq=2).fit(tf).transform(tf)
    return Normalizer(inputCol="x", outputCol="features").transform(scaled).select("node_id", "features")


def sparse_cosine(terms: DataFrame) -> DataFrame:
    """(u, v, sim) of pairs that share a term: an inverted-index join. Common terms make df^2 pairs, so they are to be cut by max_df or
    max_terms before."""
    a, b = terms.select(F.col("node_id").alias("u"), "term", F.col("weight").alias("a")), terms.select(F.col("node_id").alias("v"), "term", F.col("weight").alias("b"))
    return a.join(b, "term").filter("u < v").groupBy("u", "v").agg(F.sum(F.col("a") * F.col("b")).alias("sim"))


def cosine_knn(terms: DataFrame, k: int, block: int = 1000, columns: int = 4096) -> DataFrame:
    """(u, v, sim): for each u the k best v of every block, over all terms, so that the k best of all are among them; sim is whole millionths.

    Documents are dealt over blocks of about `block`; each pair of blocks is a task of its own that multiplies the two as matrices, `columns`
    terms at a time. No term makes pairs of rows, however common. Terms go by their 64-bit hash."""
    rows = terms.groupBy("node_id").agg(F.collect_list(F.xxhash64("term")).alias("h"), F.collect_list("weight").alias("x"))
    rows = materialise(rows, "vectors")
    blocks = max(1, -(-rows.count() // block))
    rows = rows.withColumn("block", F.pmod(F.xxhash64("node_id"), F.lit(blocks)).cast("int"))
    rows = rows.withColumn("other", F.explode(F.sequence(F.lit(0), F.lit(blocks - 1)))).withColumn("i", F.least("block", "other")).withColumn("j", F.greatest("block", "other"))

    def flat(t: pa.Table) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
        h = t["h"].combine_chunks()
        size = np.diff(h.offsets.to_numpy())
        return t["node_id"].to_numpy(), np.repeat(np.arange(len(size)), size), h.flatten().to_numpy(), t["x"].combine_chunks().flatten().to_numpy()

    def best(ids: np.ndarray, others: np.ndarray, sims: np.ndarray) -> pa.Table:
        order = np.argsort(others)
        others, sims = others[order], sims[:, order].copy()
        sims[ids[:, None] == others[None, :]] = -1
        top = np.argsort(-sims, axis=1, kind="stable")[:, :k]  # ties go to the smaller id
        got = np.take_along_axis(sims, top, axis=1)
        u, v, w = np.repeat(ids, top.shape[1]), others[top].ravel(), got.ravel()
        return pa.table({"u": u[w > 0], "v": v[w > 0], "sim": w[w > 0]})

    def score(key: tuple, group: pa.Table) -> pa.Table:
        at = group["block"].to_numpy()
        i, j = key[0].as_py(), key[1].as_py()
        a = flat(group.filter(pa.array(at == i)))
        b = flat(group.filter(pa.array(at == j)))
        both = np.intersect1d(a[2], b[2])
        sims = np.zeros((len(a[0]), len(b[0])))
        place = []
        for _, r, h, x in (a, b):
            keep = np.isin(h, both)
            c = np.searchsorted(both, h[keep])
            o = np.argsort(c, kind="stable")
            place.append((r[keep][o], c[o], x[keep][o]))
        for low in range(0, len(both), columns):
            m = []
            for (r, c, x), n in zip(place, sims.shape, strict=True):
                p, q = np.searchsorted(c, (low, low + columns))
                dense = np.zeros((n, columns))
                dense[r[p:q], c[p:q] - low] = x[p:q]
                m.append(dense)
            sims += m[0] @ m[1].T
        whole = np.rint(sims * 1_000_000).astype(np.int64)
        out = best(a[0], b[0], whole)
        return out if i == j else pa.concat_tables([out, best(b[0], a[0], whole.T)])

    return rows.groupBy("i", "j").applyInArrow(score, "u long, v long, sim long")


def quantised(vecs: DataFrame, ident: str = "vec_id", vec: str = "embedding") -> DataFrame:
    """(node_id, q): coordinates as whole thousandths, so that products are exact."""
    return vecs.select(F.col(ident).alias("node_id"), F.transform(vec, lambda x: F.floor(x.cast("double") * QUANT + 0.5).cast("long")).alias("q"))


def dense_pairs(vecs: DataFrame, queries: DataFrame | None = None, block: int = 1024) -> DataFrame:
    """(u, v, sim): whole-number dot products of quantised vectors, u of the queries against all v, in blocks.

    A stated query block set against all rows: queries are cut into blocks of `block` vectors, each broadcast to one pass over the rows in
    numpy; use lsh_knn where both sides are large."""
    q = vecs if queries is None else queries
    rows = q.orderBy("node_id").collect() if q.limit(50_001).count() <= 50_000 else None
    if rows is None:
        raise ValueError("more than 50,000 query vectors: use lsh_knn")
    out = None
    for at in range(0, max(1, len(rows)), 50_000):
        part = rows[at : at + 50_000]
        ids = np.array([r.node_id for r in part], np.int64)
        mat = np.array([r.q for r in part], np.int64)

        def score(batches, ids=ids, mat=mat):
            for batch in batches:
                v = batch.column(0).to_numpy()
                x = np.stack(batch.column(1).to_numpy(zero_copy_only=False)).astype(np.int64) if batch.num_rows else np.zeros((0, mat.shape[1]), np.int64)
                for a in range(0, len(ids), block):
                    sims = x.astype(np.float64) @ mat[a : a + block].T.astype(np.float64)  # exact: products stay far below 2^53
                    yield pa.RecordBatch.from_arrays([pa.array(np.tile(ids[a : a + block], len(v))), pa.array(np.repeat(v, len(ids[a : a + block]))), pa.array(sims.ravel().astype(np.int64))], names=["u", "v", "sim"])

        got = vecs.mapInArrow(score, "u long, v long, sim long").filter("u != v")
        out = got if out is None else out.unionByName(got)
    return out


def knn(pairs: DataFrame, k: int) -> DataFrame:
    """The k best partners of each u by similarity, ties by smaller id; planned as a group limit before the shuffle."""
    place = F.row_number().over(Window.partitionBy("u").orderBy(F.desc("sim"), "v"))
    return pairs.withColumn("place", place).filter(F.col("place") <= k).drop("place")


def both_ways(pairs: DataFrame) -> DataFrame:
    """Pairs with u < v as candidates of both ends."""
    return pairs.select("u", "v", "sim").unionByName(pairs.select(F.col("v").alias("u"), F.col("u").alias("v"), "sim"))


def knn_edges(pairs: DataFrame, k: int, symmetrise: str = "union") -> DataFrame:
    """Edges (u, v, w) of the k-nearest-neighbour graph: `union` keeps a choice of either end, `mutual` of both. `pairs` holds each
    directed candidate; the weight is the similarity, positive ones only."""
    best = knn(pairs, k).filter("sim > 0")
    e = best.select(F.least("u", "v").alias("u"), F.greatest("u", "v").alias("v"), F.col("sim").alias("w"))
    if symmetrise == "mutual":
        return e.groupBy("u", "v").agg(F.max("w").alias("w"), F.count("*").alias("n")).filter("n = 2").drop("n")
    return canonical(e, "max")


def eps_edges(pairs: DataFrame, eps: float) -> DataFrame:
    """Edges of pairs more similar than eps."""
    return canonical(pairs.filter(F.col("sim") > eps).select("u", "v", F.col("sim").alias("w")), "max")


def lsh_buckets(vecs: DataFrame, planes: int = 8, tables: int = 8, seed: int = 7) -> DataFrame:
    """(node_id, q, table, bucket): signs against random hyperplanes."""
    rng = np.random.default_rng(seed)
    dim = len(vecs.first().q)
    normals = rng.standard_normal((tables, planes, dim))

    def sign(batches):
        for batch in batches:
            x = np.stack(batch.column(1).to_numpy(zero_copy_only=False)).astype(float) if batch.num_rows else np.zeros((0, dim))
            n = len(x)
            bits = np.einsum("tpd,nd->ntp", normals, x) > 0
            code = (bits * (1 << np.arange(planes))).sum(2).astype(np.int32)
            idx = np.repeat(np.arange(n), tables)
            yield pa.RecordBatch.from_arrays([batch.column(0).take(pa.array(idx)), batch.column(1).take(pa.array(idx)), pa.array(np.tile(np.arange(tables, dtype=np.int32), n)), pa.array(code.ravel())], names=["node_id", "q", "table", "bucket"])

    return vecs.select("node_id", "q").mapInArrow(sign, "node_id long, q array<long>, table int, bucket int")


def lsh_knn(vecs: DataFrame, k: int, planes: int = 8, tables: int = 8, seed: int = 7, bucket_rows: int = 2_000, queries: DataFrame | None = None) -> DataFrame:
    """(u, v, sim): approximate k nearest neighbours. A bucket larger than bucket_rows is dealt over salts, each of which meets the whole
    bucket, so that no candidate is lost; the candidates are re-ranked exactly. `queries` (node_id) restricts u, as an insertion needs."""
    b = materialise(lsh_buckets(vecs, planes, tables, seed), "lsh")
    heavy = materialise(b.groupBy("table", "bucket").agg(F.count("*").alias("n")).filter(F.col("n") > bucket_rows).select("table", "bucket", F.ceil(F.col("n") / bucket_rows).cast("int").alias("salts")), "heavy")
    b = lookup(b, heavy, ["table", "bucket"], "left", "node_id").withColumn("salts", F.coalesce("salts", F.lit(1)))
    left = b.select(F.col("node_id").alias("u"), F.col("q").alias("qu"), "table", "bucket", F.pmod(F.xxhash64("node_id"), F.col("salts")).cast("int").alias("salt"))
    if queries is not None:
        asked = materialise(queries.select(F.col("node_id").alias("u"), F.lit(True).alias("asked")).distinct(), "asked")
        left = lookup(left, asked, ["u"], "inner", salts=1).drop("asked")
    other = b.select(F.col("node_id").alias("v"), F.col("q").alias("qv"), "table", "bucket", F.explode(F.sequence(F.lit(0), F.col("salts") - 1)).alias("salt"))
    pairs = left.join(other, ["table", "bucket", "salt"]).filter("u != v")
    sim = F.aggregate(F.zip_with("qu", "qv", lambda x, y: x * y), F.lit(0).cast("long"), lambda a, x: a + x)
    return knn(pairs.select("u", "v", sim.alias("sim")).distinct(), k)  # the vectors stay out of the shuffle


def insert_knn(old: DataFrame, new: DataFrame, k: int, search: str = "exact", planes: int = 3, tables: int = 16) -> DataFrame:
    """Edges (u, v, w) by which inserted vectors join: each picks its k best among live and co-inserted ones; old lists stay as they are.
    `exact` compares a batch of bounded size with all vectors; `lsh` meets them in buckets, for a batch of any size."""
    both = old.unionByName(new)
    if search == "exact":
        return knn_edges(dense_pairs(both, new), k)
    if search != "lsh":
        raise ValueError("search is exact or lsh")
    return knn_edges(lsh_knn(both, k, planes, tables, queries=new), k)


def changed_lists(pairs: DataFrame, new_ids: DataFrame, k: int) -> DataFrame:
    """Nodes whose k best change once the new nodes count: both ends of an edge that such a node drops are affected too."""
    old_best = knn(lookup(pairs, new_ids.select(F.col("node_id").alias("v"), F.lit(1).alias("new")), ["v"], "left", "u").filter("new is null").drop("new"), k)
    best = knn(pairs, k)
    lost = old_best.join(best.select("u", "v"), ["u", "v"], "left_anti")
    return lost.select(F.explode(F.array("u", "v")).alias("node_id")).distinct()
