"""Mixing sources to target weights by Poisson replication.

A source's repetition rate is its target share of the output over its rows. Each document draws its number of copies by inverting
the Poisson distribution of that rate at a uniform number made from the hash of its id and the seed, so draws need no state
and repeat exactly. A rate above 30 is split into equal parts drawn with hashes of their own, which keeps the inversion within
double range. Documents are exploded by their count and dealt over partitions by the hash of (id, copy), in whose order each
partition is sorted: a global shuffle with one exchange, into as many partitions as the expected bytes ask for.

Defined results: rows that repeat an id draw the same count; a null source is a source of its own; a source without a weight, or
with a weight of zero or less, gets rate zero and no rows; null ids hash as the text `null`; other columns pass through.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from labelflow.llm.common import materialise, partitions_for
from labelflow.plans.joins import lookup

SEED = 20240613
PART = 30.0
#: Bytes of the scanned files (compressed) that one partition of the shuffled output is meant to hold.
BYTES_PER_PARTITION = 64 << 20
#: The optimizer's size of a plan that it can't tell, or a product of such.
UNKNOWN_SIZE = 1 << 60
NO_SOURCE = "\x00"


def uniform(ident: Column, seed: int, part: Column | int = 0) -> Column:
    """52-bit uniform number in [0, 1) from an md5 of seed, id and part."""
    part = F.lit(part) if isinstance(part, int) else part
    digits = F.substring(F.md5(F.concat_ws(":", F.lit(str(seed)), F.coalesce(ident.cast("string"), F.lit("null")), part.cast("string"))), 1, 13)
    return F.conv(digits, 16, 10).cast("long") / F.lit(float(1 << 52))


def shuffle_key(ident: Column, copy: Column, seed: int) -> Column:
    return F.conv(F.substring(F.md5(F.concat_ws(":", F.lit(f"{seed}/copy"), F.coalesce(ident.cast("string"), F.lit("null")), copy.cast("string"))), 1, 15), 16, 10).cast("long")


def cumulative(rate: Column) -> Column:
    """The Poisson distribution function at 0, 1, ... as far as doubles tell it from 1."""
    last = F.ceil(rate + 12 * F.sqrt(rate) + 20).cast("int")
    start = F.struct(F.exp(-rate).alias("p"), F.exp(-rate).alias("c"), F.array(F.exp(-rate)).alias("all"))
    grown = F.aggregate(F.sequence(F.lit(1), last), start, lambda s, k: F.struct((s["p"] * rate / k).alias("p"), (s["c"] + s["p"] * rate / k).alias("c"), F.concat(s["all"], F.array(s["c"] + s["p"] * rate / k)).alias("all")))
    return grown["all"]


def source_rates(docs: DataFrame, weights: DataFrame | None, total: float | None, temperature: float) -> DataFrame:
    """(mix_source, rate, parts, cdf) per source. Without weights a source weighs its rows to the power `temperature`."""
    name = F.coalesce(F.col("source"), F.lit(NO_SOURCE)).alias("mix_source")
    counts = docs.select(name).groupBy("mix_source").agg(F.count("*").alias("n"))
    if weights is None:
        counts = counts.withColumn("weight", F.pow(F.col("n").cast("double"), F.lit(temperature)))
    else:
        given = weights.select(name, F.col("weight").cast("double").alias("weight")).groupBy("mix_source").agg(F.sum("weight").alias("weight"))
        counts = counts.join(given, "mix_source", "left")
    counts = materialise(counts.withColumn("weight", F.greatest(F.coalesce("weight", F.lit(0.0)), F.lit(0.0))), "sources")
    sums = counts.agg(F.sum("weight").alias("w"), F.sum("n").alias("n")).first()
    scale = (total if total is not None else float(sums.n or 0)) / sums.w if sums.w else 0.0
    rated = counts.select("mix_source", (F.col("weight") * scale / F.col("n")).alias("rate"))
    parts = F.greatest(F.lit(1), F.ceil(F.col("rate") / PART)).cast("int")
    return materialise(rated.withColumn("parts", parts).withColumn("cdf", cumulative(F.col("rate") / F.col("parts"))), "rates")


def drawn(docs: DataFrame, rates: DataFrame, seed: int = SEED) -> DataFrame:
    """The documents with _rate and _copies."""
    rows = docs.withColumn("mix_source", F.coalesce(F.col("source"), F.lit(NO_SOURCE)))
    rows = lookup(rows, rates, ["mix_source"], "left", "doc_id")
    one = lambda j: F.size(F.filter("cdf", lambda c: c <= uniform(F.col("doc_id"), seed, j)))
    single = F.size(F.filter("cdf", lambda c: c <= F.col("_u")))
    many = F.aggregate(F.sequence(F.lit(0), F.col("parts") - 1), F.lit(0), lambda n, j: n + one(j))
    rows = rows.withColumn("_u", uniform(F.col("doc_id"), seed, 0)).withColumn("_copies", F.when(F.col("parts") == 1, single).otherwise(many))
    return rows.withColumnRenamed("rate", "_rate").drop("_u", "parts", "cdf", "mix_source")


def _bytes_out(docs: DataFrame, total: float | None) -> int:
    """Expected bytes after replication: what the optimizer knows of the input's size, times rows out over rows in. Where it knows
    none (rows that are not read from files), the strings are measured."""
    size = int(str(docs._jdf.queryExecution().optimizedPlan().stats().sizeInBytes()))
    if size >= UNKNOWN_SIZE:
        strings = [F.coalesce(F.octet_length(c), F.lit(0)) for c, kind in docs.dtypes if kind == "string"]
        size = int(docs.agg(F.sum(sum(strings, F.lit(8 * len(docs.columns)))).alias("bytes")).first().bytes or 0)
    if total is None:
        return size
    return int(size * min(1e4, total / max(1, docs.count())))


def mix(docs: DataFrame, weights: DataFrame | None = None, total: float | None = None, temperature: float = 0.7, seed: int = SEED) -> DataFrame:
    """Documents replicated to the target mix and shuffled, with _rate, _copies, _copy (from 0) and _key (the shuffle's order).

    `weights` holds (source, weight); `total` is the expected number of rows out, by default as many as come in."""
    clash = {"_rate", "_copies", "_copy", "_key", "_u", "mix_source", "parts", "cdf", "rate"} & {c.lower() for c in docs.columns}
    if clash:
        raise ValueError(f"rename the columns {sorted(clash)}: the operator's own go by these names")
    rates = source_rates(docs, weights, total, temperature)
    rows = drawn(docs, rates, seed).filter("_copies > 0")
    rows = rows.withColumn("_copy", F.explode(F.sequence(F.lit(0), F.col("_copies") - 1))).withColumn("_key", shuffle_key(F.col("doc_id"), F.col("_copy"), seed))
    n = partitions_for(docs.sparkSession, _bytes_out(docs, total), BYTES_PER_PARTITION)
    return rows.repartition(n, "_key").sortWithinPartitions("_key", "doc_id")
