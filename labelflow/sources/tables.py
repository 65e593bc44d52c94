"""Readers with declared schemas: unknown columns go nowhere, null keys are refused."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

_L, _I, _D, _S, _N = T.LongType(), T.IntegerType(), T.DoubleType(), T.StringType(), T.TimestampNTZType()
SCHEMAS: dict[str, list[tuple[str, T.DataType]]] = {
    "documents": [("doc_id", _L), ("text", _S), ("lang", _S), ("source", _S), ("n_chars", _L)],
    "labels": [("doc_id", _L), ("quality", _I), ("toxic", _I)],
    "embeddings": [("vec_id", _L), ("embedding", T.ArrayType(T.FloatType())), ("label", _I)],
    "orders": [("o_orderkey", _L), ("o_custkey", _L), ("o_orderstatus", _S), ("o_totalprice", _D), ("o_orderdate", _N), ("o_orderpriority", _S)],
    "lineitem": [("l_orderkey", _L), ("l_partkey", _L), ("l_suppkey", _L), ("l_linenumber", _I), ("l_quantity", _D), ("l_extendedprice", _D), ("l_discount", _D), ("l_tax", _D), ("l_returnflag", _S), ("l_linestatus", _S), ("l_shipdate", _N)],
    "part": [("p_partkey", _L), ("p_name", _S), ("p_brand", _S), ("p_type", _S), ("p_size", _I), ("p_retailprice", _D)],
    "customer": [("c_custkey", _L), ("c_name", _S), ("c_nationkey", _I), ("c_acctbal", _D), ("c_mktsegment", _S)],
    "supplier": [("s_suppkey", _L), ("s_name", _S), ("s_nationkey", _I), ("s_acctbal", _D)],
    "events": [("event_id", _L), ("ts", _N), ("user_id", _L), ("event_type", _S), ("value", _D), ("props", _S)],
    "pages": [("page_id", _L), ("url", _S), ("html", _S)],
    "benchmark": [("item_id", _L), ("text", _S)],
    "conversations": [("conv_id", _L), ("turn", _L), ("role", _S), ("text", _S)],
}
NODES = T.StructType([T.StructField("node_id", _L, False), T.StructField("truth", T.ByteType()), T.StructField("born_batch", _I), T.StructField("dead_batch", _I)])
ARCS = T.StructType([T.StructField("src", _L, False), T.StructField("dst", _L, False), T.StructField("w", _L, False), T.StructField("born_batch", _I)])
CHANGES = T.StructType([T.StructField("batch_id", _I), T.StructField("op", _S), T.StructField("node_id", _L), T.StructField("truth", T.ByteType()), T.StructField("event_time", T.TimestampType())])


def schema_of(name: str) -> T.StructType:
    return T.StructType([T.StructField(c, t) for c, t in SCHEMAS[name]])


def read(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    """A given table by its declared schema; the scan is pruned to what a query uses."""
    return spark.read.schema(schema_of(name)).parquet(f"{sf_dir}/{name}.parquet")


def require_keys(df: DataFrame, *keys: str) -> DataFrame:
    """Fails on a null key instead of dropping the row."""
    out = df
    for k in keys:
        out = out.withColumn(k, F.coalesce(F.col(k), F.raise_error(F.lit(f"null key {k}")).cast(df.schema[k].dataType)))
    return out


def scan_nodes(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    """Vertices (node_id, truth) of a table: language English for documents, status for orders, the sign of the first coordinate
    for embeddings, the language in the address for pages."""
    df = read(spark, sf_dir, name)
    byte = T.ByteType()
    if name == "documents":
        truth = F.when(F.col("lang") == "en", 1).when(F.col("lang").isNotNull(), 0).cast(byte)
    elif name == "orders":
        truth = F.when(F.col("o_orderstatus") == "F", 0).when(F.col("o_orderstatus") == "O", 1).cast(byte)
    elif name == "embeddings":
        truth = F.when(F.col("embedding")[0] >= 0, 1).otherwise(0).cast(byte)
    elif name == "pages":
        truth = F.when(F.col("url").contains("/en/"), 1).otherwise(0).cast(byte)
    else:
        raise ValueError(f"no vertices are declared for {name}")
    return require_keys(df.select(F.col(df.columns[0]).alias("node_id"), truth.alias("truth")), "node_id")
