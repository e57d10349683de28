"""Readers and writers: tables with declared schemas, vectors of other tools, messages."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

# Schemas of the tables.
SCHEMAS = {
    "region": "r_regionkey int, r_name string",
    "nation": "n_nationkey int, n_name string, n_regionkey int",
    "customer": "c_custkey bigint, c_name string, c_nationkey int, c_acctbal double, c_mktsegment string",
    "supplier": "s_suppkey bigint, s_name string, s_nationkey int, s_acctbal double",
    "part": "p_partkey bigint, p_name string, p_brand string, p_type string, p_size int, p_retailprice double",
    "orders": "o_orderkey bigint, o_custkey bigint, o_orderstatus string, o_totalprice double, o_orderdate timestamp_ntz, o_orderpriority string",
    "lineitem": "l_orderkey bigint, l_partkey bigint, l_suppkey bigint, l_linenumber int, l_quantity double, l_extendedprice double, l_discount double, l_tax double, l_returnflag string, l_linestatus string, l_shipdate timestamp_ntz",
    "events": "event_id bigint, ts timestamp_ntz, user_id bigint, event_type string, value double, props string",
    "documents": "doc_id bigint, text string, lang string, source string, n_chars bigint",
    "embeddings": "vec_id bigint, embedding array<float>, label int",
    "labels": "doc_id bigint, quality int, toxic int",
}
MESSAGES = "round int, shard int, bucket_id bigint, codec string, scale float, n int, nnz int, n_bits bigint, payload binary"


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    reader = spark.read
    return (reader.schema(SCHEMAS[name]) if name in SCHEMAS else reader).parquet(f"{sf_dir}/{name}.parquet")


def vectors(spark: SparkSession, path: str, fmt: str = "parquet", schema: str = "vec_id bigint, values array<double>", **options: str) -> DataFrame:
    """Vectors written by another tool: parquet, orc, json, or csv in long layout."""
    return spark.read.format(fmt).schema(schema).options(**options).load(path)


def write_messages(messages: DataFrame, path: str) -> None:
    """Partitioned by round; a round that is written again replaces itself."""
    messages.sortWithinPartitions("bucket_id", "shard").write.mode("overwrite").option("partitionOverwriteMode", "dynamic").partitionBy("round").parquet(path)


def read_messages(spark: SparkSession, path: str, round_: int | None = None) -> DataFrame:
    df = spark.read.schema(MESSAGES).parquet(path)
    return df if round_ is None else df.where(F.col("round") == round_)


def append_ledger(ledger: DataFrame, path: str) -> None:
    ledger.write.mode("append").parquet(path)


def discard(df: DataFrame) -> None:
    """Runs a plan and keeps nothing, for timing."""
    df.write.format("noop").mode("overwrite").save()


def embeddings(spark: SparkSession, sf_dir: str) -> DataFrame:
    """vec_id, values (array of doubles), label."""
    return table(spark, sf_dir, "embeddings").select("vec_id", F.col("embedding").cast("array<double>").alias("values"), "label")
