"""Layouts of vectors: arrays, long rows, and buckets (the unit of parallelism)."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from lossygrad.functions.arrays import bad_values


def checked(df: DataFrame) -> DataFrame:
    """The same rows; a null, NaN or infinite value fails the query when it is read."""
    message = F.concat(F.lit("vector with a null, NaN or infinite value: "), F.coalesce(F.col("vec_id").cast("string"), F.lit("null")))
    return df.withColumn("values", F.when(bad_values(F.col("values")), F.raise_error(message).cast("array<double>")).otherwise(F.col("values")))


def to_long(df: DataFrame) -> DataFrame:
    """vec_id, coord (from 0), value.

    Explodes with ``outer`` and filters afterwards: for a plain explode the optimizer adds a
    filter on the array's size and copies the whole computation of the array into it.
    """
    rows = df.select("vec_id", F.posexplode_outer("values").alias("coord", "value")).where("coord is not null")
    return rows.withColumn("coord", F.col("coord").cast("bigint"))


def to_array(long: DataFrame) -> DataFrame:
    """One array a vector, in coordinate order; for vectors that fit a row."""
    pairs = F.array_sort(F.collect_list(F.struct("coord", "value")))
    return long.groupBy("vec_id").agg(F.transform(pairs, lambda p: p["value"]).alias("values"))


def bucketize(df: DataFrame, d: int) -> DataFrame:
    """Buckets of d consecutive values from array layout, without a shuffle; the last may be short."""
    if d < 1:
        raise ValueError("bucket size must be at least 1")
    starts = F.when(F.size("values") > 0, F.sequence(F.lit(0), F.floor((F.size("values") - 1) / d).cast("int"))).otherwise(F.array().cast("array<int>"))
    rest = [c for c in df.columns if c not in ("vec_id", "values")]
    exploded = df.select("vec_id", *rest, F.col("values").alias("all_"), F.explode(starts).alias("bucket"))
    return exploded.select("vec_id", *rest, F.col("bucket").cast("bigint").alias("bucket_id"), F.slice("all_", F.col("bucket") * d + 1, d).alias("values"))


def bucketize_long(long: DataFrame, d: int) -> DataFrame:
    """Buckets from long layout: one shuffle, by vector and bucket, and no task holds more than its buckets."""
    if d < 1:
        raise ValueError("bucket size must be at least 1")
    keyed = long.withColumn("bucket_id", F.floor(F.col("coord") / d).cast("bigint"))
    pairs = F.array_sort(F.collect_list(F.struct("coord", "value")))
    return keyed.groupBy("vec_id", "bucket_id").agg(F.transform(pairs, lambda p: p["value"]).alias("values"))


def row_aligned(d: int, width: int) -> int:
    """Bucket size that never splits a row of ``width`` values: whole rows, as many as fit d (at least one)."""
    if width < 1:
        raise ValueError("row width must be at least 1")
    return max(1, d // width) * width


def shard_of(key: Column, k: int) -> Column:
    """Worker of a row by hash of its key."""
    return F.pmod(F.xxhash64(key), F.lit(k)).cast("int")


def shard_ranges(index: Column, m: Column | int, k: int) -> Column:
    """Worker of row ``index`` (from 0) of m in contiguous ranges."""
    return F.least(F.floor(index * k / m), F.lit(k - 1)).cast("int")


def dense_index(df: DataFrame, name: str = "row_id") -> DataFrame:
    """Rows numbered 0, 1, ... without a sort: numbers inside partitions plus counts of the partitions before.

    ``df`` has to come back in the same partitions: persist it or read it from files.
    Only one count a partition goes to the driver.
    """
    marked = df.withColumn("at_", F.monotonically_increasing_id())
    part = F.shiftright("at_", 33)
    counts = {r["part"]: r["n"] for r in marked.groupBy(part.alias("part")).agg(F.count("*").alias("n")).collect()}
    before, rows = 0, []
    for p in sorted(counts):
        rows.append((p, before))
        before += counts[p]
    offsets = df.sparkSession.createDataFrame(rows, "part_ bigint, before_ bigint")
    joined = marked.withColumn("part_", part).join(F.broadcast(offsets), "part_")
    return joined.withColumn(name, F.col("before_") + F.col("at_").bitwiseAND(F.lit((1 << 33) - 1))).drop("at_", "part_", "before_")
