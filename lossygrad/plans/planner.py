"""Choices that depend on sizes: layout, codec, exchange, parameters, depth of sums."""

from __future__ import annotations

import math
from dataclasses import dataclass

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from lossygrad.functions import bounds
from lossygrad.optim.channel import Channel
from lossygrad.optim.sgd import DRIVER_PARAMETERS

#: Values of a vector above which it isn't kept in one row.
ROW_VALUES = 100_000
#: Bytes a broadcast side may have.
BROADCAST_BYTES = 64 << 20
#: Messages that one task sums for a bucket before the sum is split in two levels.
FLAT_WORKERS = 1_000


@dataclass(frozen=True)
class Plan:
    layout: str  # array or bucket
    parameters: str  # driver or table
    channel: Channel
    salts: int  # partial sums of a bucket; 1: none
    bits_per_round: float


def plan(n: int, k: int, bits: int = 4, bucket: int = 512, s: int | str | None = None) -> Plan:
    """For n values and k workers.  A bucket of one value is full precision: its scale alone takes 32 bits."""
    if n < 1 or k < 1 or bucket < 1:
        raise ValueError("sizes must be at least 1")
    if bucket == 1 or bits == 32:
        channel, cost = Channel(), 32.0 * n
    elif s is not None:
        levels = math.isqrt(n) if s == "sqrt" else int(s)
        dense = levels * levels >= n / 4
        channel = Channel("dense_prefix" if dense else "gap", s=s, norm="l2")
        cost = bounds.dense_bits(n) if dense else bounds.gap_bits(n, levels)
    else:
        channel, cost = Channel("fixed", bits, bucket), bounds.fixed_bits(bits, min(bucket, n)) * n
    salts = 1 if k <= FLAT_WORKERS else math.isqrt(k)
    return Plan("array" if n <= ROW_VALUES else "bucket", "driver" if n <= DRIVER_PARAMETERS else "table", channel, salts, cost)


def small_enough(rows: int, row_bytes: int, limit: int = BROADCAST_BYTES) -> bool:
    return rows * row_bytes <= limit


def join_by_size(left: DataFrame, right: DataFrame, on: list[str], row_bytes: int, how: str = "inner") -> DataFrame:
    """Broadcasts ``right`` only if its counted size fits; otherwise a shuffled join."""
    return left.join(F.broadcast(right) if small_enough(right.count(), row_bytes) else right, on, how)


def two_level_sum(cells: DataFrame, keys: list[str], value: str, worker: str, salts: int) -> DataFrame:
    """Sum by keys through partial sums of ``salts`` groups of workers, for hot buckets."""
    if salts <= 1:
        return cells.groupBy(*keys).agg(F.sum(value).alias(value))
    salted = cells.withColumn("salt_", F.col(worker) % salts).groupBy(*keys, "salt_").agg(F.sum(value).alias(value))
    return salted.groupBy(*keys).agg(F.sum(value).alias(value))


def step_table(parameters: DataFrame, sums: DataFrame, eta: float, workers: int) -> DataFrame:
    """Parameters as a table (bucket_id, values) stepped by summed messages (bucket_id, total): a co-partitioned join."""
    joined = parameters.join(sums.select("bucket_id", "total"), "bucket_id", "left")
    moved = F.zip_with("values", "total", lambda x, g: x - F.lit(eta / workers) * g)
    return joined.select("bucket_id", F.when(F.col("total").isNull(), F.col("values")).otherwise(moved).alias("values"))
