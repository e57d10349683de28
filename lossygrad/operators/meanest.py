"""Distributed mean estimation: the mean of many vectors from their lossy messages."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from lossygrad.functions import codes
from lossygrad.operators import baselines, quantizer


def estimate(df: DataFrame, group: str, s: int | str, norm: str = "l2", seed: int = 0) -> DataFrame:
    """group, coord, value (estimated mean) and n_messages."""
    decoded = quantizer.dequantize(quantizer.quantize(df, s, norm, seed))
    return quantizer.average(decoded, [group])


def frontier(df: DataFrame, group: str, levels: list[int], norm: str = "l2", seed: int = 0) -> DataFrame:
    """For each s: mean squared error over groups, bits of the sparse code, and the bound on the error.

    The bound of a group of K messages is min(n / s^2, sqrt(n) / s) times their squared norms over K^2.
    """
    exact = baselines.mean_exact(df, group).withColumnRenamed("value", "exact")
    out = None
    for s in levels:
        quantized = quantizer.quantize(df, s, norm, seed)
        error = quantizer.average(quantizer.dequantize(quantized), [group]).join(exact, [group, "coord"]).groupBy(group).agg(F.sum((F.col("value") - F.col("exact")) ** 2).alias("mse"))
        n = F.size("values").cast("double")
        cost = quantized.groupBy(group).agg(
            F.sum(codes.gap_bits(F.col("level"))).alias("n_bits"),
            (F.sum(F.least(n / (s * s), F.sqrt(n) / s) * F.aggregate("values", F.lit(0.0), lambda a, x: a + x * x)) / F.count("*") ** 2).alias("bound"),
        )
        row = error.join(cost, group).agg(F.avg("mse").alias("mse"), F.avg("bound").alias("bound"), F.sum("n_bits").alias("n_bits")).withColumn("s", F.lit(s))
        out = row if out is None else out.unionByName(row)
    return out
