"""Layers of a model and the policy of what is quantized and how finely."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

LAYERS = "layer_id int, name string, kind string, rows int, cols int, n bigint"
#: Tensors with fewer values are sent at full precision.
MIN_ELEMENTS = 10_000


def layers(spark: SparkSession, specs: list[tuple[str, str, int, int]]) -> DataFrame:
    """From (name, kind, rows, cols)."""
    return spark.createDataFrame([(i, name, kind, r, c, r * c) for i, (name, kind, r, c) in enumerate(specs)], LAYERS)


def policy(layers_df: DataFrame, bits: int = 4, bucket: int = 512, min_elements: int = MIN_ELEMENTS, bits_by_kind: dict[str, int] | None = None) -> DataFrame:
    """Adds bits (32: not quantized), bucket (whole rows where a row fits), and message bits."""
    chosen = F.lit(bits)
    for kind, b in (bits_by_kind or {}).items():
        chosen = F.when(F.col("kind") == kind, F.lit(b)).otherwise(chosen)
    out = layers_df.withColumn("bits", F.when(F.col("n") < min_elements, 32).otherwise(chosen))
    aligned = F.when(F.col("cols") <= bucket, F.floor(F.lit(bucket) / F.col("cols")).cast("int") * F.col("cols")).otherwise(F.col("cols"))
    out = out.withColumn("bucket", F.when(F.col("bits") == 32, F.lit(None)).otherwise(aligned).cast("int"))
    sent = F.when(F.col("bits") == 32, F.col("n") * 32).otherwise(F.col("n") * F.col("bits") + 32 * F.ceil(F.col("n") / F.col("bucket")))
    return out.withColumn("n_bits", sent.cast("bigint"))


def report(policy_df: DataFrame) -> DataFrame:
    """Share of quantized parameters and the ratio to full precision."""
    return policy_df.agg(
        F.sum("n").alias("n_params"),
        F.sum(F.when(F.col("bits") < 32, F.col("n")).otherwise(0)).alias("n_quantized"),
        (F.sum(F.when(F.col("bits") < 32, F.col("n")).otherwise(0)) / F.sum("n")).alias("share_quantized"),
        (F.sum("n") * 32 / F.sum("n_bits")).alias("ratio"),
    )
