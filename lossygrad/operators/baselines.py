"""Baselines: full and reduced precision, one bit with carried error, truncation, exact means."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from lossygrad.functions import arrays as A


def float32(df: DataFrame) -> DataFrame:
    """Values as 32-bit floats and their bits."""
    return df.withColumn("values", F.transform("values", lambda x: x.cast("float").cast("double"))).withColumn("n_bits", F.size("values").cast("bigint") * 32)


def onebit_values(w: Column, scale: str = "mean_abs") -> Column:
    """Decoded one-bit message of an array."""
    if scale == "mean_abs":
        return A.let(
            (A.norm1(w) / F.size(w)).cast("float").cast("double"), lambda m: F.transform(w, lambda x: F.when(x < 0, -m).otherwise(m))
        )
    if scale == "two_means":
        low, high = F.filter(w, lambda x: x < 0), F.filter(w, lambda x: x >= 0)
        mean = lambda part: F.when(F.size(part) == 0, 0.0).otherwise(A.fold_sum(part) / F.size(part)).cast("float").cast("double")
        return A.let(F.struct(mean(low).alias("low"), mean(high).alias("high")), lambda m: F.transform(w, lambda x: F.when(x < 0, m["low"]).otherwise(m["high"])))
    raise ValueError(f"unknown scale {scale}")


def onebit(df: DataFrame, state: DataFrame | None = None, scale: str = "mean_abs", carry: bool = True) -> DataFrame:
    """Decoded one-bit messages with the error to carry: columns values, carried and n_bits.

    ``state`` holds the last step's carried arrays by the key columns (vec_id, bucket_id
    or shard), and joins on them; without it, or without ``carry``, errors start at zero.
    """
    keys = [c for c in ("shard", "vec_id", "bucket_id") if c in df.columns]
    if state is not None and carry:
        old = state.select(*keys, F.col("carried").alias("old_"))
        df = df.join(old, keys, "left").withColumn("w_", F.when(F.col("old_").isNull(), F.col("values")).otherwise(F.zip_with("values", "old_", lambda g, e: g + e))).drop("old_")
    else:
        df = df.withColumn("w_", F.col("values"))
    sent = df.withColumn("sent_", onebit_values(F.col("w_"), scale))
    rest = [c for c in df.columns if c not in ("values", "w_", "carried", "n_bits")]
    extra = 32 if scale == "mean_abs" else 64
    return sent.select(
        *rest,
        F.col("sent_").alias("values"),
        F.zip_with("w_", "sent_", lambda w, q: w - q).alias("carried"),
        (F.size("w_") + extra).cast("bigint").alias("n_bits"),
    )


def bfloat16(x: Column) -> Column:
    """x truncated to the 8 leading significand bits of a bfloat16, for normal values."""
    size = F.floor(F.log2(F.abs(x)))
    unit = F.pow(F.lit(2.0), size - 7)
    return F.when(x == 0, 0.0).otherwise(F.signum(x) * F.floor(F.abs(x) / unit) * unit)


def reduced(df: DataFrame, kind: str = "bfloat16", bits: int = 8) -> DataFrame:
    """Plain reduced precision: bfloat16, or fixed point of ``bits`` below the largest magnitude."""
    if kind == "bfloat16":
        values, each = F.transform("values", bfloat16), 16
    elif kind == "fixed":
        n = 2 ** (bits - 1) - 1
        top = A.norm_max(F.col("values"))
        values = A.let(top, lambda t: F.transform("values", lambda x: F.when(t == 0, 0.0).otherwise(A.sign_of(x) * F.floor(F.abs(x) / t * n + 0.5) / n * t)))
        each = bits
    else:
        raise ValueError(f"unknown kind {kind}")
    return df.withColumn("values", values).withColumn("n_bits", F.size("values").cast("bigint") * each)


def topk(df: DataFrame, k: int | None = None, frac: float | None = None) -> DataFrame:
    """Array layout with only the k largest magnitudes left (ties by place); others are zero."""
    count = F.lit(k) if k is not None else F.ceil(F.size("values") * F.lit(frac)).cast("int")
    ranked = F.array_sort(F.transform("values", lambda x, i: F.struct((-F.abs(x)).alias("m"), i.alias("i"))))
    kept = F.transform(F.slice(ranked, F.lit(1), count), lambda e: e["i"])
    return df.withColumn("kept_", kept).withColumn("values", F.transform("values", lambda x, i: F.when(F.array_contains("kept_", i), x).otherwise(0.0))).drop("kept_")


def topk_cover(long: DataFrame) -> DataFrame:
    """Long layout: the shortest prefix by magnitude whose absolute sum reaches the 2-norm,
    each kept value replaced by the norm with its sign."""
    order = Window.partitionBy("vec_id").orderBy(F.abs("value").desc(), "coord")
    whole = Window.partitionBy("vec_id")
    run = long.withColumn("norm", F.sqrt(F.sum(F.col("value") * F.col("value")).over(whole))).withColumn(
        "before", F.coalesce(F.sum(F.abs("value")).over(order.rowsBetween(Window.unboundedPreceding, -1)), F.lit(0.0))
    )
    return run.where((F.col("before") < F.col("norm") * (1 - 1e-12)) & (F.col("norm") > 0)).select("vec_id", "coord", (A.sign_of(F.col("value")) * F.col("norm")).alias("value"))


def topk_threshold(long: DataFrame, frac: float, accuracy: int = 10_000) -> DataFrame:
    """At scale: values at or above an approximate quantile of magnitudes, without a sort of the vector."""
    cut = long.groupBy("vec_id").agg(F.percentile_approx(F.abs("value"), 1 - frac, accuracy).alias("cut"))
    return long.join(cut, "vec_id").where(F.abs("value") >= F.col("cut")).select("vec_id", "coord", "value")


def mean_exact(df: DataFrame, group: str) -> DataFrame:
    """Exact mean vector of each group, long."""
    return df.select(group, F.posexplode_outer("values").alias("coord", "value")).where("coord is not null").groupBy(group, "coord").agg(F.avg("value").alias("value"))
