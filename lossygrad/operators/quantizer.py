"""Quantizers over DataFrames, in each layout."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from lossygrad.functions import arrays as A
from lossygrad.functions import quantization as Q
from lossygrad.functions.uniform import uniform


def _levels(s: int | str, n: Column) -> Column:
    if s == "sqrt":
        return F.greatest(F.floor(F.sqrt(n)), F.lit(1)).cast("int")
    if not isinstance(s, int) or isinstance(s, bool) or s < 1:
        raise ValueError("levels must be a whole number of at least 1, or 'sqrt'")
    return F.lit(s)


def quantize(df: DataFrame, s: int | str, norm: str = "l2", seed: int = 0, step: int = 0, rounding: str = "random", bucket: int | None = None) -> DataFrame:
    """Array or bucket layout (``vec_id``, maybe ``bucket_id``, ``values``) plus s, scale, sign and level.

    No shuffle.  ``bucket`` is the bucket size d, which gives each value its coordinate
    in the whole vector and so its own draw.
    """
    first = (F.col("bucket_id") * bucket) if bucket and "bucket_id" in df.columns else F.lit(0)
    scaled = df.withColumn("s", _levels(s, F.size("values"))).withColumn("scale", Q.scale_of(F.col("values"), norm))
    marked = scaled.withColumn("q_", Q.quantize_array(F.col("values"), F.col("scale"), F.col("s"), F.lit(seed), F.lit(step), F.col("vec_id"), first=first, rounding=rounding))
    return marked.select(
        *scaled.columns, F.transform("q_", lambda q: q["sign"]).alias("sign"), F.transform("q_", lambda q: q["level"]).alias("level")
    )


def dequantize(df: DataFrame) -> DataFrame:
    """The decoded ``values`` instead of sign and level."""
    rest = [c for c in df.columns if c not in ("values", "sign", "level")]
    return df.select(*rest, Q.dequantize_array(F.col("scale"), F.col("sign"), F.col("level"), F.col("s")).alias("values"))


def long_scales(long: DataFrame, norm: str = "l2", decimals: int | None = None) -> DataFrame:
    """vec_id and float32 ``scale`` of long vectors, by a partial and a final aggregate.

    With ``decimals``, values are whole multiples of 10**-decimals and the squares are
    summed exactly, so the scale doesn't depend on the order of rows.
    """
    if norm == "max":
        total = F.max(F.abs("value"))
    elif decimals is None:
        total = F.sqrt(F.sum(F.col("value") * F.col("value")))
    else:
        unit = F.round(F.col("value") * 10**decimals).cast("decimal(18,0)")
        total = F.sqrt(F.sum(unit * unit).cast("double")) / 10**decimals
    return long.groupBy("vec_id").agg(Q.scale32(total).alias("scale"))


def quantize_long(long: DataFrame, s: int, norm: str = "l2", seed: int = 0, step: int = 0, decimals: int | None = None) -> DataFrame:
    """Long layout plus scale, sign and level.  The scales (a row a vector) join back by vec_id."""
    if s < 1:
        raise ValueError("levels must be a whole number of at least 1")
    joined = long.join(long_scales(long, norm, decimals), "vec_id")
    pos = Q.position(F.col("value"), F.col("scale"), s)
    return joined.select(
        "vec_id", "coord", "value", "scale",
        A.sign_of(F.col("value")).cast("int").alias("sign"),
        Q.level(pos, s, uniform(F.lit(seed), F.lit(step), F.col("vec_id"), F.col("coord"))).alias("level"),
    )


def quantize_by_intervals(long: DataFrame, s: int, norm: str = "l2", seed: int = 0, step: int = 0, decimals: int | None = None) -> DataFrame:
    """The same levels found by a range join of positions with the s intervals, as a cross-check."""
    spark = long.sparkSession
    intervals = spark.range(s).select(F.col("id").cast("int").alias("low"), (F.col("id") == s - 1).alias("last"))
    scaled = long.join(long_scales(long, norm, decimals), "vec_id").withColumn("pos", Q.position(F.col("value"), F.col("scale"), s))
    inside = (F.col("pos") >= F.col("low")) & ((F.col("pos") < F.col("low") + 1) | F.col("last"))
    met = scaled.join(F.broadcast(intervals), inside)
    up = uniform(F.lit(seed), F.lit(step), F.col("vec_id"), F.col("coord")) < F.col("pos") - F.col("low")
    return met.select(
        "vec_id", "coord", "value", "scale", A.sign_of(F.col("value")).cast("int").alias("sign"), (F.col("low") + F.when(up, 1).otherwise(0)).cast("int").alias("level")
    )


def gaps(quantized_long: DataFrame) -> DataFrame:
    """Distance of each nonzero level from the one before it (the first: its place from 1)."""
    order = Window.partitionBy("vec_id").orderBy("coord")
    return quantized_long.where("level > 0").withColumn("gap", F.col("coord") - F.coalesce(F.lag("coord").over(order), F.lit(-1)))


def average(decoded: DataFrame, by: list[str]) -> DataFrame:
    """Mean of decoded arrays, coordinate by coordinate; partial sums are combined before the shuffle."""
    cells = decoded.select(*by, F.posexplode_outer("values").alias("coord", "value")).where("coord is not null")  # as in layout.to_long
    return cells.groupBy(*by, "coord").agg(F.avg("value").alias("value"), F.count("*").alias("n_messages"))
