"""Parallel descent whose parameters are a table, for models beyond what the driver may hold.

Least squares over sparse rows (``entries``: row_id, coord, value; ``targets``: row_id, shard, y).
Nothing of the model's size is collected or broadcast.  A round is DataFrame work only:

1. entries meet the parameters of their coordinate; a row's products add up to its residual;
2. entries meet their row's residual; a worker's products add up to its mean gradient, by bucket;
3. a worker's buckets are quantized and encoded, payloads cross one exchange to the bucket's owner,
   which decodes and adds them (in two levels for many workers);
4. the parameter table is stepped by a join on the bucket.

Entries and targets are dealt by row once; every round reads that exchange.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from lossygrad.functions import quantization as Q
from lossygrad.operators import messages, quantizer
from lossygrad.plans import planner


def zeros(spark: SparkSession, n: int, bucket: int) -> DataFrame:
    """A parameter table (bucket_id, values) of n zeros."""
    ids = spark.range(-(-n // bucket)).select(F.col("id").alias("bucket_id"))
    return ids.select("bucket_id", F.array_repeat(F.lit(0.0), F.least(F.lit(bucket), n - F.col("bucket_id") * bucket).cast("int")).alias("values"))


def gradients(entries: DataFrame, targets: DataFrame, x: DataFrame, n: int, bucket: int, digits: int | None = None) -> DataFrame:
    """vec_id (the worker), bucket_id and dense ``values`` of each worker's mean gradient."""
    at = F.col("bucket_id") * bucket + F.col("at")
    parameters = x.select("bucket_id", F.posexplode_outer("values").alias("at", "x")).select(at.cast("bigint").alias("coord"), "x")
    scores = entries.join(parameters, "coord").groupBy("row_id").agg(F.sum(F.col("value") * F.col("x")).alias("score"))
    residuals = targets.join(scores, "row_id", "left").select("row_id", "shard", (F.coalesce("score", F.lit(0.0)) - F.col("y")).alias("e"))
    rows = targets.groupBy("shard").agg(F.count("*").alias("rows"))  # a row a worker
    sums = entries.join(residuals, "row_id").groupBy("shard", "coord").agg(F.sum(F.col("value") * F.col("e")).alias("g"))
    mean = sums.join(F.broadcast(rows), "shard").select("shard", "coord", (F.col("g") / F.col("rows")).alias("g"))
    if digits is not None:
        mean = mean.withColumn("g", F.round("g", digits))
    cells = mean.groupBy("shard", F.floor(F.col("coord") / bucket).alias("bucket_id")).agg(F.map_from_entries(F.collect_list(F.struct((F.col("coord") % bucket).alias("at"), F.col("g")))).alias("cells"))
    size = F.least(F.lit(bucket), n - F.col("bucket_id") * bucket)
    dense = F.transform(F.sequence(F.lit(0).cast("bigint"), size - 1), lambda i: F.coalesce(F.try_element_at("cells", i), F.lit(0.0)))
    return cells.select(F.col("shard").cast("bigint").alias("vec_id"), "bucket_id", dense.alias("values"))


def train_table(entries: DataFrame, targets: DataFrame, n: int, k: int, rounds: int, eta: float, s: int | None = None, norm: str = "l2", codec: str = "gap", bucket: int = 512,
                seed: int = 0, digits: int | None = None, cut: bool = False) -> DataFrame:
    """The parameter table after ``rounds`` rounds of k workers; ``s`` None sends full precision.

    ``cut`` checkpoints the (small beside the data) parameter table every round, for long runs.
    """
    if n < 1 or bucket < 1:
        raise ValueError("sizes must be at least 1")
    entries, targets = entries.repartition("row_id"), targets.repartition("row_id")
    x = zeros(entries.sparkSession, n, bucket)
    for t in range(rounds):
        grads = gradients(entries, targets, x, n, bucket, digits)
        if s is None:
            sent = grads.select(F.col("vec_id").cast("int").alias("shard"), "bucket_id", "values")
        else:
            made = quantizer.quantize(grads, s, norm, seed, t, bucket=bucket)
            received = messages.decode(messages.by_bucket(messages.encode(made, codec, 4, t)))
            sent = received.select("shard", "bucket_id", Q.dequantize_array(F.col("scale"), F.col("sign"), F.col("level"), s).alias("values"))
        cells = sent.select("shard", "bucket_id", F.posexplode_outer("values").alias("at", "g"))
        summed = planner.two_level_sum(cells, ["bucket_id", "at"], "g", "shard", planner.plan(n, k).salts)
        total = summed.groupBy("bucket_id").agg(F.transform(F.array_sort(F.collect_list(F.struct("at", "g"))), lambda c: c["g"]).alias("total"))
        x = planner.step_table(x, total, eta, k)
        if digits is not None:
            x = x.select("bucket_id", F.transform("values", lambda v: F.round(v, digits)).alias("values"))
        x = x.checkpoint() if cut else x
    return x
