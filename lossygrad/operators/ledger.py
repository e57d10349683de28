"""Measures: bits, variance, sparsity, curves, accuracy, time."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from lossygrad.functions import quantization as Q


def bits(messages: DataFrame, by: list[str]) -> DataFrame:
    """Sums of message rows: bits, values, nonzeros; bits a value and the ratio to 32."""
    return messages.groupBy(*by).agg(
        F.sum("n_bits").alias("n_bits"), F.sum("n").cast("bigint").alias("n"), F.sum("nnz").cast("bigint").alias("nnz"),
        (F.sum("n_bits") / F.sum("n")).alias("bits_per_coord"), (F.sum("n") * 32 / F.sum("n_bits")).alias("ratio"),
    )


def fanout(n_bits: Column, k: int) -> Column:
    """All-to-all traffic: every message goes to the k - 1 others."""
    return n_bits * (k - 1)


def variance_report(quantized: DataFrame) -> DataFrame:
    """Per vector: squared norm, closed-form variance and nonzeros, and their bounds."""
    n, s = F.size("values").cast("double"), F.col("s").cast("double")
    square = F.aggregate("values", F.lit(0.0), lambda acc, x: acc + x * x)
    return quantized.select(
        "vec_id", F.size("values").alias("n"), "s", square.alias("square"),
        Q.exact_variance(F.col("values"), F.col("scale"), F.col("s")).alias("variance"),
        (F.least(n / (s * s), F.sqrt(n) / s) * square).alias("variance_bound"),
        Q.exact_nonzeros(F.col("values"), F.col("scale"), F.col("s")).alias("nonzeros"),
        (s * (s + F.sqrt(n))).alias("nonzeros_bound"),
    )


def density(quantized: DataFrame) -> DataFrame:
    return quantized.select("vec_id", (F.size(F.filter("level", lambda k: k > 0)) / F.size("level")).alias("density"))


def level_entropy(quantized: DataFrame) -> DataFrame:
    """Bits a value that any memoryless code of levels needs at least."""
    counts = quantized.select(F.explode_outer("level").alias("level")).where("level is not null").groupBy("level").count()
    total = counts.agg(F.sum("count").alias("total"))
    shared = counts.crossJoin(F.broadcast(total)).withColumn("p", F.col("count") / F.col("total"))
    return shared.agg(F.sum(-F.col("p") * F.log2("p")).alias("entropy"), F.count("*").alias("n_levels"))


def rounds_to(curve: DataFrame, target: float, by: list[str]) -> DataFrame:
    """First round at or under the target loss; null where none is."""
    return curve.groupBy(*by).agg(F.min(F.when(F.col("loss") <= target, F.col("round"))).alias("rounds"))


def contraction(curve: DataFrame, by: list[str]) -> DataFrame:
    """Gap ratio of successive epochs, and the rate of a geometric fit."""
    order = Window.partitionBy(*by).orderBy("epoch")
    ratios = curve.withColumn("ratio", F.col("gap") / F.lag("gap").over(order))
    return ratios.groupBy(*by).agg(F.max("ratio").alias("worst"), F.exp(F.regr_slope(F.log("gap"), F.col("epoch"))).alias("rate"))


def accuracy_curve(curve: DataFrame, by: list[str]) -> DataFrame:
    """Cumulative time against accuracy."""
    order = Window.partitionBy(*by).orderBy("round").rowsBetween(Window.unboundedPreceding, 0)
    return curve.withColumn("time_s", F.sum("wall_s").over(order))


def topk_accuracy(predicted: DataFrame, k: int) -> DataFrame:
    """Share of rows whose label ``y`` is among the first k of ``ranked``."""
    place = F.array_position("ranked", F.col("y"))
    return predicted.agg(F.avg(((place > 0) & (place <= k)).cast("double")).alias(f"top{k}"))


def speedup(times: DataFrame, base_codec: str = "float32") -> DataFrame:
    """Epoch time of the base codec over each codec's, and the share of communication."""
    base = times.where(F.col("codec") == base_codec).select("workload", "k", F.col("epoch_s").alias("base_s"))
    return times.join(base, ["workload", "k"]).withColumn("speedup", F.col("base_s") / F.col("epoch_s")).withColumn("comm_share", F.col("comm_s") / (F.col("comm_s") + F.col("comp_s")))


def time_spread(times: DataFrame, by: list[str]) -> DataFrame:
    """Coefficient of variation of epoch times."""
    return times.groupBy(*by).agg(F.avg("wall_s").alias("mean_s"), (F.stddev_samp("wall_s") / F.avg("wall_s")).alias("spread"))


def accuracy_gap(accuracies: DataFrame, base_run: str = "fp32") -> DataFrame:
    """Accuracy of each run less that of the full-precision run of its workload."""
    base = accuracies.where(F.col("run") == base_run).select("workload", F.col("top1").alias("base_top1"))
    return accuracies.join(base, "workload").withColumn("gap", F.col("top1") - F.col("base_top1"))


def _stages(spark: SparkSession) -> list:
    jvm, gateway = spark._jvm, spark.sparkContext._gateway
    spark.sparkContext._jsc.sc().listenerBus().waitUntilEmpty()
    none = jvm.java.util.ArrayList()
    found = spark.sparkContext._jsc.sc().statusStore().stageList(none, False, False, gateway.new_array(jvm.double, 0), none)
    return [found.apply(i) for i in range(found.size())]


def shuffle_bytes_of(spark: SparkSession, action: Callable[[], object]) -> tuple[object, int]:
    """What ``action`` returns, and the bytes that its stages wrote to shuffles, by Spark's own count.

    Spark keeps the newest stages only (``spark.ui.retainedStages``), so an action is measured as soon as it ends.
    """
    last = max((s.stageId() for s in _stages(spark)), default=-1)
    result = action()
    return result, sum(s.shuffleWriteBytes() for s in _stages(spark) if s.stageId() > last)
