"""Streaming forms: rounds from event time, and one-bit messages with carried error as state."""

from __future__ import annotations

import tempfile
from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

from lossygrad.operators import kernels
from lossygrad.session import ship_package
from lossygrad.sources import SCHEMAS

_RUNS = [0]


def event_stream(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The events table as a stream of files; ``ts`` becomes a timestamp, as watermarks need."""
    return (
        spark.readStream.schema(SCHEMAS["events"]).option("pathGlobFilter", "events.parquet").option("recursiveFileLookup", "true").parquet(sf_dir)
        .withColumn("ts", F.col("ts").cast("timestamp"))
    )


def _place(spark: SparkSession) -> str:
    """A new folder for one stream, shared between driver and executors."""
    _RUNS[0] += 1
    named = spark.sparkContext.getConf().get("spark.checkpoint.dir")
    if not named and not spark.sparkContext.master.startswith("local"):
        raise ValueError("set spark.checkpoint.dir to a folder that driver and executors share")
    return f"{named.rstrip('/')}/stream-{spark.sparkContext.applicationId}-{_RUNS[0]}" if named else tempfile.mkdtemp(prefix="lossygrad-stream-")


def drain(stream: DataFrame, mode: str = "complete") -> DataFrame:
    """Runs a stream over what there is and returns its result table, which the driver holds: for small results."""
    spark = stream.sparkSession
    place = _place(spark)
    name = f"drained_{_RUNS[0]}"
    q = stream.writeStream.outputMode(mode).format("memory").queryName(name).option("checkpointLocation", place).trigger(availableNow=True).start()
    q.awaitTermination()
    return spark.table(name)


def drain_to_files(stream: DataFrame) -> DataFrame:
    """As ``drain`` in append mode, for results that grow with the stream: executors write them to files, and
    state lies in RocksDB, beside the heap."""
    spark = stream.sparkSession
    place = _place(spark)
    key = "spark.sql.streaming.stateStore.providerClass"
    before = spark.conf.get(key, None)
    spark.conf.set(key, "org.apache.spark.sql.execution.streaming.state.RocksDBStateStoreProvider")
    try:
        q = stream.writeStream.outputMode("append").format("parquet").option("path", f"{place}/rows").option("checkpointLocation", f"{place}/checkpoint").trigger(availableNow=True).start()
        q.awaitTermination()
    finally:
        spark.conf.unset(key) if before is None else spark.conf.set(key, before)
    return spark.read.schema(stream.schema).parquet(f"{place}/rows")


def daily_rounds(events: DataFrame, delay: str = "1 hour") -> DataFrame:
    """A day of events is a round: rows, workers and the sum of the gradient's stand-in (whole thousandths)."""
    unit = F.round(F.col("value") * 1000).cast("bigint")
    return events.withWatermark("ts", delay).groupBy(F.window("ts", "1 day")).agg(F.count("*").alias("n"), F.approx_count_distinct("user_id").alias("workers"), F.sum(unit).alias("total"))


def sliding_rounds(events: DataFrame, size: str = "1 day", slide: str = "6 hours", delay: str = "1 hour") -> DataFrame:
    """Overlapping rounds: rows of each sliding window."""
    return events.withWatermark("ts", delay).groupBy(F.window("ts", size, slide)).agg(F.count("*").alias("n"))


def sessions(events: DataFrame, gap: str = "12 hours", delay: str = "1 hour") -> DataFrame:
    """Rows of each user's sessions, which a gap ends."""
    return events.withWatermark("ts", delay).groupBy("user_id", F.session_window("ts", gap)).agg(F.count("*").alias("n"))


def distinct_events(events: DataFrame, delay: str = "1 hour") -> DataFrame:
    """Each event once: gradients that arrive twice count once."""
    return events.withWatermark("ts", delay).dropDuplicatesWithinWatermark(["event_id"])


def against_parameters(events: DataFrame, parameters: DataFrame) -> DataFrame:
    """A stream joined with a static parameter table (event_type, weight) of a few rows, summed by type."""
    joined = events.join(F.broadcast(parameters), "event_type")
    return joined.groupBy("event_type").agg(F.sum(F.round(F.col("value") * 1000).cast("bigint") * F.col("weight")).alias("total"))


def carried_onebit(events: DataFrame, bucket: int = 16) -> DataFrame:
    """Each user's values in buckets of ``bucket``; the error of a bucket carries into the next as state."""
    ship_package(events.sparkSession)

    def send(key: tuple, batches: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
        error, waiting, number = (np.array(state.get[0]), list(state.get[1]), state.get[2]) if state.exists else (np.zeros(bucket), [], 0)
        rows = []
        frame = pd.concat(list(batches)).sort_values(["ts", "event_id"])
        waiting += frame["value"].tolist()
        while len(waiting) >= bucket:
            w = np.array(waiting[:bucket]) + error
            sent = kernels.onebit(w)
            error, waiting = w - sent, waiting[bucket:]
            rows.append((key[0], number, float(np.abs(sent[0])), int((sent < 0).sum()), float(np.abs(error).sum()), bucket + 32))
            number += 1
        state.update((error.tolist(), waiting, number))
        yield pd.DataFrame(rows, columns=["user_id", "bucket_id", "scale", "negatives", "carried", "n_bits"])

    return events.select("user_id", "event_id", "ts", "value").groupBy("user_id").applyInPandasWithState(
        send, "user_id bigint, bucket_id bigint, scale double, negatives bigint, carried double, n_bits bigint", "error array<double>, waiting array<double>, number bigint", "append", GroupStateTimeout.NoTimeout
    )


def online_descent(events: DataFrame, path: str, bits: int = 4, eta: float = 1e-5) -> None:
    """Each micro-batch is a round: workers' mean gradients of a one-value model, quantized, averaged and applied.

    Parameter versions are written to ``path`` by batch number, so a batch that is run
    again writes the same version.
    """
    from lossygrad.functions import quantization as Q
    from lossygrad.operators import quantizer

    def step(batch: DataFrame, number: int) -> None:
        spark = batch.sparkSession
        old = spark.read.parquet(f"{path}/version={number - 1}").first()["x"] if number else 0.0
        g = batch.groupBy((F.col("user_id") % 8).alias("vec_id")).agg(F.array(F.avg(F.lit(old) - F.col("value")), F.lit(0.0)).alias("values"))
        sent = quantizer.dequantize(quantizer.quantize(g, Q.levels_from_bits(bits), "max", step=number))
        mean = sent.agg(F.avg(F.get("values", F.lit(0))).alias("g"))
        mean.select((F.lit(old) - eta * F.coalesce("g", F.lit(0.0))).alias("x")).write.mode("overwrite").parquet(f"{path}/version={number}")

    q = events.writeStream.foreachBatch(step).option("checkpointLocation", f"{path}/checkpoint").trigger(availableNow=True).start()
    q.awaitTermination()
