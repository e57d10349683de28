"""Streaming queries, run over the table as a stream of files."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from lossygrad.queries import query
from lossygrad.streaming import online


@query("stream_daily_rounds", "SELECT CAST(CAST(ts AS DATE) AS VARCHAR) AS day, count(*) AS n, CAST(sum(CAST(round(value * 1000) AS BIGINT)) AS BIGINT) AS total FROM events GROUP BY 1")
def stream_daily_rounds(spark: SparkSession, sf_dir: str) -> DataFrame:
    got = online.drain(online.daily_rounds(online.event_stream(spark, sf_dir)))
    return got.select(F.col("window.start").cast("date").cast("string").alias("day"), "n", "total")


@query("stream_onebit_state")
def stream_onebit_state(spark: SparkSession, sf_dir: str) -> DataFrame:
    return online.drain(online.carried_onebit(online.event_stream(spark, sf_dir)), "append")


@query(
    "stream_sliding_rounds",
    "SELECT strftime(make_timestamp((epoch_us(ts) // 21600000000 - i) * 21600000000), '%Y-%m-%d %H') AS start, count(*) AS n FROM events, (SELECT unnest(range(4)) AS i) GROUP BY 1",
)
def stream_sliding_rounds(spark: SparkSession, sf_dir: str) -> DataFrame:
    got = online.drain(online.sliding_rounds(online.event_stream(spark, sf_dir)))
    return got.select(F.date_format("window.start", "yyyy-MM-dd HH").alias("start"), "n")


@query("stream_distinct_events", "SELECT event_type, count(DISTINCT event_id) AS n FROM events GROUP BY event_type")
def stream_distinct_events(spark: SparkSession, sf_dir: str) -> DataFrame:
    got = online.drain_to_files(online.distinct_events(online.event_stream(spark, sf_dir)).select("event_id", "event_type"))
    return got.groupBy("event_type").agg(F.count("*").alias("n"))


@query("stream_static_join", "SELECT event_type, CAST(sum(CAST(round(value * 1000) AS BIGINT) * length(event_type)) AS BIGINT) AS total FROM events GROUP BY event_type")
def stream_static_join(spark: SparkSession, sf_dir: str) -> DataFrame:
    from lossygrad.sources import table

    kinds = table(spark, sf_dir, "events").select("event_type").distinct().select("event_type", F.length("event_type").cast("bigint").alias("weight"))
    return online.drain(online.against_parameters(online.event_stream(spark, sf_dir), kinds))


@query(
    "stream_sessions",
    """
    WITH g AS (SELECT user_id, ts, CASE WHEN ts - lag(ts) OVER (PARTITION BY user_id ORDER BY ts) < INTERVAL 12 HOUR THEN 0 ELSE 1 END AS fresh FROM events),
    s AS (SELECT user_id, ts, sum(fresh) OVER (PARTITION BY user_id ORDER BY ts) AS session FROM g)
    SELECT user_id, count(*) AS n FROM s GROUP BY user_id, session
    """,
)
def stream_sessions(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All sessions, those still open at the newest event too."""
    return online.drain(online.sessions(online.event_stream(spark, sf_dir))).select("user_id", "n")
