"""Plans: payloads cross the exchange, filters reach the scan, no window on one partition."""

from __future__ import annotations

import pytest
from pyspark.sql import functions as F

from lossygrad import sources
from lossygrad.operators import layout, messages, quantizer
from lossygrad.queries import QUERIES, load
from lossygrad.streaming import online


load()


def plan_of(df) -> str:
    return df._jdf.queryExecution().executedPlan().toString()


def test_payload_crosses_the_exchange(spark, sf):
    made = quantizer.quantize(sources.embeddings(spark, sf), 4)
    plan = plan_of(messages.by_bucket(messages.encode(made.select("vec_id", "scale", "sign", "level"))))
    below = plan.split("Exchange hashpartitioning(bucket_id")[1].splitlines()[1]
    assert "MapInArrow" in below and "payload" in below


def test_pruning_and_pushdown(spark, sf):
    plan = plan_of(QUERIES["filter_date_holdout"](spark, sf))
    assert "PushedFilters: [IsNotNull(o_orderdate), GreaterThanOrEqual(o_orderdate" in plan and "o_totalprice" not in plan


@pytest.mark.parametrize("name", ["lq_orders_long_s16", "lq_lineitem_orders_4bit", "gap_window_s4", "rank_coords", "bit_offsets_running", "asof_params_events"])
def test_no_single_partition_window(spark, sf, name):
    plan = plan_of(QUERIES[name](spark, sf))
    for chunk in plan.split("Window")[1:]:
        assert "SinglePartition" not in chunk.split("Exchange", 1)[1].splitlines()[0] if "Exchange" in chunk else True


def test_partial_sums_before_the_shuffle(spark, sf):
    assert "partial_sum" in plan_of(QUERIES["agg_gradient_partial"](spark, sf))


def test_quantizing_buckets_needs_no_shuffle(spark, sf):
    made = quantizer.quantize(layout.bucketize(sources.embeddings(spark, sf).select("vec_id", "values"), 16), 4, bucket=16)
    assert "Exchange" not in plan_of(made)


def test_message_store(spark, sf, tmp_path):
    made = quantizer.quantize(sources.embeddings(spark, sf), 4)
    path = str(tmp_path / "messages")
    for round_ in (0, 1, 1):  # a round that is written again replaces itself
        sources.write_messages(messages.encode(made, "gap", round_=round_), path)
    assert sources.read_messages(spark, path).groupBy("round").count().orderBy("round").collect() == [(0, 500), (1, 500)]
    assert sources.read_messages(spark, path, 1).agg(F.sum("n_bits")).first()[0] > 0


def test_vector_readers(spark, tmp_path):
    df = spark.createDataFrame([(1, [1.0, 2.0])], "vec_id bigint, values array<double>")
    for fmt in ("orc", "json", "parquet"):
        df.write.format(fmt).save(str(tmp_path / fmt))
        assert sources.vectors(spark, str(tmp_path / fmt), fmt).collect() == df.collect()


def test_online_descent(spark, sf, tmp_path):
    online.online_descent(online.event_stream(spark, sf), str(tmp_path / "versions"))
    assert spark.read.parquet(str(tmp_path / "versions" / "version=0")).count() == 1


def test_descent_in_tables_sends_payloads_only(spark, sf):
    plan = plan_of(QUERIES["cps_step"](spark, sf))
    assert plan.count("Exchange hashpartitioning(shard") <= 1 and "Exchange hashpartitioning(bucket_id" in plan
    below = plan.split("Exchange hashpartitioning(bucket_id")[1].splitlines()[1]
    assert "MapInArrow" in below and "payload" in below

