from __future__ import annotations

import pytest

from pyspark.sql import functions as F

from lossygrad.operators import ledger


def test_curves(spark):
    curve = spark.createDataFrame([("a", 1, 3.0, 1.0), ("a", 2, 1.0, 2.0), ("a", 3, 0.5, 3.0), ("b", 1, 3.0, 1.0)], "run string, round int, loss double, wall_s double")
    assert {r["run"]: r["rounds"] for r in ledger.rounds_to(curve, 1.0, ["run"]).collect()} == {"a": 2, "b": None}
    assert [r["time_s"] for r in ledger.accuracy_curve(curve, ["run"]).where("run = 'a'").orderBy("round").collect()] == [1, 3, 6]
    assert ledger.time_spread(curve.where("run = 'a'"), ["run"]).first()["spread"] == pytest.approx(0.5)
    gaps = spark.createDataFrame([("a", e, 0.5**e) for e in range(5)], "run string, epoch int, gap double")
    r = ledger.contraction(gaps, ["run"]).first()
    assert r["worst"] == pytest.approx(0.5) and r["rate"] == pytest.approx(0.5)


def test_accuracy_and_times(spark):
    ranked = spark.createDataFrame([([1, 2, 3], 1), ([1, 2, 3], 2), ([1, 2, 3], 9)], "ranked array<int>, y int")
    assert ledger.topk_accuracy(ranked, 1).first()[0] == pytest.approx(1 / 3) and ledger.topk_accuracy(ranked, 2).first()[0] == pytest.approx(2 / 3)
    times = spark.createDataFrame([("w", 4, "float32", 8.0, 6.0, 2.0), ("w", 4, "fixed", 4.0, 2.0, 2.0)], "workload string, k int, codec string, epoch_s double, comm_s double, comp_s double")
    rows = {r["codec"]: r for r in ledger.speedup(times).collect()}
    assert rows["fixed"]["speedup"] == 2 and rows["float32"]["comm_share"] == 0.75
    acc = spark.createDataFrame([("w", "fp32", 0.9), ("w", "q4", 0.88)], "workload string, run string, top1 double")
    assert {r["run"]: round(r["gap"], 6) for r in ledger.accuracy_gap(acc).collect()} == {"fp32": 0, "q4": -0.02}


def test_shuffle_bytes(spark):
    n, written = ledger.shuffle_bytes_of(spark, spark.range(10000).repartition(4).count)
    assert n == 10000 and written > 0
    rows = spark.range(100000).select("id", F.md5(F.col("id").cast("string")).alias("m")).repartition(4, "id")
    assert ledger.shuffle_bytes_of(spark, lambda: rows.write.format("noop").mode("overwrite").save())[1] > 1_000_000


def test_bits(spark):
    rows = spark.createDataFrame([(0, 0, 100, 32, 4), (0, 1, 156, 32, 4)], "round int, shard int, n_bits long, n int, nnz int")
    r = ledger.bits(rows, ["round"]).first()
    assert (r["n_bits"], r["bits_per_coord"], r["ratio"]) == (256, 4.0, 8.0)
