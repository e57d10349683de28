from __future__ import annotations

import numpy as np
import pytest
from hypothesis import given, settings
from hypothesis import strategies as st
from pyspark.sql import functions as F

from lossygrad.functions import bounds
from lossygrad.functions import quantization as Q
from lossygrad.functions.arrays import sign_of
from lossygrad.operators import kernels, layout, ledger, quantizer

VECTORS = st.lists(st.floats(-1e6, 1e6, allow_nan=False, width=32), min_size=1, max_size=70).map(np.array)


def one(spark, values):
    return spark.createDataFrame([(0, [float(x) for x in values])], "vec_id bigint, values array<double>")


def test_worked_example(spark):
    made = quantizer.quantize(one(spark, [3, -4, 0]), 2)
    r = made.first()
    assert r["scale"] == 5.0 and r["sign"] == [1, -1, 1]
    assert r["level"][0] in (1, 2) and r["level"][1] in (1, 2) and r["level"][2] == 0
    report = ledger.variance_report(made).first()
    assert report["variance"] == pytest.approx(1.0 + 1.5) and report["variance_bound"] == pytest.approx(18.75)
    top = quantizer.quantize(one(spark, [3, -4, 0]), 2, "max").first()
    assert top["scale"] == 4.0 and top["level"][1] == 2 and top["level"][2] == 0 and top["level"][0] in (1, 2)


def test_probabilities_of_the_worked_example(spark):
    seeds = spark.range(4000).select(F.col("id").alias("vec_id"), F.array(F.lit(3.0), F.lit(-4.0), F.lit(0.0)).alias("values"))
    up = quantizer.quantize(seeds, 2).agg(F.avg((F.get("level", F.lit(0)) == 2).cast("double")), F.avg((F.get("level", F.lit(1)) == 2).cast("double"))).first()
    assert up[0] == pytest.approx(0.2, abs=0.03) and up[1] == pytest.approx(0.6, abs=0.03)


@pytest.mark.parametrize(("values", "levels"), [([0, 0, 0], [0, 0, 0]), ([0, 0, 7, 0], [0, 0, 4, 0]), ([], [])])
def test_zero_spike_and_empty(spark, values, levels):
    assert quantizer.quantize(one(spark, values), 4).first()["level"] == levels


def test_constant_vector_has_level_one_everywhere(spark):
    r = quantizer.quantize(one(spark, [2.0] * 64), 8).first()
    assert r["level"] == [1] * 64 or set(r["level"]) <= {0, 1}


def test_signs_of_zeros(spark):
    r = spark.range(1).select(sign_of(F.lit(-0.0)).alias("a"), sign_of(F.lit(0.0)).alias("b"), sign_of(F.lit(-1e-300)).alias("c")).first()
    assert (r["a"], r["b"], r["c"]) == (1, 1, -1)


@given(VECTORS, st.integers(1, 12), st.sampled_from(["l2", "max"]))
@settings(max_examples=150, deadline=None)
def test_kernel_bounds(v, s, norm):
    scale, sign, level = kernels.quantize(v, s, norm, (1,))
    assert level.min() >= 0 and level.max() <= s
    if float(scale):
        pos = np.minimum(np.abs(v) / float(scale), 1) * s
        assert (np.abs(level - pos) <= 1).all()
        f = pos - np.minimum(np.floor(pos), s - 1)
        exact = (float(scale) / s) ** 2 * (f * (1 - f)).sum()
        if norm == "l2":
            assert exact <= bounds.variance(len(v), s) * float(scale) ** 2 * (1 + 1e-9)
            assert np.minimum(1, pos).sum() <= bounds.nnz(len(v), s) * (1 + 1e-9)


@given(st.floats(0, 3e38, allow_nan=False))
@settings(max_examples=200, deadline=None)
def test_scale_is_the_next_float_above(r):
    f = kernels.scale32(r)
    assert float(f) >= r and float(np.nextafter(f, np.float32(-1))) < r or r == 0


def test_column_scale_matches_kernel(spark):
    rs = [float(x) for x in np.random.default_rng(0).random(500) * 10.0 ** np.random.default_rng(1).integers(-20, 20, 500)]
    got = spark.createDataFrame([(x,) for x in rs], "r double").select("r", Q.scale32(F.col("r")).alias("f")).collect()
    assert all(np.float32(x["f"]) == kernels.scale32(x["r"]) for x in got)


def test_unbiased_over_seeds():
    v = np.random.default_rng(3).normal(size=64)
    n, s = 4000, 4
    sums = np.zeros(64)
    for seed in range(n):
        sums += kernels.dequantize(*kernels.quantize(v, s, "l2", (seed,)), s)
    scale = float(kernels.scale_of(v))
    pos = np.abs(v) / scale * s
    f = pos - np.floor(pos)
    error = scale / s * np.sqrt(f * (1 - f) / n) + 1e-9
    assert (np.abs(sums / n - v) <= 5 * error).all()


def test_same_levels_in_every_layout(spark):
    df = spark.createDataFrame([(i, [float(x) for x in np.random.default_rng(i).normal(size=40)]) for i in range(20)], "vec_id bigint, values array<double>")
    array = {(r["vec_id"], i): k for r in quantizer.quantize(df, 5, "max").collect() for i, k in enumerate(r["level"])}
    long = layout.to_long(df)
    assert {(r["vec_id"], r["coord"]): r["level"] for r in quantizer.quantize_long(long, 5, "max").collect()} == array
    assert {(r["vec_id"], r["coord"]): r["level"] for r in quantizer.quantize_by_intervals(long, 5, "max").collect()} == array
    assert {(r["vec_id"], i): k for r in quantizer.quantize(df.repartition(7), 5, "max").collect() for i, k in enumerate(r["level"])} == array
    whole = quantizer.quantize(layout.bucketize(df, 40), 5, "max", bucket=40)
    assert {(r["vec_id"], i): k for r in whole.collect() for i, k in enumerate(r["level"])} == array


def test_buckets(spark):
    df = one(spark, range(10))
    rows = {r["bucket_id"]: r["values"] for r in layout.bucketize(df, 4).collect()}
    assert rows == {0: [0, 1, 2, 3], 1: [4, 5, 6, 7], 2: [8, 9]}
    assert {r["bucket_id"]: r["values"] for r in layout.bucketize_long(layout.to_long(df), 4).collect()} == rows
    single = quantizer.dequantize(quantizer.quantize(layout.bucketize(df, 1), 3, bucket=1)).collect()
    assert all(r["values"][0] == pytest.approx(r["bucket_id"]) for r in single)
    assert layout.row_aligned(512, 200) == 400 and layout.row_aligned(100, 300) == 300


def test_levels_from_bits():
    assert [Q.levels_from_bits(b) for b in (2, 4, 8)] == [1, 7, 127]
    assert Q.levels_from_bits(4, "paper_example") == 16


@pytest.mark.parametrize("bad", [[float("nan"), 1.0], [float("inf")], [None, 1.0], None])
def test_bad_vectors_fail(spark, bad):
    df = spark.createDataFrame([(1, bad)], "vec_id bigint, values array<double>")
    with pytest.raises(Exception, match="vector with a null"):
        layout.checked(df).collect()


@pytest.mark.parametrize("s", [0, -1, 1.5, True, "cube"])
def test_bad_levels_fail(spark, s):
    with pytest.raises(ValueError, match="levels"):
        quantizer.quantize(one(spark, [1.0]), s)


def test_dense_index(spark):
    df = spark.range(1000).repartition(7).persist()
    assert sorted(r["row_id"] for r in layout.dense_index(df).collect()) == list(range(1000))
