from __future__ import annotations

import numpy as np
import pytest
from hypothesis import given, settings
from hypothesis import strategies as st
from pyspark.sql import functions as F

from lossygrad.functions import bounds, codes
from lossygrad.operators import kernels, messages, quantizer

# Published lengths and code words.
LENGTHS = {1: 1, 2: 3, 3: 3, 4: 6, 7: 6, 8: 7, 15: 7, 16: 11, 31: 11, 32: 12, 100: 13, 1000: 17, 65536: 28}
WORDS = {1: "0", 2: "100", 3: "110", 4: "101000", 7: "101110", 8: "1110000", 16: "10100100000"}


def test_omega(spark):
    got = spark.createDataFrame([(k,) for k in [*LENGTHS, (1 << 20) + 1, 1 << 40]], "k bigint").select("k", codes.omega_len(F.col("k")).alias("n"), codes.omega_bits(F.col("k")).alias("bits")).collect()
    for r in got:
        assert r["n"] == len(r["bits"]) == len(kernels.omega(r["k"]))
        assert LENGTHS.get(r["k"], r["n"]) == r["n"] and WORDS.get(r["k"], r["bits"]) == r["bits"] == kernels.omega(r["k"])


@given(st.lists(st.integers(1, 1 << 45), max_size=20))
def test_omega_reads_back(ks):
    text, at, got = "".join(map(kernels.omega, ks)), 0, []
    while at < len(text):
        k, at = kernels.omega_read(text, at)
        got.append(k)
    assert got == ks


LEVELS = st.lists(st.integers(-7, 7), max_size=60)


@given(LEVELS, st.sampled_from(["gap", "dense_omega", "dense_prefix", "fixed", "auto"]))
@settings(max_examples=200, deadline=None)
def test_messages_read_back(signed, codec):
    level, sign = np.abs(np.array(signed, int)).astype(np.int32), np.where(np.array(signed) < 0, -1, 1).astype(np.int8)
    name, bits, payload = kernels.encode(codec, 1.5, sign, level, 4)
    scale, s2, l2 = kernels.decode(name, payload, len(level), bits - (3 if codec == "auto" else 0), 4)
    assert scale == 1.5 and (s2 * l2 == sign * level).all()


def test_long_gap_reads_back():
    level = np.zeros((1 << 20) + 5, np.int32)
    level[[2, (1 << 20) + 3]] = 3, 1
    sign = np.ones(len(level), np.int8)
    name, bits, payload = kernels.encode("gap", 1.0, sign, level)
    assert (kernels.decode(name, payload, len(level), bits)[2] == level).all()


def test_worked_message(spark):
    df = spark.createDataFrame([([1, -1, 1], [1, 2, 0])], "sign array<tinyint>, level array<int>")
    r = df.select(codes.gap_bits(F.col("level")).alias("n"), codes.gap_string(F.col("sign"), F.col("level")).alias("bits")).first()
    assert r["n"] == 40 and r["bits"] == "000" + "01100"
    assert kernels.encode("gap", 5.0, np.array([1, -1, 1], np.int8), np.array([1, 2, 0], np.int32))[1] == 40


def test_truncated_message_fails():
    name, bits, payload = kernels.encode("gap", 5.0, np.ones(9, np.int8), np.full(9, 3, np.int32))
    with pytest.raises(ValueError, match="truncated"):
        kernels.decode(name, payload[:5], 9, bits)


def test_column_lengths_match_payloads(spark, sf):
    from lossygrad.sources import embeddings

    made = quantizer.quantize(embeddings(spark, sf), 7, "max").persist()
    lengths = {"gap": codes.gap_bits(F.col("level")), "dense_omega": codes.dense_omega_bits(F.col("level")), "dense_prefix": codes.dense_prefix_bits(F.col("level")), "fixed": codes.fixed_bits(F.col("level"), 4)}
    for codec, length in lengths.items():
        want = {r["vec_id"]: r["n"] for r in made.select("vec_id", length.alias("n")).collect()}
        got = {r["shard"]: (r["n_bits"], len(r["payload"])) for r in messages.encode(made, codec, 4).select("shard", "n_bits", "payload").collect()}
        assert {k: v[0] for k, v in got.items()} == want
        assert all(b == 4 + -(-(n - 32) // 8) for n, b in got.values())


@given(st.lists(st.floats(-100, 100, allow_nan=False), min_size=1, max_size=64).map(np.array))
@settings(max_examples=100, deadline=None)
def test_prefix_code_expectation(v):
    """Exact expected bits of the dense prefix code at s = sqrt(n) stay under the bound for every vector."""
    n = len(v)
    s = max(1, int(np.sqrt(n)))
    scale = float(kernels.scale_of(v))
    if not scale:
        return
    pos = np.minimum(np.abs(v) / scale, 1) * s
    low = np.minimum(np.floor(pos), s - 1)
    f = pos - low
    cost = lambda k: np.where(k <= 1, 2, k + 2)
    assert 32 + ((1 - f) * cost(low) + f * cost(low + 1)).sum() <= bounds.dense_bits(n) + 1e-9


# Figures of the formulas.
TABLE = {(64, 1): (8, 9, 111.0, 211.2), (64, 8): (1, 128, 608.0, 211.2), (1024, 1): (32, 33, 425.9, 2899.2), (1024, 32): (1, 2048, 9248.0, 2899.2), (15000, 1): (122.474, 123.5, 1870.2, 42032),
         (60000, 1): (244.949, 245.9, 4064.5, 168032), (60000, 16): (15.309, 4175.2, 42939.5, 168032)}


@pytest.mark.parametrize(("key", "want"), TABLE.items())
def test_bounds_table(key, want):
    n, s = key
    got = (bounds.variance(n, s), bounds.nnz(n, s), bounds.gap_bits(n, s), bounds.dense_bits(n))
    assert all(a == pytest.approx(b, rel=2e-3) for a, b in zip(got, want, strict=True))


def test_other_bounds():
    assert bounds.saving(100) == pytest.approx(5.714, abs=1e-3)
    assert [bounds.fixed_bits(b, d) for b, d in ((2, 128), (4, 512), (8, 512))] == [2.25, 4.0625, 8.0625]
    assert bounds.bucket_variance(512, 16) == pytest.approx(1.414, abs=1e-3)
    assert bounds.second_moment(64, 8) == 2 and bounds.contraction(2) == pytest.approx(0.81)
    assert bounds.omega_bound(16) >= 4 and bounds.vr_bits(100, 9) == pytest.approx((32 + 280) * 10 + 3200)
