from __future__ import annotations

import numpy as np
import pytest
from pyspark.sql import functions as F

from lossygrad.functions import bounds
from lossygrad.operators import baselines, kernels, layers
from lossygrad.optim import gd, sgd, svrg
from lossygrad.optim.channel import Channel
from lossygrad.optim.objectives import LeastSquares, Logistic, Perceptron, Recurrent, Softmax, accuracy
from lossygrad.plans import planner


def vec(spark, *rows):
    return spark.createDataFrame([(i, [float(x) for x in r]) for i, r in enumerate(rows)], "vec_id bigint, values array<double>")


def test_onebit(spark):
    r = baselines.onebit(vec(spark, [3, -4, 0])).first()
    third = float(np.float32(7 / 3))
    assert r["values"] == [third, -third, third] and r["n_bits"] == 35
    assert r["carried"] == pytest.approx([3 - third, -4 + third, -third])
    again = baselines.onebit(vec(spark, [3, -4, 0]), baselines.onebit(vec(spark, [3, -4, 0]))).first()
    w = np.array([3, -4, 0]) + np.array(r["carried"])
    assert again["values"] == pytest.approx(kernels.onebit(w).tolist())
    two = baselines.onebit(vec(spark, [3, -4, 0]), scale="two_means").first()
    assert two["values"] == [1.5, -4.0, 1.5] and two["n_bits"] == 67


def test_topk(spark):
    assert baselines.topk(vec(spark, [3, -4, 0, 4]), k=2).first()["values"] == [0, -4, 0, 4]
    assert kernels.topk(np.array([3.0, -4, 0, 4]), k=2).tolist() == [0, -4, 0, 4]
    v = np.array([3.0, -4, 0])
    assert kernels.topk(v, cover="l2").tolist() == [5, -5, 0]


def test_reduced(spark):
    rng = np.random.default_rng(0).normal(size=200)
    got = baselines.reduced(vec(spark, rng), "bfloat16").first()["values"]
    assert got == kernels.reduced(rng.astype(np.float32).astype(float), "bfloat16")[0].tolist() or np.allclose(got, rng, rtol=1 / 128)


@pytest.mark.parametrize("objective", [LeastSquares(6, 0.1), Logistic(6, 0.1), Softmax(6, 3), Perceptron(6, 5, 3, 2), Recurrent(2, 4, 3, 3)])
def test_gradients(objective):
    r = np.random.default_rng(1)
    a, y = r.normal(size=(9, 6)), r.integers(0, 3 if not isinstance(objective, Logistic) else 2, 9).astype(float)
    x = r.normal(size=objective.n) * 0.3
    g = objective.grad(x, a, y)
    for i in r.choice(objective.n, min(objective.n, 8), replace=False):
        e = np.zeros(objective.n)
        e[i] = 1e-5
        assert g[i] == pytest.approx((objective.loss(x + e, a, y) - objective.loss(x - e, a, y)) / 2e-5, rel=1e-4, abs=1e-7)


def learning(spark, m=400, dim=5, seed=0):
    r = np.random.default_rng(seed)
    a = r.normal(size=(m, dim))
    y = a @ np.arange(1, dim + 1) + 0.01 * r.normal(size=m)
    return a, y, spark.createDataFrame([(i, row.tolist(), float(t)) for i, (row, t) in enumerate(zip(a, y, strict=True))], "row_id bigint, features array<double>, y double")


def test_full_precision_equals_minibatch_descent(spark):
    a, y, df = learning(spark)
    objective = LeastSquares(5)
    x, ledger = sgd.train(df, objective, Channel(), 4, 3, 0.1)
    owners = {r["row_id"]: r["shard"] for r in sgd.deal(df, 4).collect()}
    want = np.zeros(5)
    for _ in range(3):
        grads = [objective.grad(want, a[[i for i in owners if owners[i] == w]], y[[i for i in owners if owners[i] == w]]) for w in range(4)]
        want = want - 0.1 * np.mean([g.astype(np.float32) for g in grads], axis=0)
    assert x == pytest.approx(want, rel=1e-6) and ledger[0]["n_bits"] == 4 * 5 * 32


@pytest.mark.parametrize("channel", [Channel("fixed", 4, 3), Channel("gap", s=2, norm="l2"), Channel("dense_prefix", s="sqrt", norm="l2"), Channel("auto", 4, 4), Channel("dense_omega", s=3)])
def test_simulated_lengths_equal_payloads(channel):
    v = np.random.default_rng(5).normal(size=11)
    parts = list(channel.parts(v, 3, 1))
    sent, bits = channel.send(v, 3, 1)
    got = np.concatenate([channel.restore(codec, payload, n, nb, s) for _, _, n, s, codec, nb, _, _, payload in parts])
    assert bits == sum(p[5] for p in parts) and got == pytest.approx(sent)


@pytest.mark.parametrize("bits", [2, 3, 4, 8])
@pytest.mark.parametrize("d", [1, 5, 64, 200])
def test_buckets_at_once_equal_bucket_by_bucket(bits, d):
    v = np.random.default_rng(bits).normal(size=171) * np.repeat([1.0, 0.0, 7.0], 57)
    s = max(1, 2 ** (bits - 1) - 1)
    scales, sign, level = kernels.quantize_buckets(v, d, s, (3, 4), 10)
    for b in range(len(scales)):
        one = kernels.quantize(v[b * d : (b + 1) * d], s, "max", (3, 4), 10 + b * d)
        assert scales[b] == one[0] and sign[b * d : (b + 1) * d].tolist() == one[1].tolist() and level[b * d : (b + 1) * d].tolist() == one[2].tolist()
    back = kernels.unpack_fixed(kernels.pack_fixed(scales, sign, level, bits), len(v), d, bits)
    assert back[0].tolist() == scales.tolist() and (back[1] * back[2]).tolist() == (sign * level).tolist()


def test_sparse_softmax_equals_dense():
    from lossygrad.optim.objectives import Softmax, SparseRows, SparseSoftmax

    r = np.random.default_rng(0)
    a = r.normal(size=(7, 12)) * (r.random((7, 12)) < 0.3)
    y, x = r.integers(0, 3, 7).astype(float), r.normal(size=36)
    at = [np.flatnonzero(row) for row in a]
    rows = SparseRows(np.concatenate([[0], np.cumsum([len(p) for p in at])]), np.concatenate(at), np.concatenate([row[p] for row, p in zip(a, at, strict=True)]))
    dense, sparse = Softmax(12, 3), SparseSoftmax(12, 3)
    assert sparse.loss(x, rows, y) == pytest.approx(dense.loss(x, a, y)) and sparse.grad(x, rows, y) == pytest.approx(dense.grad(x, a, y))
    use = np.array([True, False, True, True, False, False, True])
    assert sparse.grad(x, rows[use], y[use]) == pytest.approx(dense.grad(x, a[use], y[use]))


def test_shared_windows_gradient():
    from lossygrad.optim.objectives import SharedWindows

    r = np.random.default_rng(1)
    o = SharedWindows(4, 3, 5, 3)
    a, y, x = r.normal(size=(6, 12)), r.integers(0, 3, 6).astype(float), o.init(2)
    step = 1e-6
    numeric = [(o.loss(x + step * e, a, y) - o.loss(x - step * e, a, y)) / (2 * step) for e in np.eye(o.n)]
    assert o.grad(x, a, y) == pytest.approx(numeric, abs=1e-6)


def test_training_is_the_same_for_any_partitioning(spark):
    _, _, df = learning(spark)
    a, _ = sgd.train(df, LeastSquares(5), Channel("gap", s=2, norm="l2"), 4, 4, 0.05)
    b, _ = sgd.train(df.repartition(13), LeastSquares(5), Channel("gap", s=2, norm="l2"), 4, 4, 0.05)
    assert a == pytest.approx(b)


def test_compressed_descent_keeps_its_guarantee():
    r = np.random.default_rng(2)
    a = r.normal(size=(600, 8))
    y = a @ r.normal(size=8) + 0.1 * r.normal(size=600)
    objective = LeastSquares(8)
    best = objective.loss(objective.optimum(a, y), a, y)
    gaps = {}
    for name, channel in {"fp": Channel(), "s1": Channel("gap", s=1, norm="l2"), "s4": Channel("gap", s=4, norm="l2")}.items():
        x, _ = sgd.simulate(objective, a, y, channel, 8, 150, 0.05, 16, average_iterates=True)
        gaps[name] = objective.loss(x, a, y) - best
    start = objective.loss(np.zeros(8), a, y) - best
    assert gaps["fp"] < 0.1 * start and gaps["s4"] < 0.15 * start and gaps["s1"] < 0.5 * start
    sigma2 = max(float((objective.grad(np.zeros(8), a[i : i + 16], y[i : i + 16]) ** 2).sum()) for i in range(0, 600, 16)) * bounds.second_moment(8, 4) / 8
    smooth = float(np.linalg.eigvalsh(a.T @ a / 600)[-1])
    radius = float(np.sqrt((objective.optimum(a, y) ** 2).sum()))
    assert gaps["s4"] <= bounds.sgd_gap(radius, sigma2, 150, smooth)


def test_variance_reduction_contracts():
    r = np.random.default_rng(4)
    a = r.normal(size=(500, 6))
    y = a @ r.normal(size=6)
    objective = LeastSquares(6, 0.1)
    best = objective.loss(objective.optimum(a, y), a, y)
    ratio = {}
    for name, channel in {"fp": Channel(), "lq": Channel("dense_prefix", s="sqrt", norm="l2")}.items():
        _, out = svrg.simulate(objective, a, y, channel, 4, 60, 5, 0.03, evaluate=lambda p, x: {"gap": objective.loss(x, a, y) - best})
        gaps = [objective.loss(np.zeros(6), a, y) - best, *(o["gap"] for o in out)]
        ratio[name] = max(b / a for a, b in zip(gaps[:-1], gaps[1:], strict=True))
        if name == "lq":
            assert all(o["n_bits"] <= 4 * bounds.vr_bits(6, 60) for o in out)
    assert ratio["fp"] <= 0.9 and ratio["lq"] <= 0.9
    local, _ = svrg.simulate(objective, a, y, Channel(), 4, 60, 3, 0.03, sampling="local")
    assert objective.loss(local, a, y) - best < 0.2


def test_distributed_variance_reduction_equals_simulation(spark):
    a, y, df = learning(spark, 120)
    objective = LeastSquares(5, 0.1)
    channel = Channel("dense_prefix", s="sqrt", norm="l2")
    want, rows = svrg.simulate(objective, a, y, channel, 3, 10, 2, 0.05)
    got, out = svrg.train_vr(df, objective, channel, 3, 10, 2, 0.05)
    assert got == pytest.approx(want, rel=1e-3, abs=1e-4) and [o["n_bits"] for o in out] == pytest.approx([o["n_bits"] for o in rows], rel=0.05)


def test_variance_reduction_grid_shares_jobs(spark):
    a, y, df = learning(spark, 120)
    objective = LeastSquares(5, 0.1)
    runs = [svrg.VrRun("full", Channel()), svrg.VrRun("lq", Channel("dense_prefix", s="sqrt", norm="l2")), svrg.VrRun("naive", Channel("gap", s=2, norm="l2"), naive=True)]
    got = svrg.train_vr_grid(df, objective, runs, 3, 8, 2, 0.05)
    for r in runs:
        want, rows = svrg.simulate(objective, a, y, r.channel, 3, 8, 2, 0.05, naive=r.naive)
        assert got[r.name][-1]["anchor"] == pytest.approx(want, rel=1e-3, abs=1e-4)
        assert [o["n_bits"] for o in got[r.name]] == pytest.approx([o["n_bits"] for o in rows], rel=0.05)
    with pytest.raises(ValueError):
        svrg.train_vr_grid(df, objective, [svrg.VrRun("one", Channel("onebit"))], 3, 8, 2, 0.05)


@pytest.mark.parametrize("channel", [Channel("onebit", bucket=4), Channel("onebit", bucket=4, scale="two_means"), Channel("onebit"), Channel("topk", frac=0.3), Channel("topk", cover="l2"),
                                     Channel("reduced"), Channel("reduced", kind="float16"), Channel("reduced", kind="fixed8"), Channel(noise=0.1)])
@pytest.mark.parametrize("n", [0, 1, 11, 64])
def test_baselines_on_the_wire(channel, n):
    v = np.random.default_rng(n).normal(size=n)
    for v in (v, -np.abs(v), v * 0):
        sent, bits = channel.send(v, 3, 1)
        code, kept, payload = channel.payload(sent)
        assert channel.restore(code, payload, n, bits, kept) == pytest.approx(sent, rel=1e-6, abs=1e-12)
        assert 8 * len(payload) <= bits + 7 + (32 if channel.codec == "topk" else 0)


def test_matched_noise_has_the_quantizer_s_variance():
    v = np.random.default_rng(0).normal(size=512)
    quantizer = Channel("fixed", 4, 128)
    noisy = np.mean([((Channel(like=quantizer, seed=i).send(v, 1)[0] - v) ** 2).sum() for i in range(200)])
    rounded = np.mean([((Channel("fixed", 4, 128, seed=i).send(v, 1)[0] - v) ** 2).sum() for i in range(200)])
    assert quantizer.added_variance(v) == pytest.approx(rounded, rel=0.05) and noisy == pytest.approx(rounded, rel=0.05)


@pytest.mark.parametrize("bucket", [2, 5, 64])
def test_parameter_table_equals_driver_parameters(spark, bucket, monkeypatch):
    from lossygrad.optim import table

    a, y, df = learning(spark, 90)
    shards = sgd.deal(df, 3).select("row_id", "shard", "y")
    entries = df.select("row_id", F.posexplode("features").alias("at", "value")).select("row_id", F.col("at").cast("bigint").alias("coord"), "value").where("value <> 0")
    want, _ = sgd.train(df, LeastSquares(5), Channel(), 3, 2, 0.1)
    got = table.train_table(entries, shards, 5, 3, 2, 0.1, bucket=bucket)
    assert np.concatenate([r["values"] for r in got.orderBy("bucket_id").collect()]) == pytest.approx(want, rel=1e-5)
    lossy = table.train_table(entries, shards, 5, 3, 2, 0.1, s=8, bucket=bucket)
    x = np.concatenate([r["values"] for r in lossy.orderBy("bucket_id").collect()])
    assert LeastSquares(5).loss(x, a, y) < LeastSquares(5).loss(np.zeros(5), a, y)
    monkeypatch.setattr(sgd, "DRIVER_PARAMETERS", 4)
    with pytest.raises(ValueError, match="table"):
        sgd.train(df, LeastSquares(5), Channel(), 3, 2, 0.1)


def test_truncated_descent(spark):
    a, y, df = learning(spark)
    objective = LeastSquares(5)
    full, _ = gd.train_gd(df, objective, Channel(), 20, 0.3)
    top, ledger = gd.train_gd(df, objective, Channel("topk", frac=0.4), 20, 0.3)
    assert objective.loss(full, a, y) < 0.01 and objective.loss(top, a, y) < 0.5 and ledger[0]["n_bits"] < 5 * 32


def test_onebit_in_the_grid_carries_its_error(spark):
    a, y, df = learning(spark)
    objective = LeastSquares(5)
    shards = sgd.deal(df, 2)
    found, ledger = sgd.train_grid(shards, objective, [sgd.Run("carry", Channel("onebit"), 0.1), sgd.Run("none", Channel("onebit", carry=False), 0.1)], 25)
    assert objective.loss(found["carry"], a, y) < objective.loss(found["none"], a, y)
    assert ledger[0]["n_bits"] == 2 * (5 + 32)


def test_staleness_and_random_stop():
    r = np.random.default_rng(0)
    a = r.normal(size=(200, 4))
    y = a @ np.ones(4)
    objective = LeastSquares(4)
    fresh, _ = sgd.simulate(objective, a, y, Channel(), 4, 60, 0.05)
    stale, _ = sgd.simulate(objective, a, y, Channel(), 4, 60, 0.05, staleness=8)
    assert objective.loss(fresh, a, y) < 0.05 and objective.loss(stale, a, y) < 0.5
    assert not np.array_equal(fresh, stale)
    stopped, _ = sgd.simulate(objective, a, y, Channel(), 4, 60, 0.05, stop="random")
    assert objective.loss(stopped, a, y) < objective.loss(np.zeros(4), a, y)


def test_projection_steps_and_accuracy():
    assert sgd.project(np.array([3.0, 4]), "ball", 1) == pytest.approx([0.6, 0.8])
    assert sgd.project(np.array([3.0, -4]), "box", 2).tolist() == [2, -2]
    assert 0 < bounds.step_size("parallel", 1.0, 1, 1, 4, 100) < bounds.step_size("constant", 1.0, 1, 1, 1, 100) < 1
    objective = Softmax(2, 3)
    x = np.array([[1.0, 0, 0], [0, 1.0, 0]]).ravel()
    assert accuracy(objective, x, np.eye(2), np.array([0.0, 2.0])) == 0.5 and accuracy(objective, x, np.eye(2), np.array([0.0, 2.0]), 3) == 1.0


def test_planner(spark):
    assert planner.plan(1000, 4, bucket=1).channel.codec == "float32"
    assert planner.plan(10**9, 5000).parameters == "table" and planner.plan(10**9, 5000).salts > 1
    assert planner.plan(4096, 4, s="sqrt").channel.codec == "dense_prefix" and planner.plan(4096, 4, s=1).channel.codec == "gap"
    cells = spark.createDataFrame([(0, i, 1.0) for i in range(100)], "bucket int, shard int, v double")
    assert planner.two_level_sum(cells, ["bucket"], "v", "shard", 10).first()["v"] == 100
    p = planner.step_table(spark.createDataFrame([(0, [1.0, 2.0]), (1, [5.0])], "bucket_id bigint, values array<double>"), spark.createDataFrame([(0, [2.0, 4.0])], "bucket_id bigint, total array<double>"), 0.5, 2)
    assert {r["bucket_id"]: r["values"] for r in p.collect()} == {0: [0.5, 1.0], 1: [5.0]}


def test_layer_policy(spark):
    made = layers.policy(layers.layers(spark, [("a", "conv", 3000, 10), ("b", "dense", 100, 10), ("c", "dense", 40, 1000)]), bits_by_kind={"conv": 8})
    rows = {r["name"]: r for r in made.collect()}
    assert rows["a"]["bits"] == 8 and rows["a"]["bucket"] == 510 and rows["b"]["bits"] == 32 and rows["c"]["bucket"] == 1000
    assert layers.report(made).first()["share_quantized"] == pytest.approx(70000 / 71000)
