"""The experiment workloads as queries; timings keep them from having SQL twins."""

from __future__ import annotations

import numpy as np
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from lossygrad import experiments as E
from lossygrad.functions import bounds
from lossygrad.operators import layout
from lossygrad.optim import sgd, svrg
from lossygrad.optim.channel import Channel
from lossygrad.optim.objectives import LeastSquares, Perceptron
from lossygrad.queries import query
from lossygrad.sources import features

for _name, _run in {
    "accuracy_lang": lambda s, d: E.accuracy(s, d, "lang"),
    "accuracy_quality": E.quality,
    "bucket_grid": E.bucket_grid,
    "norm_comparison": E.norm_comparison,
    "noise_comparison": E.noise_comparison,
    "onebit_compare": E.onebit_comparison,
    "layer_sensitivity": E.layer_sensitivity,
    "breakdown_epoch": E.breakdown,
    "sequence_recurrent": E.sequence,
    "convex_levels": E.convex,
    "convex_wide": E.convex_wide,
    "strongly_convex": E.strongly_convex,
    "hard_target": E.hard_target,
    "skip_training": E.skip_training,
    "wide_sparse": E.wide_sparse,
    "model_depth": E.depths,
    "two_layer": E.two_layer,
    "wire_bytes": E.wire_bytes,
    "async_staleness": E.staleness,
    "step_and_batch": E.step_and_batch,
}.items():

    @query(_name)
    def experiment(spark: SparkSession, sf_dir: str, run=_run) -> DataFrame:
        return E.as_rows(spark, run(spark, sf_dir))


@query(
    "scale_messages",
    """
    WITH n AS (SELECT max(o_orderkey) AS top, count(*) * 16 AS n FROM orders), s(bits, bucket) AS (VALUES (2, 128), (4, 512), (8, 512)),
    b AS (SELECT bits, bucket, count(DISTINCT o_orderkey // bucket) * 16 AS buckets FROM orders, s GROUP BY ALL)
    SELECT bits, bucket, CAST(buckets AS BIGINT) AS buckets, CAST(n AS BIGINT) AS n, CAST(32 * buckets + bits * n AS BIGINT) AS fixed_bits FROM b, n
    """,
)
def scale_messages(spark: SparkSession, sf_dir: str) -> DataFrame:
    return E.scale_messages(spark, sf_dir).select("bits", "bucket", "buckets", "n", "fixed_bits")


@query("vr_contraction")
def vr_contraction(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Gap to the optimum after each epoch: exact, quantized and naively quantized corrections."""
    base = features.planted(spark, sf_dir).persist()
    data = layout.dense_index(base).select("row_id", "features", "y").persist()
    objective = LeastSquares(5, 0.05)
    # The Hessian column by column: differences of gradients are exact for least squares.  One pass for all.
    shards = data.select("row_id", F.lit(0).alias("shard"), "features", "y")
    (full, *columns), _ = svrg.anchor_gradients(shards, objective, [objective.init(), *np.eye(5)])
    best = np.linalg.solve(np.stack([c - full for c in columns]), -full)
    runs = [svrg.VrRun("float32", Channel()), svrg.VrRun("lq_sqrt", Channel("dense_prefix", s="sqrt", norm="l2")), svrg.VrRun("naive_s1", Channel("gap", s=1, norm="l2"), naive=True)]
    ledger = svrg.train_vr_grid(data, objective, runs, 8, 12, 4, 0.35)
    points = {"best": best, "start": objective.init()} | {f"{n}/{r['epoch']}": r["anchor"] for n, rows in ledger.items() for r in rows}
    measured = sgd.evaluate(data, objective, points, ())
    floor = measured["best"]["loss"]
    out = []
    for run in runs:
        gap = max(measured["start"]["loss"] - floor, 0.0)
        out.append({"run": run.name, "epoch": 0, "gap": gap, "n_bits": 0, "bits_bound": 0.0, "contracts": True})
        for r in ledger[run.name]:
            was, gap = gap, max(measured[f"{run.name}/{r['epoch']}"]["loss"] - floor, 0.0)
            out.append({"run": run.name, "epoch": r["epoch"], "gap": gap, "n_bits": int(r["n_bits"]), "bits_bound": 8 * bounds.vr_bits(5, 12), "contracts": bool(gap <= 0.9 * was + 1e-12)})
    data.unpersist()
    base.unpersist()
    return E.as_rows(spark, out)


@query("nonconvex_stop")
def nonconvex_stop(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Squared gradient norm of a perceptron at a randomly drawn round, by channel."""
    data = features.vectors_with_labels(spark, sf_dir)
    objective = Perceptron(64, 16, 10)
    shards = sgd.deal(data, 4)
    stop, rows = 1 + int(sgd.uniform_array(1, 3, 77)[0] * 10), []
    channels = {"fp32": Channel(), "q4_512": E.quantized(4, 512), "lq_sqrt": Channel("dense_prefix", s="sqrt", norm="l2", bucket=512)}
    found, ledger = sgd.train_grid(shards, objective, [sgd.Run(n, c, 0.5) for n, c in channels.items()], stop)
    (g0, *ends), _ = svrg.anchor_gradients(shards, objective, [objective.init(0), *found.values()])
    for name, g in zip(found, ends, strict=True):
        rows.append({"run": name, "stopped_at": stop, "grad_norm2": float(g @ g), "start_norm2": float(g0 @ g0), "n_bits": int(sum(r["n_bits"] for r in ledger if r["run"] == name))})
    shards.unpersist()
    return E.as_rows(spark, rows)
