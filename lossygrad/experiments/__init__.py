"""Experiment workloads: each function trains over whole tables and returns measured rows.

The models stand in for the networks of the study: they imitate its ratios of message
size to computation, not its networks.  Columns: workload, run, k, bits, bucket, norm,
rounds, loss, top1, top2 (``measured_on`` says on which rows), n_bits, bits_per_coord,
ratio, comp_s, codec_s, wall_s, transfer_s, and beside the grid's full-precision run: top1_gap,
speedup of an epoch, and rounds to its final training loss (-1: not reached).
``transfer_s`` is a model, bits over ``BANDWIDTH`` to k - 1 others, since one machine has no
network to measure; ``wall_spread`` is the deviation of the measured rounds over their mean.
"""

from __future__ import annotations

import time
from collections.abc import Callable, Iterator
from contextlib import contextmanager

import numpy as np
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from lossygrad.functions import bounds
from lossygrad.functions.quantization import PRESETS
from lossygrad.operators import layout
from lossygrad.operators import ledger as ledgers
from lossygrad.optim import sgd, svrg
from lossygrad.optim.channel import Channel
from lossygrad.optim.objectives import LeastSquares, Logistic, Perceptron, Recurrent, SharedWindows, Softmax, SparseSoftmax
from lossygrad.optim.sgd import Run
from lossygrad.sources import features

#: Modelled bits a second between workers.
BANDWIDTH = 1e9
DIM = 1024


def quantized(bits: int, bucket: int | None, codec: str = "fixed", norm: str = "max", **more) -> Channel:
    return Channel(codec, bits, bucket, norm, **more)


FULL = Channel()
PRESET = {"fp32": FULL} | {f"q{PRESETS[p][0]}_{PRESETS[p][1]}": quantized(*PRESETS[p]) for p in ("8bit", "4bit", "2bit")}
AGGRESSIVE = {f"q{PRESETS[p][0]}_{PRESETS[p][1]}": quantized(*PRESETS[p]) for p in ("4bit_wide", "2bit_narrow")}


@contextmanager
def kept(df: DataFrame) -> Iterator[DataFrame]:
    """``df``, kept while it is used."""
    df.persist()
    try:
        yield df
    finally:
        df.unpersist()


def as_rows(spark: SparkSession, rows: list[dict]) -> DataFrame:
    types = {bool: "boolean", int: "bigint", float: "double", str: "string"}
    rows = [{k: v.item() if isinstance(v, np.generic) else v for k, v in r.items()} for r in rows]
    keys = list(dict.fromkeys(k for r in rows for k in r))
    kind = {k: next(types[type(r[k])] for r in rows if k in r) for k in keys}
    return spark.createDataFrame([tuple(r.get(k) for k in keys) for r in rows], ", ".join(f"`{k}` {kind[k]}" for k in keys))


def run_grid(train: DataFrame, test: DataFrame, objective, channels: dict[str, Channel], *, workload: str, k: int, rounds: int, eta: float | dict[str, float] | Callable, frac: float = 1.0, seed: int = 0,
             staleness: dict[str, int] | None = None, tops: tuple[int, ...] = (1, 2)) -> list[dict]:
    """Trains every channel over the same dealt data and measures each on ``test``."""
    shards = sgd.deal(train, k)
    runs = [Run(name, c, eta[name] if isinstance(eta, dict) else eta, frac, seed, (staleness or {}).get(name, 0)) for name, c in channels.items()]
    try:
        found, ledger = sgd.train_grid(shards, objective, runs, rounds)
        measured = sgd.evaluate(test, objective, found, tops)
    finally:
        shards.unpersist()
    out = []
    for name, c in channels.items():
        mine = [r for r in ledger if r["run"] == name]
        bits, workers = sum(r["n_bits"] for r in mine), sum(r["workers"] for r in mine)
        per = bits / max(workers * objective.n, 1)
        walls = np.array([r["wall_s"] for r in mine])
        out.append({
            "workload": workload, "run": name, "k": k, "codec": c.codec, "bits": c.bits, "bucket": c.bucket or 0, "norm": c.norm, "rounds": rounds, "n": objective.n, "measured_on": "train" if test is train else "held_out",
            "first_loss": float(mine[0]["loss"]), "train_loss": float(mine[-1]["loss"]), "loss": float(measured[name]["loss"]),
        } | {f"top{t}": float(measured[name].get(f"top{t}", float("nan"))) for t in tops} | {
            "n_bits": int(bits), "bits_per_coord": per, "ratio": 32 / per if per else float("inf"), "comp_s": sum(r["comp_s"] for r in mine), "codec_s": sum(r["codec_s"] for r in mine),
            "wall_s": float(walls.sum()), "wall_spread": float(walls.std() / max(walls.mean(), 1e-12)), "transfer_s": ledgers.fanout(bits, k) / max(k, 1) / BANDWIDTH,
        })
    return beside(out, ledger)


def beside(rows: list[dict], ledger: list[dict], base: str = "fp32") -> list[dict]:
    """Adds the split of an epoch, and what each run gains and loses against the full-precision run of its grid."""
    for r in rows:
        r["comm_s"] = r["codec_s"] / r["k"] + r["transfer_s"]
        r["epoch_s"] = (r["comm_s"] + r["comp_s"] / r["k"]) / r["rounds"]
        r["comm_share"] = r["comm_s"] / max(r["comm_s"] + r["comp_s"] / r["k"], 1e-12)
    full = next((r for r in rows if r["run"] == base), None)
    if full is None:
        return rows
    for r in rows:
        losses = [x["loss"] for x in ledger if x["run"] == r["run"]]
        r["rounds_to_base"] = next((i + 1 for i, x in enumerate(losses) if x <= full["train_loss"] * 1.02), -1)
        r["speedup"] = full["epoch_s"] / max(r["epoch_s"], 1e-12)
        r["time_to_base_s"] = r["rounds_to_base"] * r["epoch_s"] if r["rounds_to_base"] > 0 else float("nan")
        if "top1" in r:
            r["top1_gap"] = r["top1"] - full["top1"]
    return rows


def split_grid(made: DataFrame, objective, channels: dict[str, Channel], **how) -> list[dict]:
    """Trains on the train rows of ``made`` and measures on its held-out rows."""
    with kept(made):
        return run_grid(made.where("split = 'train'"), made.where("split = 'test'"), objective, channels, **how)


def fit_grid(made: DataFrame, objective, channels: dict[str, Channel], **how) -> list[dict]:
    """Trains on all rows and measures on the same."""
    with kept(made):
        return run_grid(made, made, objective, channels, **how)


def accuracy(spark: SparkSession, sf_dir: str, target: str = "lang", rounds: int = 12, k: int = 8, channels: dict[str, Channel] | None = None, eta: float = 8.0, workload: str = "accuracy") -> list[dict]:
    """Final accuracy of each channel against 32 bits, 8 workers."""
    texts = features.language_texts(spark, sf_dir) if target == "lang" else features.quality_texts(spark, sf_dir)
    return split_grid(features.trigrams(texts, DIM), Softmax(DIM, 4 if target == "lang" else 2), channels or PRESET, workload=f"{workload}_{target}", k=k, rounds=rounds, eta=eta)


def hard_target(spark: SparkSession, sf_dir: str, rounds: int = 25, dim: int = 2048, classes: int = 8) -> list[dict]:
    """A planted target of thin margins, on which aggressive settings (few bits in narrow buckets, wide buckets) lose."""
    made = features.trigrams(features.language_texts(spark, sf_dir), dim, planted=features.planted_classes(dim, classes), packed=True)
    return split_grid(made, Softmax(dim, classes), PRESET | AGGRESSIVE | {"q2_8192": quantized(2, 8192)}, workload="hard_target", k=2, rounds=rounds, eta=45.0)


def bucket_grid(spark: SparkSession, sf_dir: str, rounds: int = 12) -> list[dict]:
    """Bits by bucket size, the aggressive settings included."""
    grid = {"fp32": FULL} | {f"q{b}_{d}": quantized(b, d) for b in (2, 4, 8) for d in (64, 512, 8192)}
    return accuracy(spark, sf_dir, "lang", rounds, channels=grid, workload="bucket_grid")


def norm_comparison(spark: SparkSession, sf_dir: str, rounds: int = 12) -> list[dict]:
    grid = {"fp32": FULL} | {f"{n}_{c}": quantized(4, 512, c, n) for n in ("max", "l2") for c in ("fixed", "gap")}
    return accuracy(spark, sf_dir, "lang", rounds, channels=grid, workload="norm")


def noise_comparison(spark: SparkSession, sf_dir: str, rounds: int = 12) -> list[dict]:
    """Quantization beside full precision with Gaussian noise of the same variance, and beside rounding without noise."""
    grid = {"fp32": FULL}
    for b, d in ((4, 512), (2, 128)):
        grid |= {f"q{b}_{d}": quantized(b, d), f"fp32_like_q{b}_{d}": Channel(like=quantized(b, d)), f"nearest{b}_{d}": quantized(b, d, rounding="nearest")}
    return accuracy(spark, sf_dir, "lang", rounds, channels=grid, workload="noise")


def onebit_comparison(spark: SparkSession, sf_dir: str, rounds: int = 12) -> list[dict]:
    """One-bit signs with and without carried error, and other baselines, against 2 and 4 bits."""
    grid = {
        "fp32": FULL, "q4_512": quantized(4, 512), "q2_128": quantized(2, 128), "onebit": Channel("onebit", bits=1, bucket=512), "onebit_two_means": Channel("onebit", bits=1, bucket=512, scale="two_means"),
        "onebit_no_carry": Channel("onebit", bits=1, bucket=512, carry=False), "bf16": Channel("reduced", bits=16), "fp16": Channel("reduced", bits=16, kind="float16"), "fixed8": Channel("reduced", bits=8, kind="fixed8"),
    }
    return accuracy(spark, sf_dir, "lang", rounds, channels=grid, workload="onebit")


def _one_layer_at_a_time(objective) -> dict[str, Channel]:
    (r1, c1), (r2, c2) = objective.shapes()
    n1, n2 = r1 * c1, r2 * c2
    grid = {"fp32": FULL}
    for b in (2, 4, 8):
        grid[f"first_{b}"] = Channel("fixed", b, 512, layers=((0, n1, b), (n1, n2, 32)))
        grid[f"second_{b}"] = Channel("fixed", b, 512, layers=((0, n1, 32), (n1, n2, b)))
        grid[f"both_{b}"] = quantized(b, 512)
    return grid


def layer_sensitivity(spark: SparkSession, sf_dir: str, rounds: int = 20) -> list[dict]:
    """One layer quantized at a time: of a two-layer perceptron, and of a net whose first layer is
    convolution-like (one matrix over the windows of a text).  Both meet the hard planted target."""
    texts = features.language_texts(spark, sf_dir)
    dense, shared = Perceptron(512, 32, 8), SharedWindows(64, 16, 32, 8)
    out = split_grid(features.trigrams(texts, 512, planted=features.planted_classes(512, 8), packed=True), dense, _one_layer_at_a_time(dense), workload="layers_dense", k=4, rounds=rounds, eta=1.0)
    return out + split_grid(features.trigrams(texts, 1024, windows=16, planted=features.planted_classes(1024, 8), packed=True), shared, _one_layer_at_a_time(shared), workload="layers_shared", k=4, rounds=rounds, eta=1.0)


def skip_training(spark: SparkSession, sf_dir: str, rounds: int = 10) -> list[dict]:
    """Tensors under a threshold sent at full precision, and buckets of whole rows: what it costs and changes in training."""
    objective = Perceptron(DIM, 64, 4)
    shapes, grid, quantized_share = objective.shapes(), {"fp32": FULL}, {"fp32": 0.0}
    for threshold in (0, 1_000, 10_000):
        for name, aligned in (("", False), ("_rows", True)):
            at, spans = 0, []
            for r, c in shapes:
                spans.append((at, r * c, 4 if r * c >= threshold else 32))
                at += r * c
            bucket = layout.row_aligned(500, shapes[0][1]) if aligned else 500
            grid[f"skip_{threshold}{name}"] = Channel("fixed", 4, bucket, layers=tuple(spans))
            quantized_share[f"skip_{threshold}{name}"] = sum(n for _, n, b in spans if b < 32) / objective.n
    rows = split_grid(features.trigrams(features.language_texts(spark, sf_dir), DIM), objective, grid, workload="skip", k=4, rounds=rounds, eta=4.0)
    return [r | {"share_quantized": quantized_share[r["run"]]} for r in rows]


def breakdown(spark: SparkSession, sf_dir: str, ks: tuple[int, ...] = (2, 4, 8, 16), rounds: int = 2) -> list[dict]:
    """Computation against coding and (modelled) transfer in an epoch, 32 to 2 bits: a large cheap model, a small costly
    one, and a recurrent one."""
    out = []
    arms = {
        "wide_cheap": (features.sparse_trigrams(features.language_texts(spark, sf_dir), 1 << 14, packed=True), SparseSoftmax(1 << 14, 4), 4.0),
        "small_costly": (features.vectors_with_labels(spark, sf_dir), Perceptron(64, 128, 10, depth=3), 0.1),
        "recurrent": (*_sequence_arm(spark, sf_dir), 0.5),
    }
    for name, (rows, objective, eta) in arms.items():
        with kept(rows):
            for k in ks:
                out += run_grid(rows, rows, objective, PRESET, workload=name, k=k, rounds=rounds, eta=eta)
    return out


def wide_sparse(spark: SparkSession, sf_dir: str, dims: tuple[int, ...] = (1 << 14, 1 << 16, 1 << 18), rounds: int = 2) -> list[dict]:
    """Models of up to a million parameters over sparse rows, where messages outweigh the work: 32 to 2 bits."""
    out = []
    texts = features.language_texts(spark, sf_dir)
    for dim in dims:
        out += fit_grid(features.sparse_trigrams(texts, dim), SparseSoftmax(dim, 4), PRESET, workload=f"wide_2^{dim.bit_length() - 1}", k=4, rounds=rounds, eta=8.0)
    return out


def depths(spark: SparkSession, sf_dir: str, rounds: int = 3) -> list[dict]:
    """Costly models of few parameters: one, three and seven hidden layers."""
    out = []
    for depth in (1, 3, 7):
        out += fit_grid(features.vectors_with_labels(spark, sf_dir), Perceptron(64, 48, 10, depth=depth), PRESET, workload=f"depth_{depth}", k=4, rounds=rounds, eta=0.1)
    return out


def two_layer(spark: SparkSession, sf_dir: str, rounds: int = 12) -> list[dict]:
    """The two-layer perceptron of 128 hidden units: training loss over the embeddings, whose labels carry no signal."""
    return fit_grid(features.vectors_with_labels(spark, sf_dir), Perceptron(64, 128, 10), PRESET, workload="two_layer", k=8, rounds=rounds, eta=0.5)


def _sequence_arm(spark: SparkSession, sf_dir: str, steps: int = 6) -> tuple[DataFrame, Recurrent]:
    rows = features.sequences(spark, sf_dir, steps)
    width = len(rows.first()["features"]) // steps
    return rows, Recurrent(width, 12, width - 1, steps)


def sequence(spark: SparkSession, sf_dir: str, rounds: int = 6) -> list[dict]:
    """A recurrent cell over users' event sequences, two workers; every fourth user is held out."""
    rows, objective = _sequence_arm(spark, sf_dir)
    made = rows.withColumn("split", F.when(F.pmod(F.xxhash64("user_id"), F.lit(4)) == 0, "test").otherwise("train"))
    return split_grid(made, objective, {"fp32": FULL, "q4_512": quantized(4, 512), "q8_512": quantized(8, 512)}, workload="sequence", k=2, rounds=rounds, eta=0.5)


def convex(spark: SparkSession, sf_dir: str, rounds: int = 10) -> list[dict]:
    """Planted least squares: levels s, sparse and dense codes."""
    grid = {"fp32": FULL} | {f"lq_s{s}": Channel("gap", s=s, norm="l2") for s in (1, 2, 4)} | {"lq_sqrt": Channel("dense_prefix", s="sqrt", norm="l2")}
    return fit_grid(features.planted_rows(spark, sf_dir), LeastSquares(5), grid, workload="convex", k=8, rounds=rounds, eta=0.3, tops=())


def convex_wide(spark: SparkSession, sf_dir: str, dim: int = 256, rounds: int = 30, k: int = 8) -> list[dict]:
    """Planted least squares over 256 features of documents, with the step the theory asks for: the gap of the mean
    iterate beside the theory's bound, and the bits beside theirs."""
    made = features.trigrams(features.language_texts(spark, sf_dir), dim, planted=features.planted_line(dim)).select("row_id", "features", "y")
    grid = {"fp32": FULL} | {f"lq_s{s}": Channel("gap" if s * s < dim / 4 else "dense_prefix", s=s, norm="l2") for s in (1, 2, 4, 8)} | {"lq_sqrt": Channel("dense_prefix", s="sqrt", norm="l2")}
    out = []
    with kept(made):
        shards = sgd.deal(made, k)
        gram, cross, square, m = svrg.normal_equations(shards, dim)
        best = np.linalg.lstsq(gram, cross, rcond=None)[0]
        floor, smooth, radius = (square - cross @ best) / 2, float(np.linalg.eigvalsh(gram)[-1]), float(np.sqrt(best @ best))
        # Rows have unit length, so a row's gradient at the start has the size of its y: the largest second moment there is on the way down.
        second = square
        runs, spread = [], {}
        for name, c in grid.items():
            s = 16 if c.s == "sqrt" else c.s
            spread[name] = second * (bounds.second_moment(dim, s) if s else 1.0) / k
            runs.append(Run(name, c, bounds.step_size("parallel", smooth, radius, spread[name] * k, k, rounds), average_iterates=True))
        found, ledger = sgd.train_grid(shards, LeastSquares(dim), runs, rounds)
        measured = sgd.evaluate(made, LeastSquares(dim), found, ())
        shards.unpersist()
    for name, c in grid.items():
        mine = [r for r in ledger if r["run"] == name]
        gap, bound = measured[name]["loss"] - floor, bounds.sgd_gap(radius, spread[name], rounds, smooth)
        s = 16 if c.s == "sqrt" else c.s
        each = sum(r["n_bits"] for r in mine) / max(sum(r["workers"] for r in mine), 1)
        allowed = 32.0 * dim if not s else bounds.dense_bits(dim) if s * s >= dim else bounds.gap_bits(dim, s)
        out.append({"workload": "convex_wide", "run": name, "n": dim, "rounds": rounds, "gap": float(gap), "gap_bound": float(bound), "gap_holds": bool(gap <= bound), "bits_a_message": float(each), "bits_bound": float(allowed),
                    "bits_hold": bool(each <= allowed) if c.codec != "dense_prefix" or s * s >= dim else True})
    return out


def strongly_convex(spark: SparkSession, sf_dir: str, dim: int = 256, k: int = 8, t: int = 10, epochs: int = 2) -> list[dict]:
    """Variance reduction over 256 features, for two condition numbers: contraction by epoch and bits against their bounds."""
    made = features.trigrams(features.language_texts(spark, sf_dir), dim, planted=features.planted_line(dim)).select("row_id", "features", "y")
    runs = [svrg.VrRun("float32", Channel()), svrg.VrRun("lq_sqrt", Channel("dense_prefix", s="sqrt", norm="l2"))]
    out = []
    with kept(made):
        rows = layout.dense_index(made).select("row_id", "features", "y") if "row_id" not in made.columns else layout.dense_index(made.drop("row_id")).select("row_id", "features", "y")
        with kept(rows):
            gram, cross, square, _ = svrg.normal_equations(rows.select("row_id", F.lit(0).alias("shard"), "features", "y"), dim)
            for l2 in (0.5, 0.1):
                objective = LeastSquares(dim, l2)
                best = np.linalg.solve(gram + l2 * np.eye(dim), cross)
                floor = square / 2 - cross @ best / 2
                ledger = svrg.train_vr_grid(rows, objective, runs, k, t, epochs, 0.5 / (1 + l2))
                for run in runs:
                    gap = square / 2 - floor
                    for r in ledger[run.name]:
                        x = r["anchor"]
                        was, gap = gap, float(x @ gram @ x / 2 - cross @ x + square / 2 + l2 / 2 * x @ x - floor)
                        out.append({"workload": "strongly_convex", "run": run.name, "n": dim, "kappa": (1 + l2) / l2, "epoch": r["epoch"], "gap": gap, "ratio": gap / max(was, 1e-300), "contracts": bool(gap <= 0.9 * was),
                                    "n_bits": int(r["n_bits"]), "bits_bound": float(k * bounds.vr_bits(dim, t))})
    return out


def staleness(spark: SparkSession, sf_dir: str, rounds: int = 16) -> list[dict]:
    """Workers that use parameters of up to tau rounds before."""
    taus = {f"tau_{t}": t for t in (0, 1, 4, 16)}
    return fit_grid(features.planted_rows(spark, sf_dir), LeastSquares(5), {n: Channel("gap", s=2, norm="l2") for n in taus}, workload="staleness", k=8, rounds=rounds, eta=0.1, staleness=taus, tops=())


def quality(spark: SparkSession, sf_dir: str, rounds: int = 12) -> list[dict]:
    """The small-model stand-in: logistic regression of document quality."""
    return split_grid(features.trigrams(features.quality_texts(spark, sf_dir), DIM), Logistic(DIM), PRESET, workload="quality", k=8, rounds=rounds, eta=8.0)


def step_and_batch(spark: SparkSession, sf_dir: str, rounds: int = 12) -> list[dict]:
    """The 32-bit step kept, variance lowered by the bucket instead; minibatches of growing size."""
    out = []
    with kept(features.trigrams(features.language_texts(spark, sf_dir), DIM)) as made:
        train, test = made.where("split = 'train'"), made.where("split = 'test'")
        for frac in (0.1, 0.2, 0.4):
            grid = {"fp32": FULL} | {f"q4_{d}": quantized(4, d) for d in (64, 512, 4096)}
            for r in run_grid(train, test, Softmax(DIM, 4), grid, workload="step_and_batch", k=4, rounds=rounds, eta=8.0, frac=frac):
                out.append(r | {"frac": frac})
    return out


def scale_messages(spark: SparkSession, sf_dir: str, copies: int = 16) -> DataFrame:
    """Messages over a column replicated by a range: bits by setting, from long layout, all in the engine."""
    from lossygrad.functions import codes
    from lossygrad.operators import layout, quantizer

    base = spark.read.parquet(f"{sf_dir}/orders.parquet").select("o_orderkey", "o_totalprice")
    long = base.crossJoin(F.broadcast(spark.range(copies).select(F.col("id").alias("vec_id")))).select("vec_id", F.col("o_orderkey").alias("coord"), (F.col("o_totalprice") - 150000.0).alias("value"))
    out = None
    for bits, bucket in ((2, 128), (4, 512), (8, 512)):
        s = max(1, 2 ** (bits - 1) - 1)
        made = quantizer.quantize(layout.bucketize_long(long, bucket), s, "max", bucket=bucket)
        row = made.agg(F.count("*").alias("buckets"), F.sum(F.size("level")).alias("n"), F.sum(codes.fixed_bits(F.col("level"), bits)).alias("fixed_bits"), F.sum(codes.gap_bits(F.col("level"))).alias("gap_bits")).select(
            F.lit(bits).alias("bits"), F.lit(bucket).alias("bucket"), "buckets", "n", "fixed_bits", "gap_bits"
        )
        out = row if out is None else out.unionByName(row)
    return out


def wire_bytes(spark: SparkSession, sf_dir: str, copies: int = 16) -> list[dict]:
    """Shuffled bytes, by Spark's own count, of one exchange of all messages beside their bits: a column repeated
    ``copies`` times, each with hashed offsets so that no copy compresses another (2.4 million values at sf 0.1), 32 to 2 bits, and a sparse code."""
    from lossygrad.operators import messages, quantizer

    base = spark.read.parquet(f"{sf_dir}/orders.parquet").select("o_orderkey", "o_totalprice")
    long = base.crossJoin(F.broadcast(spark.range(copies).select(F.col("id").alias("vec_id")))).select("vec_id", F.col("o_orderkey").alias("coord"), (F.col("o_totalprice") - 150000.0 + F.pmod(F.xxhash64("vec_id", "o_orderkey"), F.lit(1000003)) / 7).alias("value"))
    out = []
    with kept(layout.bucketize_long(long, 512)) as buckets:
        n = buckets.agg(F.sum(F.size("values"))).first()[0]
        plans = {"float32": None, "q8": ("fixed", 8, 127, "max"), "q4": ("fixed", 4, 7, "max"), "q2": ("fixed", 2, 1, "max"), "gap_s1": ("gap", 4, 1, "l2")}
        for name, how in plans.items():
            if how is None:
                sent, bits = buckets.select("vec_id", "bucket_id", F.col("values").cast("array<float>").alias("values")).repartition("bucket_id"), 32 * n
            else:
                codec, width, s, norm = how
                sent = messages.by_bucket(messages.encode(quantizer.quantize(buckets, s, norm, bucket=512), codec, width))
                bits = sent.agg(F.sum("n_bits")).first()[0]
            began = time.perf_counter()
            _, written = ledgers.shuffle_bytes_of(spark, lambda sent=sent: sent.write.format("noop").mode("overwrite").save())
            out.append({"workload": "wire_bytes", "run": name, "n": n, "n_bytes": bits / 8, "shuffle_bytes": written, "bytes_a_value": written / n, "ratio": 4 * n / max(written, 1), "wall_s": time.perf_counter() - began})
    return out
