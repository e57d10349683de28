"""Variance-reduced descent with lossy corrections.

Epoch: the exact gradient at an anchor (full precision, one pass over the data), then T
rounds in which each worker sends the quantized difference of one row's gradients at the
iterate and at the anchor, plus the anchor's gradient; the next anchor is the mean of
the inner iterates.  ``train_vr_grid`` runs it over a DataFrame: corrections are made and
encoded by the workers' tasks.  ``simulate`` runs the same steps over arrays in one process.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from lossygrad.session import map_arrow
from lossygrad.functions.uniform import uniform_array
from lossygrad.optim.channel import Channel, State
from lossygrad.optim.sgd import _KINDS, _MESSAGE, DRIVER_PARAMETERS, _arrays, sum_messages


def draws(m: int, k: int, t: int, epoch: int, seed: int, sampling: str = "global") -> np.ndarray:
    """Row numbers (t, k): of all rows, or of each worker's contiguous shard (``local``)."""
    u = uniform_array(t * k, seed, 13, epoch).reshape(t, k)
    if sampling == "global":
        return (u * m).astype(np.int64)
    if sampling == "local":
        low = np.array([m * i // k for i in range(k)])
        high = np.array([m * (i + 1) // k for i in range(k)])
        return (low + u * (high - low)).astype(np.int64)
    raise ValueError(f"unknown sampling {sampling}")


def inner(objective, y_anchor: np.ndarray, full: np.ndarray, rows: Callable[[int, int], tuple[np.ndarray, np.ndarray]], channel: Channel, t: int, k: int, eta: float,
          epoch: int, naive: bool = False, states: State | None = None) -> tuple[np.ndarray, int]:
    """The mean of an epoch's inner iterates, and the bits its messages took.

    ``naive`` quantizes the plain difference and adds the anchor's gradient outside.
    """
    x, mean, bits = y_anchor.copy(), np.zeros(len(y_anchor)), 0
    states = states or State()
    for r in range(t):
        total = np.zeros(len(x))
        for i in range(k):
            a, b = rows(r, i)
            diff = objective.grad(x, a, b) - objective.grad(y_anchor, a, b)
            sent, n = channel.send(diff if naive else diff + full, epoch, r, i, state=states.of(i))
            total += sent + full if naive else sent
            bits += n
        x = x - eta * total / k
        mean += (x - mean) / (r + 1)
    return mean, bits


def simulate(objective, a: np.ndarray, y: np.ndarray, channel: Channel, k: int, t: int, epochs: int, eta: float, seed: int = 0, sampling: str = "global", naive: bool = False,
             evaluate: Callable[[int, np.ndarray], dict] | None = None) -> tuple[np.ndarray, list[dict]]:
    anchor, out, states = objective.init(seed), [], State()
    for p in range(epochs):
        full = objective.grad(anchor, a, y)
        at = draws(len(y), k, t, p, seed, sampling)
        anchor, bits = inner(objective, anchor, full, lambda r, i, at=at: (a[at[r, i]][None], y[at[r, i]][None]), channel, t, k, eta, p, naive, states)
        # The anchor's gradient goes out at full precision from every worker.
        out.append({"epoch": p + 1, "n_bits": bits + 32 * len(anchor) * k} | (evaluate(p, anchor) if evaluate else {}))
    return anchor, out


def anchor_gradients(shards: DataFrame, objective, xs: list[np.ndarray]) -> tuple[list[np.ndarray], int]:
    """Exact mean gradients at each of ``xs`` over all rows, and the rows' count: one pass, one sum a task, added up by coordinate."""
    if sum(map(len, xs)) > DRIVER_PARAMETERS:
        raise ValueError("too many parameters for the driver")
    sent = shards.sparkSession.sparkContext.broadcast(xs)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        totals, m = [np.zeros(objective.n) for _ in sent.value], 0
        for batch in batches:
            if batch.num_rows:
                _, _, a, y = _arrays(batch)
                for total, x in zip(totals, sent.value, strict=True):
                    total += objective.grad(x, a, y) * len(y)
                m += len(y)
        flat = np.concatenate([*totals, [m]])
        yield pa.RecordBatch.from_arrays([pa.array(np.arange(len(flat))), pa.array(flat)], names=["coord", "value"])

    rows = map_arrow(shards, run, "coord bigint, value double").groupBy("coord").agg(F.sum("value").alias("value")).orderBy("coord").collect()
    values = np.array([r["value"] for r in rows])
    return list(values[:-1].reshape(len(xs), -1) / max(values[-1], 1)), int(values[-1])


def anchor_gradient(shards: DataFrame, objective, x: np.ndarray) -> tuple[np.ndarray, int]:
    (g,), m = anchor_gradients(shards, objective, [x])
    return g, m


def normal_equations(shards: DataFrame, dim: int) -> tuple[np.ndarray, np.ndarray, float, int]:
    """Mean of a a', of a y, of y squared, and the rows' count, over all rows: one sum a task, added up by coordinate."""
    if dim * dim > DRIVER_PARAMETERS:
        raise ValueError("too many parameters for the driver")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        gram, cross, square, m = np.zeros((dim, dim)), np.zeros(dim), 0.0, 0
        for batch in batches:
            if batch.num_rows:
                _, _, a, y = _arrays(batch)
                gram, cross, square, m = gram + a.T @ a, cross + a.T @ y, square + float(y @ y), m + len(y)
        flat = np.concatenate([gram.ravel(), cross, [square, m]])
        yield pa.RecordBatch.from_arrays([pa.array(np.arange(len(flat))), pa.array(flat)], names=["coord", "value"])

    rows = map_arrow(shards, run, "coord bigint, value double").groupBy("coord").agg(F.sum("value").alias("value")).orderBy("coord").collect()
    values = np.array([r["value"] for r in rows])
    m = max(values[-1], 1)
    return values[: dim * dim].reshape(dim, dim) / m, values[dim * dim : -2] / m, values[-2] / m, int(values[-1])


@dataclass(frozen=True)
class VrRun:
    """One configuration; runs of a grid share the draws, the passes and the jobs."""

    name: str
    channel: Channel
    naive: bool = False


def corrections(drawn: DataFrame, objective, runs: list[VrRun], xs: list[np.ndarray], anchors: list[np.ndarray], fulls: list[np.ndarray], epoch: int, r: int) -> DataFrame:
    """Messages of a round: each worker's task takes its drawn row, makes the correction and encodes it."""
    sent = drawn.sparkSession.sparkContext.broadcast((xs, anchors, fulls))

    def run_(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        xs, anchors, fulls = sent.value
        rows = []
        for batch in batches:
            if not batch.num_rows:
                continue
            _, workers, a, y = _arrays(batch)
            for i, w in enumerate(workers.tolist()):
                for j, run in enumerate(runs):
                    v = objective.grad(xs[j], a[i : i + 1], y[i : i + 1]) - objective.grad(anchors[j], a[i : i + 1], y[i : i + 1])
                    parts = run.channel.parts(v if run.naive else v + fulls[j], epoch, r, w)
                    rows += [(j, w, b, first, n, s, codec, bits, payload, 0, 0.0, 0.0, 0.0) for b, first, n, s, codec, bits, _, _, payload in parts]
        columns = list(zip(*rows, strict=True)) or [[]] * len(_KINDS)
        yield pa.RecordBatch.from_arrays([pa.array(list(c), t) for c, t in zip(columns, _KINDS, strict=True)], names=[c.split()[0] for c in _MESSAGE.split(", ")])

    return map_arrow(drawn.where(F.col("round") == r).select("row_id", "shard", "features", "y"), run_, _MESSAGE)


def train_vr_grid(data: DataFrame, objective, runs: list[VrRun], k: int, t: int, epochs: int, eta: float, seed: int = 0, sampling: str = "global") -> dict[str, list[dict]]:
    """A ledger row (epoch, n_bits, anchor) for each run and epoch, over a DataFrame whose row_id runs from 0 to m - 1.

    An epoch is one pass for the anchors' gradients, one join that deals the drawn rows to their
    workers, and t rounds of one job each: corrections are encoded by the workers' tasks, payloads
    cross one exchange, and their sums (n floats a run) come to the driver.
    """
    if any(r.channel.whole for r in runs):
        raise ValueError("corrections are sent quantized or at full precision")
    if objective.n * len(runs) > DRIVER_PARAMETERS:
        raise ValueError("too many parameters for the driver")
    spark = data.sparkSession
    anchors, out = [objective.init(seed) for _ in runs], {r.name: [] for r in runs}
    shards = data.select("row_id", F.lit(0).alias("shard"), "features", F.col("y").cast("double").alias("y")).persist()
    try:
        for p in range(epochs):
            fulls, m = anchor_gradients(shards, objective, anchors)
            at = draws(m, k, t, p, seed, sampling)
            wanted = spark.createDataFrame([(int(at[r, i]), r, i) for r in range(t) for i in range(k)], "row_id bigint, round int, worker int")  # t x k rows, known to the driver
            drawn = shards.join(F.broadcast(wanted), "row_id").select("row_id", F.col("worker").alias("shard"), "features", "y", "round").repartition(k, "shard").persist()
            xs, means, bits = [x.copy() for x in anchors], [np.zeros(objective.n) for _ in runs], [0] * len(runs)
            for r in range(t):
                sums = sum_messages(corrections(drawn, objective, runs, xs, anchors, fulls, p, r), runs).collect()
                for j, run in enumerate(runs):
                    g = k * fulls[j] if run.naive else np.zeros(objective.n)
                    for x in sums:
                        if x["run"] == j:
                            g[x["first"] : x["first"] + len(x["total"])] += x["total"]
                            bits[j] += x["n_bits"]
                    xs[j] = xs[j] - eta * g / k
                    means[j] += (xs[j] - means[j]) / (r + 1)
            drawn.unpersist()
            anchors = means
            for j, run in enumerate(runs):
                # The anchor's gradient goes out at full precision from every worker.
                out[run.name].append({"epoch": p + 1, "n_bits": bits[j] + 32 * objective.n * k, "anchor": anchors[j]})
    finally:
        shards.unpersist()
    return out


def train_vr(data: DataFrame, objective, channel: Channel, k: int, t: int, epochs: int, eta: float, seed: int = 0, sampling: str = "global", naive: bool = False) -> tuple[np.ndarray, list[dict]]:
    ledger = train_vr_grid(data, objective, [VrRun("run", channel, naive)], k, t, epochs, eta, seed, sampling)["run"]
    return (ledger[-1]["anchor"] if ledger else objective.init(seed)), ledger
