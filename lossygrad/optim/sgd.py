"""Parallel stochastic descent with lossy messages.

``train`` (and ``train_grid``, for many configurations in the same passes) runs it over a
DataFrame: shards are dealt once and kept; each round is one job in which a worker's task adds up its minibatch gradient and encodes it in the same
pass, the encoded buckets cross one shuffle, and the owner of a bucket decodes and adds
them.  Only the summed vector (n floats) comes to the driver, which steps and projects.

``simulate`` runs the same steps for K logical workers over arrays in one process, for
sweeps of many configurations (one a task), staleness and non-convex stopping.
"""

from __future__ import annotations

import time
from collections.abc import Callable, Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark import StorageLevel
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from lossygrad.session import map_arrow
from lossygrad.functions.uniform import _mix, uniform_array
from lossygrad.optim.channel import Channel, State
from lossygrad.optim.objectives import SparseRows, losses_and_grads, measure
from lossygrad.sources import features as rows_of

#: Parameters that the driver may hold and send to every worker (floats).
DRIVER_PARAMETERS = 10_000_000
#: Values of a slice of rows.
SLICE = 1 << 16


def project(x: np.ndarray, kind: str | None = None, radius: float = 1.0) -> np.ndarray:
    """Onto nothing, a box, or a 2-ball."""
    if kind is None:
        return x
    if kind == "box":
        return np.clip(x, -radius, radius)
    if kind == "ball":
        n = float(np.sqrt(x @ x))
        return x if n <= radius else x * (radius / n)
    raise ValueError(f"unknown set {kind}")


def picked(row_ids: np.ndarray, frac: float, step: int, seed: int) -> np.ndarray:
    """Rows of the minibatch of a step: by a hash of the row, so a retry picks the same."""
    if frac >= 1:
        return np.ones(len(row_ids), bool)
    with np.errstate(over="ignore"):
        salt = _mix(np.uint64(seed * 1_000_003 + step + 1) * np.uint64(0x9E3779B97F4A7C15))
        h = _mix(row_ids.astype(np.uint64) ^ salt)
    return (h >> np.uint64(11)) / float(1 << 53) < frac


def deal(data: DataFrame, k: int) -> DataFrame:
    """row_id, features, y and shard, a shard a partition where Spark can do so by id; kept for the rounds."""
    keyed = data if "shard" in data.columns else data.withColumn("shard", F.pmod(F.xxhash64("row_id"), F.lit(k)).cast("int"))
    keyed = keyed.select("row_id", "shard", "features", F.col("y").cast("double").alias("y"))
    dealt = keyed.repartitionById(k, F.col("shard")) if hasattr(keyed, "repartitionById") else keyed.repartition(k, "shard")
    return dealt.persist(StorageLevel.MEMORY_AND_DISK)


def _arrays(batch: pa.RecordBatch) -> tuple:
    """row_id, shard, features (a matrix, or sparse rows where the column holds places and values; packed ones unpacked) and y."""
    column = batch.column("features")
    names = [f.name for f in column.type] if pa.types.is_struct(column.type) else []
    if "wide" in names:
        features = SparseRows(*rows_of.unpacked_sparse(column))
    elif "counts" in names:
        features = rows_of.unpacked(column)
    elif names:
        at, value = column.field(0), column.field(1)
        bounds = at.offsets.to_numpy().astype(np.int64)
        features = SparseRows(bounds - bounds[0], at.flatten().to_numpy(zero_copy_only=False), value.flatten().to_numpy(zero_copy_only=False))
    else:
        features = column.flatten().to_numpy(zero_copy_only=False).reshape(batch.num_rows, -1)
    return batch.column("row_id").to_numpy(zero_copy_only=False), batch.column("shard").to_numpy(zero_copy_only=False), features, batch.column("y").to_numpy(zero_copy_only=False)


def _slices(batch: pa.RecordBatch) -> Iterator[tuple]:
    """As ``_arrays``, by few rows at a time, which stay in the processor's caches; batches may be large and packed."""
    if not batch.num_rows:
        return
    first = _arrays(batch.slice(0, 1))[2]
    step = 1024 if isinstance(first, SparseRows) else max(128, SLICE // max(first.shape[1], 1))
    for at in range(0, batch.num_rows, step):
        yield _arrays(batch.slice(at, step))


@dataclass(frozen=True)
class Run:
    """One configuration of a training run; runs of a grid share the data and its passes."""

    name: str
    channel: Channel
    eta: float | Callable[[int], float]
    frac: float = 1.0
    seed: int = 0
    staleness: int = 0
    average_iterates: bool = False
    projection: tuple[str, float] | None = None


_MESSAGE = "run int, shard int, bucket_id bigint, first bigint, n int, s int, codec string, n_bits bigint, payload binary, rows bigint, loss double, comp_s double, codec_s double"
_KINDS = [pa.int32(), pa.int32(), pa.int64(), pa.int64(), pa.int32(), pa.int32(), pa.string(), pa.int64(), pa.binary(), pa.int64(), pa.float64(), pa.float64(), pa.float64()]
_SUM = "run int, bucket_id bigint, first bigint, total array<double>, n_messages int, n_bits bigint, rows bigint, loss double, comp_s double, codec_s double, carried array<struct<shard:int,e:array<double>>>"
#: A message of a run whose worker carries an error has it in a bucket of this number.
_CARRIED = -1


def _version(x_list: list[np.ndarray], run: Run, step: int, worker: int) -> np.ndarray:
    """The parameters a worker sees: the latest, or those of up to ``staleness`` rounds before."""
    back = int(uniform_array(1, run.seed, 991, step, worker)[0] * (min(run.staleness, len(x_list) - 1) + 1)) if run.staleness else 0
    return x_list[-1 - back]


def round_messages(shards: DataFrame, objective, runs: list[Run], versions: list[list[np.ndarray]], carried: list[dict], step: int) -> DataFrame:
    """Encoded gradients of every worker and run: gradient and encoding in one pass over the shard."""
    sent = shards.sparkSession.sparkContext.broadcast((versions, carried))

    def run_(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        versions, carried = sent.value
        sums: dict[tuple[int, int], list] = {}
        same = [[v.tobytes() for v in of_run] for of_run in versions]
        draws: dict[tuple[float, int], list[int]] = {}
        for j, r in enumerate(runs):
            draws.setdefault((1.0, 0) if r.frac >= 1 else (r.frac, r.seed), []).append(j)
        for ids, owner, a, y in (part for batch in batches for part in _slices(batch)):
            for (frac, seed), members in draws.items():
                use = picked(ids, frac, step, seed)
                for w in np.unique(owner[use]).tolist():
                    mine = use & (owner == w)
                    m = int(mine.sum())
                    x_of = {j: _version(versions[j], runs[j], step, w) for j in members}
                    # Runs whose parameters are (still) alike share a gradient.
                    alike: dict[bytes, list[int]] = {}
                    for j in members:
                        alike.setdefault(next(s for s, v in zip(same[j], versions[j], strict=True) if v is x_of[j]), []).append(j)
                    few = (a, y) if m == len(y) else (a[mine], y[mine])
                    clock = time.perf_counter()
                    found = losses_and_grads(objective, [x_of[js[0]] for js in alike.values()], *few)
                    spent = (time.perf_counter() - clock) / len(found)
                    for js, (loss, g) in zip(alike.values(), found, strict=True):
                        for j in js:
                            have = sums.setdefault((j, w), [np.zeros(len(g)), 0, 0.0, 0.0])
                            have[0] += g * m
                            have[1] += m
                            have[2] += loss * m
                            have[3] += spent
        rows = []
        for (j, w), (g, m, loss, comp) in sorted(sums.items()):
            channel = runs[j].channel
            clock = time.perf_counter()
            if channel.whole:
                state = {"e": carried[j][w]} if w in carried[j] else {}
                v, bits = channel.send(g / m, step, w, state=state)
                code, kept, payload = channel.payload(v)
                made = [(0, 0, len(v), kept, code, bits, payload)]
                if "e" in state:
                    made.append((_CARRIED, 0, len(v), 0, "float64", 0, state["e"].astype("<f8").tobytes()))
            else:
                made = [(b, first, n, s, codec, bits, payload) for b, first, n, s, codec, bits, _, _, payload in channel.parts(g / m, step, w)]
            spent = time.perf_counter() - clock
            for i, (b, first, n, s, codec, bits, payload) in enumerate(made):
                once = (m, loss, comp, spent) if not i else (0, 0.0, 0.0, 0.0)
                rows.append((j, w, b, first, n, s, codec, bits, payload, *once))
        columns = list(zip(*rows, strict=True)) or [[]] * len(_KINDS)
        names = [c.split()[0] for c in _MESSAGE.split(", ")]
        yield pa.RecordBatch.from_arrays([pa.array(list(c), t) for c, t in zip(columns, _KINDS, strict=True)], names=names)

    return map_arrow(shards, run_, _MESSAGE)


def sum_messages(messages: DataFrame, runs: list[Run]) -> DataFrame:
    """Decoded sums by run and bucket: payloads cross the shuffle, floats don't."""

    def run_(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        sums: dict[tuple[int, int], list] = {}
        for batch in batches:
            for r in batch.to_pylist():
                have = sums.setdefault((r["run"], r["bucket_id"]), [r["first"], np.zeros(r["n"]), 0, 0, 0, 0.0, 0.0, 0.0, []])
                clock = time.perf_counter()
                if r["bucket_id"] == _CARRIED:
                    have[8].append({"shard": r["shard"], "e": np.frombuffer(r["payload"], "<f8").tolist()})
                else:
                    have[1] += runs[r["run"]].channel.restore(r["codec"], r["payload"], r["n"], r["n_bits"], r["s"])
                    have[2] += 1
                have[7] += r["codec_s"] + time.perf_counter() - clock
                for i, c in ((3, "n_bits"), (4, "rows"), (5, "loss"), (6, "comp_s")):
                    have[i] += r[c]
        keys = list(sums)
        v = list(sums.values())
        yield pa.RecordBatch.from_arrays(
            [
                pa.array([k[0] for k in keys], pa.int32()), pa.array([k[1] for k in keys], pa.int64()), pa.array([x[0] for x in v], pa.int64()),
                pa.array([x[1].tolist() for x in v], pa.list_(pa.float64())), pa.array([x[2] for x in v], pa.int32()), pa.array([x[3] for x in v], pa.int64()),
                pa.array([x[4] for x in v], pa.int64()), *(pa.array([x[i] for x in v], pa.float64()) for i in (5, 6, 7)),
                pa.array([x[8] for x in v], pa.list_(pa.struct([("shard", pa.int32()), ("e", pa.list_(pa.float64()))]))),
            ],
            names=["run", "bucket_id", "first", "total", "n_messages", "n_bits", "rows", "loss", "comp_s", "codec_s", "carried"],
        )

    ordered = messages.repartition("run", "bucket_id").sortWithinPartitions("run", "bucket_id", "shard")
    return map_arrow(ordered, run_, _SUM)


def train_grid(shards: DataFrame, objective, runs: list[Run], rounds: int, start: np.ndarray | None = None) -> tuple[dict[str, np.ndarray], list[dict]]:
    """Parameters by run, and a ledger row for each run and round, over dealt ``shards``.

    One job a round for all runs.  Workers count alike in the mean, whatever rows their minibatches
    have, as in the method; hashes deal shards of nearly equal size.  Parameters and carried errors pass through the driver,
    up to ``DRIVER_PARAMETERS`` floats; beyond, ``optim.table`` keeps them as a table by bucket.
    """
    if objective.n * len(runs) > DRIVER_PARAMETERS:
        raise ValueError("too many parameters for the driver; optim.table.train_table keeps them as a table")
    versions = [[objective.init(r.seed) if start is None else start.copy()] for r in runs]
    means, carried, ledger = [np.zeros(objective.n) for _ in runs], [{} for _ in runs], []
    for t in range(rounds):
        began = time.perf_counter()
        rows = sum_messages(round_messages(shards, objective, runs, versions, carried, t), runs).collect()
        wall = time.perf_counter() - began
        for j, r in enumerate(runs):
            mine = [x for x in rows if x["run"] == j]
            workers = max((x["n_messages"] for x in mine), default=0)
            g = np.zeros(objective.n)
            for x in mine:
                if x["bucket_id"] == _CARRIED:
                    carried[j] |= {c["shard"]: np.array(c["e"]) for c in x["carried"]}  # a worker without rows this round keeps its own
                    if objective.n * len(carried[j]) > DRIVER_PARAMETERS:
                        raise ValueError("too many carried errors for the driver")
                else:
                    g[x["first"] : x["first"] + len(x["total"])] = x["total"]
            now = versions[j][-1]
            if workers:
                now = project(now - (r.eta(t) if callable(r.eta) else r.eta) * g / workers, *(r.projection or (None,)))
            versions[j] = [*versions[j], now][-(r.staleness + 1) :]
            means[j] += (now - means[j]) / (t + 1)
            seen = sum(x["rows"] for x in mine)
            ledger.append({
                "run": r.name, "round": t + 1, "workers": workers, "n_bits": sum(x["n_bits"] for x in mine), "loss": sum(x["loss"] for x in mine) / seen if seen else float("nan"),
                "comp_s": sum(x["comp_s"] for x in mine), "codec_s": sum(x["codec_s"] for x in mine), "wall_s": wall,
            })
    return {r.name: means[j] if r.average_iterates else versions[j][-1] for j, r in enumerate(runs)}, ledger


def train(data: DataFrame, objective, channel: Channel, k: int, rounds: int, eta: float | Callable[[int], float], frac: float = 1.0, seed: int = 0, average_iterates: bool = False,
          projection: tuple[str, float] | None = None, staleness: int = 0, start: np.ndarray | None = None) -> tuple[np.ndarray, list[dict]]:
    """Parameters and a ledger row for each round, over row_id, features and y."""
    shards = deal(data, k)
    try:
        found, ledger = train_grid(shards, objective, [Run("run", channel, eta, frac, seed, staleness, average_iterates, projection)], rounds, start)
    finally:
        shards.unpersist()
    return found["run"], ledger


def evaluate(data: DataFrame, objective, parameters: dict[str, np.ndarray], ks: tuple[int, ...] = (1,)) -> dict[str, dict]:
    """Mean loss and top-k accuracies of each run over row_id, features and y; one pass."""
    sent = data.sparkSession.sparkContext.broadcast(parameters)
    names = list(parameters)

    def run_(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        sums, xs = np.zeros((len(names), 2 + len(ks))), [sent.value[name] for name in names]
        for _, _, a, y in (part for batch in batches for part in _slices(batch)):
            sums[:, 0] += len(y)
            for j, found in enumerate(measure(objective, xs, a, y, ks)):
                sums[j, 1 : 1 + len(found)] += np.array(found) * len(y)
        cells = [(j, i, v) for j in range(len(names)) for i, v in enumerate(sums[j])]
        yield pa.RecordBatch.from_arrays([pa.array([c[0] for c in cells], pa.int32()), pa.array([c[1] for c in cells], pa.int32()), pa.array([c[2] for c in cells], pa.float64())], names=["run", "cell", "value"])

    rows = data.select("row_id", F.lit(0).alias("shard"), "features", F.col("y").cast("double").alias("y"))
    got = {(r["run"], r["cell"]): r["value"] for r in map_arrow(rows, run_, "run int, cell int, value double").groupBy("run", "cell").agg(F.sum("value").alias("value")).collect()}
    out = {}
    for j, name in enumerate(names):
        m = max(got.get((j, 0), 0.0), 1.0)
        out[name] = {"rows": int(got.get((j, 0), 0)), "loss": got.get((j, 1), 0.0) / m} | {f"top{k}": got.get((j, 2 + i), 0.0) / m for i, k in enumerate(ks)}
    return out


def simulate(objective, a: np.ndarray, y: np.ndarray, channel: Channel, k: int, rounds: int, eta: float | Callable[[int], float], batch: int = 32, seed: int = 0,
             staleness: int = 0, projection: tuple[str, float] | None = None, average_iterates: bool = False, stop: str | None = None,
             evaluate: Callable[[int, np.ndarray], dict] | None = None, every: int = 1) -> tuple[np.ndarray, list[dict]]:
    """K logical workers over arrays.  Worker i draws its minibatch from its contiguous shard;
    with ``staleness`` it uses the parameters of up to that many rounds before.

    ``stop='random'`` returns the iterate of a round drawn uniformly, as the non-convex
    guarantee has it.
    """
    x = objective.init(seed)
    history, states, rows = [x], State(), []
    bounds = [len(y) * i // k for i in range(k + 1)]
    mean, wanted = np.zeros(len(x)), int(uniform_array(1, seed, 77)[0] * rounds) if stop == "random" else -1
    stopped = x
    for t in range(rounds):
        g, bits, comm, comp = np.zeros(len(x)), 0, 0.0, 0.0
        for i in range(k):
            size = bounds[i + 1] - bounds[i]
            if not size:
                continue
            at = bounds[i] + (uniform_array(batch, seed, t, i) * size).astype(int)
            back = int(uniform_array(1, seed, 991, t, i)[0] * (min(staleness, t) + 1)) if staleness else 0
            clock = time.perf_counter()
            mine = objective.grad(history[-1 - back], a[at], y[at])
            comp += time.perf_counter() - clock
            clock = time.perf_counter()
            sent, n = channel.send(mine, t, i, state=states.of(i))
            comm += time.perf_counter() - clock
            g, bits = g + sent, bits + n
        x = project(x - (eta(t) if callable(eta) else eta) * g / k, *(projection or (None,)))
        history = (history + [x])[-(staleness + 1) :]
        mean += (x - mean) / (t + 1)
        if t == wanted:
            stopped = x
        if evaluate is not None and (t % every == every - 1 or t == rounds - 1):
            rows.append({"round": t + 1, "n_bits": bits, "codec_s": comm, "comp_s": comp} | evaluate(t, mean if average_iterates else x))
    return (stopped if stop == "random" else mean if average_iterates else x), rows
