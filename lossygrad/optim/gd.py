"""Full-gradient descent, exact or with the gradient truncated to its largest values."""

from __future__ import annotations

from collections.abc import Callable

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from lossygrad.optim.channel import Channel, State
from lossygrad.optim.svrg import anchor_gradient


def simulate(objective, a: np.ndarray, y: np.ndarray, channel: Channel, rounds: int, eta: float, seed: int = 0, evaluate: Callable[[int, np.ndarray], dict] | None = None) -> tuple[np.ndarray, list[dict]]:
    x, out, states = objective.init(seed), [], State()
    for t in range(rounds):
        sent, bits = channel.send(objective.grad(x, a, y), t, 0, state=states.of(0))
        x = x - eta * sent
        out.append({"round": t + 1, "n_bits": bits} | (evaluate(t, x) if evaluate else {}))
    return x, out


def train_gd(data: DataFrame, objective, channel: Channel, rounds: int, eta: float, seed: int = 0) -> tuple[np.ndarray, list[dict]]:
    shards = data.select("row_id", F.lit(0).alias("shard"), "features", F.col("y").cast("double").alias("y")).persist()
    x, out, states = objective.init(seed), [], State()
    try:
        for t in range(rounds):
            g, _ = anchor_gradient(shards, objective, x)
            sent, bits = channel.send(g, t, 0, state=states.of(0))
            x = x - eta * sent
            out.append({"round": t + 1, "n_bits": bits})
    finally:
        shards.unpersist()
    return x, out
