"""Objectives with one contract: ``loss(x, a, y)`` and ``grad(x, a, y)``, means over rows of a.

Some have ``both`` (loss and gradient from one forward pass) or ``many`` (those of several parameter
vectors over the same rows); ``losses_and_grads`` and ``measure`` use them where they are.
"""

from __future__ import annotations

from dataclasses import dataclass
from typing import ClassVar

import numpy as np


def _softmax(z: np.ndarray) -> np.ndarray:
    z = np.exp(z - z.max(axis=1, keepdims=True))
    return z / z.sum(axis=1, keepdims=True)


def _tanh(z: np.ndarray) -> np.ndarray:
    """In place, by exp, which takes half the time of np.tanh and differs by a few units of 1e-16."""
    np.clip(z, -20, 20, out=z)
    z *= 2
    np.exp(z, out=z)
    z += 1
    np.divide(-2, z, out=z)
    z += 1
    return z


def cross_entropy(p: np.ndarray, y: np.ndarray) -> float:
    return float(-np.log(np.maximum(p[np.arange(len(y)), y.astype(int)], 1e-300)).mean())


def _down(p: np.ndarray, y: np.ndarray) -> np.ndarray:
    """The mean loss by score, from probabilities, which it changes."""
    p[np.arange(len(y)), y.astype(int)] -= 1
    return p / len(y)


@dataclass(frozen=True)
class LeastSquares:
    """Half squared error, with an L2 penalty (ridge) if ``l2`` is positive."""

    dim: int
    l2: float = 0.0

    @property
    def n(self) -> int:
        return self.dim

    def init(self, seed: int = 0) -> np.ndarray:
        return np.zeros(self.dim)

    def loss(self, x, a, y) -> float:
        r = a @ x - y
        return float(r @ r) / (2 * len(y)) + self.l2 / 2 * float(x @ x)

    def grad(self, x, a, y) -> np.ndarray:
        return a.T @ (a @ x - y) / len(y) + self.l2 * x

    def smoothness(self, a) -> tuple[float, float]:
        """(L of the worst row, strong convexity of the mean)."""
        low = float(np.linalg.eigvalsh(a.T @ a / len(a))[0])
        return float((a * a).sum(1).max()) + self.l2, max(low, 0.0) + self.l2

    def optimum(self, a, y) -> np.ndarray:
        return np.linalg.lstsq(a.T @ a / len(y) + self.l2 * np.eye(self.dim), a.T @ y / len(y), rcond=None)[0]


@dataclass(frozen=True)
class Logistic:
    """Labels 0 and 1."""

    dim: int
    l2: float = 0.0

    @property
    def n(self) -> int:
        return self.dim

    def init(self, seed: int = 0) -> np.ndarray:
        return np.zeros(self.dim)

    def loss(self, x, a, y) -> float:
        z = a @ x
        return float(np.mean(np.logaddexp(0, z) - y * z)) + self.l2 / 2 * float(x @ x)

    def grad(self, x, a, y) -> np.ndarray:
        p = 1 / (1 + np.exp(-np.clip(a @ x, -35, 35)))
        return a.T @ (p - y) / len(y) + self.l2 * x

    def scores(self, x, a) -> np.ndarray:
        z = a @ x
        return np.stack([-z, z], axis=1)


@dataclass(frozen=True)
class Softmax:
    dim: int
    classes: int
    l2: float = 0.0

    @property
    def n(self) -> int:
        return self.dim * self.classes

    def init(self, seed: int = 0) -> np.ndarray:
        return np.zeros(self.n)

    def scores(self, x, a) -> np.ndarray:
        return a @ x.reshape(self.dim, self.classes)

    def loss(self, x, a, y) -> float:
        p = _softmax(self.scores(x, a))
        return float(-np.log(np.maximum(p[np.arange(len(y)), y.astype(int)], 1e-300)).mean()) + self.l2 / 2 * float(x @ x)

    def grad(self, x, a, y) -> np.ndarray:
        p = _softmax(self.scores(x, a))
        p[np.arange(len(y)), y.astype(int)] -= 1
        return (a.T @ p / len(y)).ravel() + self.l2 * x

    def scores_many(self, xs, a) -> list[np.ndarray]:
        z = a @ np.concatenate([x.reshape(self.dim, self.classes) for x in xs], axis=1)
        return np.split(z, len(xs), axis=1)

    def many(self, xs, a, y) -> list[tuple[float, np.ndarray]]:
        probabilities = [_softmax(z) for z in self.scores_many(xs, a)]
        losses = [cross_entropy(p, y) + self.l2 / 2 * float(x @ x) for p, x in zip(probabilities, xs, strict=True)]
        g = a.T @ np.concatenate([_down(p, y) for p in probabilities], axis=1)
        return [(loss, part.ravel() + self.l2 * x) for loss, part, x in zip(losses, np.split(g, len(xs), axis=1), xs, strict=True)]


class SparseRows:
    """Rows of a sparse matrix: ``at`` and ``value`` of row i lie between ``bounds[i]`` and ``bounds[i + 1]``."""

    def __init__(self, bounds: np.ndarray, at: np.ndarray, value: np.ndarray):
        self.bounds, self.at, self.value = bounds, at, value

    def __len__(self) -> int:
        return len(self.bounds) - 1

    def __getitem__(self, rows) -> SparseRows:
        picked = np.arange(len(self))[rows]
        size = np.diff(self.bounds)[picked]
        bounds = np.concatenate([[0], np.cumsum(size)])
        places = np.repeat(self.bounds[picked] - bounds[:-1], size) + np.arange(bounds[-1])
        return SparseRows(bounds, self.at[places], self.value[places])

    @property
    def owner(self) -> np.ndarray:
        return np.repeat(np.arange(len(self)), np.diff(self.bounds))

    def dense(self, dim: int) -> np.ndarray:
        return np.bincount(self.owner * dim + self.at, self.value, len(self) * dim).reshape(len(self), dim)


@dataclass(frozen=True)
class SparseSoftmax:
    """A softmax over hashed features, of which a row has few: work follows the rows' values, not ``dim``."""

    dim: int
    classes: int
    #: Rows of fewer than one value in so many cells are not filled up.
    FILLED: ClassVar[int] = 32

    @property
    def n(self) -> int:
        return self.dim * self.classes

    def init(self, seed: int = 0) -> np.ndarray:
        return np.zeros(self.n)

    def scores(self, x, a: SparseRows) -> np.ndarray:
        w = x.reshape(self.dim, self.classes)
        return np.stack([np.bincount(a.owner, a.value * w[a.at, c], len(a)) for c in range(self.classes)], axis=1)

    def loss(self, x, a, y) -> float:
        p = _softmax(self.scores(x, a))
        return float(-np.log(np.maximum(p[np.arange(len(y)), y.astype(int)], 1e-300)).mean())

    def grad(self, x, a, y) -> np.ndarray:
        p = _softmax(self.scores(x, a))
        p[np.arange(len(y)), y.astype(int)] -= 1
        return np.stack([np.bincount(a.at, a.value * p[a.owner, c], self.dim) for c in range(self.classes)], axis=1).ravel() / len(y)

    def _slices(self, a: SparseRows) -> list[slice] | None:
        """Rows that are filled up to matrices at a time: products of matrices are faster unless rows are very sparse."""
        if self.dim > self.FILLED * max(len(a.at), 1) / max(len(a), 1):
            return None
        step = max(1, (1 << 20) // self.dim)
        return [slice(i, i + step) for i in range(0, len(a), step)]

    def scores_many(self, xs, a: SparseRows) -> list[np.ndarray]:
        slices = self._slices(a)
        if slices is None:
            return [self.scores(x, a) for x in xs]
        dense = Softmax(self.dim, self.classes)
        found = [dense.scores_many(xs, a[i].dense(self.dim)) for i in slices]
        return [np.concatenate(z) for z in zip(*found, strict=True)]

    def many(self, xs, a: SparseRows, y) -> list[tuple[float, np.ndarray]]:
        slices = self._slices(a)
        if slices is None:
            return [self._both(x, a, y) for x in xs]
        dense, losses, total = Softmax(self.dim, self.classes), np.zeros(len(xs)), np.zeros((len(xs), self.n))
        for i in slices:
            for j, (loss, g) in enumerate(dense.many(xs, a[i].dense(self.dim), y[i])):
                losses[j] += loss * len(y[i])
                total[j] += g * len(y[i])
        return [(float(loss) / len(y), g / len(y)) for loss, g in zip(losses, total, strict=True)]

    def _both(self, x, a: SparseRows, y) -> tuple[float, np.ndarray]:
        p, owner = _softmax(self.scores(x, a)), a.owner
        loss = cross_entropy(p, y)
        d = _down(p, y)
        return loss, np.stack([np.bincount(a.at, a.value * d[owner, c], self.dim) for c in range(self.classes)], axis=1).ravel()


@dataclass(frozen=True)
class SharedWindows:
    """A convolution-like layer: one weight matrix, applied to each of ``windows`` pieces of ``dim`` values,
    tanh, their mean, and a softmax on top."""

    dim: int
    windows: int
    hidden: int
    classes: int

    def shapes(self) -> list[tuple[int, int]]:
        return [(self.dim, self.hidden), (self.hidden, self.classes)]

    @property
    def n(self) -> int:
        return sum(r * c for r, c in self.shapes())

    def init(self, seed: int = 0) -> np.ndarray:
        r = np.random.default_rng(seed)
        return np.concatenate([r.normal(0, 1 / np.sqrt(i), i * o) for i, o in self.shapes()])

    def _forward(self, x, a):
        cut = self.dim * self.hidden
        shared, top = x[:cut].reshape(self.dim, self.hidden), x[cut:].reshape(self.hidden, self.classes)
        pieces = a.reshape(len(a) * self.windows, self.dim)
        act = _tanh(pieces @ shared)
        return pieces, act, act.reshape(len(a), self.windows, self.hidden).mean(axis=1), top

    def scores(self, x, a) -> np.ndarray:
        *_, pooled, top = self._forward(x, a)
        return pooled @ top

    def loss(self, x, a, y) -> float:
        p = _softmax(self.scores(x, a))
        return float(-np.log(np.maximum(p[np.arange(len(y)), y.astype(int)], 1e-300)).mean())

    def grad(self, x, a, y) -> np.ndarray:
        return self.both(x, a, y)[1]

    def both(self, x, a, y) -> tuple[float, np.ndarray]:
        pieces, act, pooled, top = self._forward(x, a)
        p = _softmax(pooled @ top)
        loss = cross_entropy(p, y)
        d = _down(p, y)
        np.multiply(act, act, out=act)
        np.subtract(1, act, out=act)
        back = act.reshape(len(a), self.windows, self.hidden)
        back *= (d @ top.T / self.windows)[:, None]
        return loss, np.concatenate([(pieces.T @ act).ravel(), (pooled.T @ d).ravel()])


@dataclass(frozen=True)
class Perceptron:
    """Hidden layers of ``hidden`` tanh units (``depth`` of them) and a softmax; non-convex."""

    dim: int
    hidden: int
    classes: int
    depth: int = 1

    def shapes(self) -> list[tuple[int, int]]:
        widths = [self.dim, *[self.hidden] * self.depth, self.classes]
        return list(zip(widths[:-1], widths[1:], strict=True))

    @property
    def n(self) -> int:
        return sum(r * c for r, c in self.shapes())

    def init(self, seed: int = 0) -> np.ndarray:
        r = np.random.default_rng(seed)
        return np.concatenate([r.normal(0, 1 / np.sqrt(i), i * o) for i, o in self.shapes()])

    def _weights(self, x) -> list[np.ndarray]:
        out, at = [], 0
        for r, c in self.shapes():
            out.append(x[at : at + r * c].reshape(r, c))
            at += r * c
        return out

    def scores(self, x, a) -> np.ndarray:
        *hidden, last = self._weights(x)
        for w in hidden:
            a = _tanh(a @ w)
        return a @ last

    def loss(self, x, a, y) -> float:
        p = _softmax(self.scores(x, a))
        return float(-np.log(np.maximum(p[np.arange(len(y)), y.astype(int)], 1e-300)).mean())

    def grad(self, x, a, y) -> np.ndarray:
        return self.both(x, a, y)[1]

    def both(self, x, a, y) -> tuple[float, np.ndarray]:
        *hidden, last = self._weights(x)
        acts = [a]
        for w in hidden:
            acts.append(_tanh(acts[-1] @ w))
        p = _softmax(acts[-1] @ last)
        loss = cross_entropy(p, y)
        d = _down(p, y)
        grads = [acts[-1].T @ d]
        back = d @ last.T
        for w, out, into in zip(reversed(hidden), reversed(acts[1:]), reversed(acts[:-1]), strict=True):
            d = back * (1 - out * out)
            grads.append(into.T @ d)
            back = d @ w.T
        return loss, np.concatenate([g.ravel() for g in reversed(grads)])


@dataclass(frozen=True)
class Recurrent:
    """A gated recurrent cell over sequences; predicts the class of the step after the last.

    Rows of a are sequences of ``steps`` vectors of ``dim`` values, flattened.
    """

    dim: int
    hidden: int
    classes: int
    steps: int

    @property
    def n(self) -> int:
        return 2 * (self.dim + self.hidden) * self.hidden + self.hidden * self.classes

    def init(self, seed: int = 0) -> np.ndarray:
        return np.random.default_rng(seed).normal(0, 0.2, self.n)

    def _parts(self, x):
        m = (self.dim + self.hidden) * self.hidden
        shape = (self.dim + self.hidden, self.hidden)
        return x[:m].reshape(shape), x[m : 2 * m].reshape(shape), x[2 * m :].reshape(self.hidden, self.classes)

    def _run(self, x, a):
        gate_w, cand_w, out_w = self._parts(x)
        seq = a.reshape(len(a), self.steps, self.dim)
        h = np.zeros((len(a), self.hidden))
        tape = []
        for t in range(self.steps):
            both = np.concatenate([seq[:, t], h], axis=1)
            g = 1 / (1 + np.exp(-both @ gate_w))
            c = _tanh(both @ cand_w)
            tape.append((both, g, c, h))
            h = g * h + (1 - g) * c
        return h, tape, gate_w, cand_w, out_w

    def scores(self, x, a) -> np.ndarray:
        h, *_, out_w = self._run(x, a)
        return h @ out_w

    def loss(self, x, a, y) -> float:
        p = _softmax(self.scores(x, a))
        return float(-np.log(np.maximum(p[np.arange(len(y)), y.astype(int)], 1e-300)).mean())

    def grad(self, x, a, y) -> np.ndarray:
        return self.both(x, a, y)[1]

    def both(self, x, a, y) -> tuple[float, np.ndarray]:
        h, tape, gate_w, cand_w, out_w = self._run(x, a)
        p = _softmax(h @ out_w)
        loss = cross_entropy(p, y)
        d = _down(p, y)
        d_out = h.T @ d
        dh = d @ out_w.T
        d_gate, d_cand = np.zeros_like(gate_w), np.zeros_like(cand_w)
        for both, g, c, before in reversed(tape):
            zg = dh * (before - c) * g * (1 - g)
            zc = dh * (1 - g) * (1 - c * c)
            d_gate += both.T @ zg
            d_cand += both.T @ zc
            dh = dh * g + (zg @ gate_w.T + zc @ cand_w.T)[:, self.dim :]
        return loss, np.concatenate([d_gate.ravel(), d_cand.ravel(), d_out.ravel()])


def losses_and_grads(objective, xs: list[np.ndarray], a, y) -> list[tuple[float, np.ndarray]]:
    """Loss and gradient of each parameter vector over the same rows."""
    if hasattr(objective, "many"):
        return objective.many(xs, a, y)
    if hasattr(objective, "both"):
        return [objective.both(x, a, y) for x in xs]
    return [(objective.loss(x, a, y), objective.grad(x, a, y)) for x in xs]


def measure(objective, xs: list[np.ndarray], a, y, ks: tuple[int, ...]) -> list[list[float]]:
    """Loss, and accuracies where the objective has scores, of each parameter vector; scores are computed once."""
    if not hasattr(objective, "scores"):
        return [[objective.loss(x, a, y)] for x in xs]
    found = objective.scores_many(xs, a) if hasattr(objective, "scores_many") else (objective.scores(x, a) for x in xs)
    out = []
    for x, z in zip(xs, found, strict=True):
        loss = objective.loss(x, a, y) if isinstance(objective, Logistic) else cross_entropy(_softmax(z), y) + getattr(objective, "l2", 0.0) / 2 * float(x @ x)
        out.append([loss, *_within(z, y, ks)])
    return out


def _within(scores: np.ndarray, y, ks: tuple[int, ...]) -> list[float]:
    """Shares of rows whose class is among the k best scores."""
    if not ks or not len(y):
        return [float("nan")] * len(ks)
    hits = np.argsort(-scores, axis=1, kind="stable")[:, : max(ks)] == y.astype(int)[:, None]
    return [float(hits[:, :k].any(axis=1).mean()) for k in ks]


def accuracy(objective, x, a, y, k: int = 1) -> float:
    """Share of rows whose class is among the k best scores."""
    return _within(objective.scores(x, a), y, (k,))[0] if len(y) else float("nan")
