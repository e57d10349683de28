"""Quality classifier: logistic regression on hashed word n-grams, trained by FTRL-proximal.

A text becomes a stream of tokens: each word gives its runs of letters and digits
(lower case, after a mark if written in capitals) and of other characters; a word
equal to the one before gives one repeat mark.  Uni- and bigrams of the stream are
hashed into ``2**BITS`` cells, and a cell's value is its count divided by the number of
n-grams, times ``SCALE``.  Scores are the logistic of one sparse dot product.

Labels come from a bounded sample: the ``TRAIN_DOCS`` labelled documents with the
smallest seeded hash of their id, never held-out ones.  They are learned in one task
(its rows are bounded), and the weights (2**BITS floats, 1 MB) are broadcast.  Scoring
covers every whole text in one pass without a shuffle.

Edge cases: null or empty text is scored by the bias; without usable labels every score
is 0.5; a document with conflicting labels counts as the lower one; null labels are
ignored; extra columns are never inputs; an empty table gives no rows.
"""

from __future__ import annotations

import math
import re
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from lossygrad.llm import common

BITS = 18
SCALE = 24.0
#: Labelled documents that are learned from, at most.
TRAIN_DOCS = 4096
EPOCHS = 3
ALPHA, BETA, L1, L2 = 0.4, 1.0, 1e-4, 1e-3
THRESHOLD = 0.7
FOLDS, HELD_OUT = 4, 2
_RUNS = re.compile(rb"[0-9A-Za-z\x80-\xff]+|[^0-9A-Za-z\x80-\xff]+")
#: Distinct words whose features a worker keeps before it starts anew.
_WORDS = 300_000
_MIX = np.uint64(0x9E3779B97F4A7C15)


def _token_hash(token: bytes) -> int:
    from xxhash import xxh64_intdigest

    return xxh64_intdigest(token, 7)


#: Token before a run in capitals.
_CAPITALS = 0x5DEECE66D


def _cells(h: np.ndarray) -> np.ndarray:
    return ((h * _MIX) >> np.uint64(64 - BITS)).astype(np.int64)


def _pairs(a: np.ndarray, b: np.ndarray) -> np.ndarray:
    return _cells(a * np.uint64(31) + (b ^ (b >> np.uint64(29))))


class Features:
    """Words by number, and for each the cells it gives alone (inner) and its end tokens."""

    def __init__(self) -> None:
        self.clear()

    def clear(self) -> None:
        self.number: dict[bytes, int] = {b" ": 0}  # the repeat mark; no word has a space
        self.tokens: list[int] = [_token_hash(b"=")]
        self.starts: list[int] = [0]
        self.cells_, self.begin, self.size = np.zeros(0, np.int64), np.zeros(0, np.int64), np.zeros(0, np.int64)
        self.first, self.last = np.zeros(0, np.uint64), np.zeros(0, np.uint64)
        self.grow()

    def _learn(self, words: set[bytes]) -> None:
        number, tokens, starts = self.number, self.tokens, self.starts
        for w in words:
            if w not in number:
                number[w] = len(starts)
                starts.append(len(tokens))
                if w.islower() and w.isalpha():
                    tokens.append(_token_hash(w))
                    continue
                for run in _RUNS.findall(w):
                    if len(run) > 1 and run.isupper():
                        tokens.append(_CAPITALS)
                    tokens.append(_token_hash(run.lower()))

    def grow(self) -> tuple[int, int]:
        """Brings the arrays up to the words learned; the span of new words."""
        old, new = len(self.first), len(self.starts)
        if old == new:
            return old, new
        base = self.starts[old]
        h = np.array(self.tokens[base:], np.uint64)
        starts = np.array(self.starts[old:], np.int64) - base
        counts = np.diff(np.r_[starts, len(h)])
        # A word of t tokens has t unigrams and t - 1 bigrams, side by side.
        inside = np.ones(max(len(h) - 1, 0), bool)
        inside[starts[1:] - 1] = False
        pairs = np.flatnonzero(inside)
        owner = np.repeat(np.arange(len(starts)), counts)
        cells = np.concatenate([_cells(h), _pairs(h[pairs], h[pairs + 1])])
        order = np.argsort(np.concatenate([owner, owner[pairs]]), kind="stable")
        sizes = 2 * counts - 1
        self.begin = np.r_[self.begin, len(self.cells_) + np.cumsum(sizes) - sizes]
        self.cells_ = np.r_[self.cells_, cells[order]]
        self.size = np.r_[self.size, sizes]
        self.first, self.last = np.r_[self.first, h[starts]], np.r_[self.last, h[starts + counts - 1]]
        return old, new

    def numbers(self, words: list[bytes]) -> np.ndarray:
        self._learn(set(words))
        ids = np.fromiter(map(self.number.__getitem__, words), np.int64, len(words))
        ids[1:][ids[1:] == ids[:-1]] = 0
        return ids

    def cells(self, text: bytes) -> tuple[np.ndarray, np.ndarray]:
        """Cells of a text and their values."""
        words = text.split()
        if not words:
            return np.zeros(0, np.int64), np.zeros(0)
        ids = self.numbers(words)
        self.grow()
        sizes = self.size[ids]
        at = np.repeat(self.begin[ids] - (np.cumsum(sizes) - sizes), sizes) + np.arange(sizes.sum())
        all_ = np.concatenate([self.cells_[at], _pairs(self.last[ids[:-1]], self.first[ids[1:]])])
        cells, counts = np.unique(all_, return_counts=True)
        return cells, counts * (SCALE / len(all_))


class Model:
    """Weights of the cells, and bias."""

    def __init__(self, weights: np.ndarray, bias: float):
        self.weights, self.bias = weights.astype(np.float64), bias


def train(texts: list[bytes], labels: list[int], epochs: int = EPOCHS) -> Model:
    """FTRL-proximal, one document at a time, in the order given."""
    z, n = np.zeros(1 << BITS), np.zeros(1 << BITS)
    zb = nb = 0.0
    features = Features()
    features.numbers([w for t in texts for w in t.split()])
    rows = [features.cells(t) for t in texts]

    def bias() -> float:
        return -zb / ((BETA + math.sqrt(nb)) / ALPHA)

    for _ in range(epochs):
        for (cells, x), y in zip(rows, labels, strict=True):
            zc, nc = z[cells], n[cells]
            w = np.where(np.abs(zc) <= L1, 0.0, -(zc - np.sign(zc) * L1) / ((BETA + np.sqrt(nc)) / ALPHA + L2))
            p = 1 / (1 + math.exp(-max(-35.0, min(35.0, float(w @ x) + bias()))))
            g = (p - y) * x
            z[cells] = zc + g - (np.sqrt(nc + g * g) - np.sqrt(nc)) / ALPHA * w
            n[cells] = nc + g * g
            gb = p - y
            zb += gb - (math.sqrt(nb + gb * gb) - math.sqrt(nb)) / ALPHA * bias()
            nb += gb * gb
    weights = np.where(np.abs(z) <= L1, 0.0, -(z - np.sign(z) * L1) / ((BETA + np.sqrt(n)) / ALPHA + L2))
    return Model(weights, bias())


class Scorer:
    """Dot products by word numbers: the weights of a word's inner cells are summed once."""

    def __init__(self, model: Model):
        self.model, self.features = model, Features()
        self._reset()

    def _reset(self) -> None:
        self.features.clear()
        self.weight = np.zeros(0)

    def _sums(self) -> None:
        f, old = self.features, len(self.weight)
        if old < len(f.begin):
            cells = f.cells_[f.begin[old] :]
            self.weight = np.r_[self.weight, np.add.reduceat(self.model.weights[cells], f.begin[old:] - f.begin[old])]

    def scores(self, texts: list[bytes]) -> list[float]:
        """Of a batch of texts: words are learned together, then each text is one dot product."""
        f, weights, out = self.features, self.model.weights, []
        for at in range(0, len(texts), 256):
            if len(f.number) > _WORDS:
                self._reset()
            split = [t.split() for t in texts[at : at + 256]]
            f._learn(set().union(*split))
            f.grow()
            self._sums()
            for words in split:
                total = 0.0
                if words:
                    ids = f.numbers(words)
                    cross = weights[_pairs(f.last[ids[:-1]], f.first[ids[1:]])]
                    total = SCALE * float(self.weight[ids].sum() + cross.sum()) / float(f.size[ids].sum() + len(cross))
                out.append(1 / (1 + math.exp(-max(-35.0, min(35.0, total + self.model.bias)))))
        return out


def fit(docs: DataFrame, labels: DataFrame, label: str = "quality", limit: int = TRAIN_DOCS, seed: int = 11) -> Model:
    usable = common.only(labels, "doc_id", label).where(F.col(label).isNotNull() & F.col("doc_id").isNotNull())
    usable = usable.where(common.crc_bucket(F.col("doc_id"), FOLDS) != HELD_OUT)
    one = usable.groupBy("doc_id").agg(F.min(label).cast("int").alias("y"))
    sample = one.withColumn("draw", F.xxhash64("doc_id", F.lit(seed))).orderBy("draw", "doc_id").limit(limit)
    rows = common.only(docs, "doc_id", "text").join(F.broadcast(sample), "doc_id")  # at most ``limit`` rows
    rows = rows.select("draw", "y", "text").repartition(1).sortWithinPartitions("draw", "text")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        texts, ys = [], []
        for b in batches:
            texts += common.utf8_bytes(b, "text")
            ys += b.column("y").to_pylist()
        if texts:
            m = train(texts, ys)
            yield pa.RecordBatch.from_pydict({"weights": [m.weights.astype(np.float32).tobytes()], "bias": [m.bias]})

    found = common.map_arrow(rows, run, "weights binary, bias double").collect()
    if not found:
        return Model(np.zeros(1 << BITS), 0.0)
    return Model(np.frombuffer(bytes(found[0]["weights"]), np.float32), found[0]["bias"])


def score(docs: DataFrame, model: Model, keep: tuple[str, ...] = ("doc_id",)) -> DataFrame:
    """``keep`` columns and ``score``."""
    spark = common.session_of(docs)
    sent = spark.sparkContext.broadcast((model.weights.astype(np.float32), model.bias))
    rows = common.only(docs, *dict.fromkeys((*keep, "text")))
    types = ", ".join(f"`{f.name}` {f.dataType.simpleString()}" for f in rows.select(*keep).schema)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        scorer = Scorer(Model(*sent.value))
        for batch in batches:
            scores = scorer.scores(common.utf8_bytes(batch, "text"))
            yield pa.RecordBatch.from_arrays([*(batch.column(c) for c in keep), pa.array(scores, pa.float64())], names=[*keep, "score"])

    return common.map_arrow(rows, run, f"{types}, score double")


def classify(docs: DataFrame, labels: DataFrame) -> DataFrame:
    """doc_id, held_out, score and predicted."""
    scored = score(docs, fit(docs, labels))
    return scored.select(
        "doc_id",
        (common.crc_bucket(F.col("doc_id"), FOLDS) == HELD_OUT).alias("held_out"),
        "score",
        (F.col("score") >= THRESHOLD).cast("int").alias("predicted"),
    )


def passing(docs: DataFrame, labels: DataFrame) -> DataFrame:
    """The rows of ``docs`` predicted 1, with the columns of ``docs``."""
    safe = common.guarded(docs)
    scored = score(safe, fit(docs, labels), tuple(safe.columns))
    return common.restored(scored.where(F.col("score") >= THRESHOLD), docs)
