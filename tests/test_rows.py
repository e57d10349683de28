"""Rows kept packed, and the forms that the descent computes them by, equal the plain ones."""

from __future__ import annotations

import numpy as np
import pytest
from pyspark.sql import functions as F

from lossygrad import experiments as E
from lossygrad.optim import sgd
from lossygrad.optim.objectives import LeastSquares, Logistic, Perceptron, Recurrent, SharedWindows, Softmax, SparseRows, SparseSoftmax, accuracy, losses_and_grads, measure
from lossygrad.sources import features


@pytest.mark.parametrize("windows", [1, 4])
def test_packed_rows_equal_unpacked(spark, sf, windows):
    """Also those of a text whose counts need two bytes."""
    texts = features.language_texts(spark, sf).withColumn("text", F.when(F.col("row_id") % 50 == 0, F.expr("repeat(text, 40)")).otherwise(F.col("text")))
    how = {"dim": 64, "windows": windows, "planted": features.planted_classes(64, 3)}
    plain, packed = ({r["row_id"]: r for r in sgd.deal(features.trigrams(texts, packed=p, **how), 2).collect()} for p in (False, True))
    assert {r["features"]["size"] for r in packed.values()} == {1, 2} and plain.keys() == packed.keys()
    assert all(packed[i]["y"] == plain[i]["y"] for i in plain)
    row = features.trigrams(texts, packed=True, **how).toArrow().sort_by("row_id").combine_chunks().to_batches()[0]
    assert np.array_equal(features.unpacked(row.column("features")), np.array([plain[i]["features"] for i in sorted(plain)]))


def test_hard_target_keeps_rows_packed(spark, sf, monkeypatch):
    """A row of 2048 values is no longer 16 KB where it is kept, dealt and sent to Python."""
    seen = []
    monkeypatch.setattr(E, "run_grid", lambda train, test, *a, **b: seen.append(train) or [])
    E.hard_target(spark, sf)
    assert seen[0].select(F.avg(F.length("features.counts"))).first()[0] < 2 * 2048 + 1


def test_forms_agree():
    r = np.random.default_rng(3)
    a, y, cases = r.normal(size=(40, 24)), r.integers(0, 3, 40).astype(float), []
    cases += [(o, a, y) for o in (Softmax(24, 3, 0.1), Perceptron(24, 5, 3, depth=2), SharedWindows(6, 4, 5, 3), Recurrent(6, 4, 3, 4), LeastSquares(24))]
    cases.append((Logistic(24, 0.1), a, (y > 0).astype(float)))
    dense = np.where(r.random((40, 24)) < 0.3, a, 0)
    at = [np.flatnonzero(x) for x in dense]
    rows = SparseRows(np.concatenate([[0], np.cumsum([len(x) for x in at])]), np.concatenate(at), np.concatenate([x[i] for x, i in zip(dense, at, strict=True)]))
    cases += [(SparseSoftmax(24, 3), rows, y), (SparseSoftmax(4096, 3), rows, y)]
    for objective, a_, y_ in cases:
        xs = [r.normal(size=objective.n) for _ in range(3)]
        found = losses_and_grads(objective, xs, a_, y_)
        for x, (loss, g), m in zip(xs, found, measure(objective, xs, a_, y_, (1, 2)), strict=True):
            # The gradient beside differences of the loss, which has a code of its own.
            e = r.normal(size=objective.n)
            assert loss == pytest.approx(objective.loss(x, a_, y_)) and m[0] == pytest.approx(loss)
            assert g @ e == pytest.approx((objective.loss(x + 1e-6 * e, a_, y_) - objective.loss(x - 1e-6 * e, a_, y_)) / 2e-6, rel=1e-5, abs=1e-7)
            assert not hasattr(objective, "scores") or m[1:] == [accuracy(objective, x, a_, y_, k) for k in (1, 2)]


def test_layer_sensitivity_keeps_rows_packed(spark, sf, monkeypatch):
    seen = []
    monkeypatch.setattr(E, "run_grid", lambda train, test, *a, **b: seen.append(train) or [])
    E.layer_sensitivity(spark, sf)
    assert len(seen) == 2 and all("counts" in t.schema["features"].dataType.names for t in seen)


def test_breakdown_keeps_rows_packed(spark, sf, monkeypatch):
    """Sparse rows too: counts of a byte and places of two, equal to the plain ones."""
    seen = []
    monkeypatch.setattr(E, "run_grid", lambda train, test, *a, **b: seen.append((b["workload"], train)) or [])
    E.breakdown(spark, sf)
    packed = next(t for n, t in seen if n == "wide_cheap").toArrow().sort_by("row_id").combine_chunks().to_batches()[0]
    bounds, at, value = features.unpacked_sparse(packed.column("features"))
    plain = features.sparse_trigrams(features.language_texts(spark, sf), 1 << 14).orderBy("row_id").collect()
    assert np.array_equal(at, np.concatenate([r["features"]["at"] for r in plain])) and np.array_equal(value, np.concatenate([r["features"]["value"] for r in plain]))
    assert list(np.diff(bounds)) == [len(r["features"]["at"]) for r in plain]
