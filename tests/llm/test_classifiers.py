"""Quality classifier, quality rules and language model."""

from __future__ import annotations

import math
import re
import zlib
from collections import Counter

import numpy as np
import pytest

from lossygrad.llm import lm_scoring, quality_classifier, quality_rules
from lossygrad.llm.queries import QUERIES

WORDS = re.compile(r"[^\x20\x09-\x0D]+")
SF = "/root/testdata/sf0.01"


def crc(doc_id, parts):
    return 0 if doc_id is None else zlib.crc32(str(doc_id).encode()) % parts


# ---- quality classifier


def test_op2_held_out_accuracy(spark):
    rows = {r["doc_id"]: r for r in QUERIES["op2_quality_classifier"](spark, SF).collect()}
    truth = {r["doc_id"]: r["quality"] for r in spark.read.parquet(f"{SF}/labels.parquet").collect()}
    assert all(r["held_out"] == (crc(d, 4) == 2) and 0 <= r["score"] <= 1 and r["predicted"] == int(r["score"] >= 0.7) for d, r in rows.items())
    held = [(rows[d]["score"], y) for d, y in truth.items() if d in rows and rows[d]["held_out"]]
    good, bad = [s for s, y in held if y == 1], [s for s, y in held if y == 0]
    auc = np.mean([(g > b) + (g == b) / 2 for g in good for b in bad])
    assert auc > 0.97 and np.mean([(s >= 0.7) == y for s, y in held]) > 0.93


def test_scorer_equals_plain_dot_product():
    texts = [f"good calm text number {i} with words." for i in range(60)] + [f"BAD!!! LOUD### x{i} y y y y y y" for i in range(60)]
    model = quality_classifier.train([t.encode() for t in texts], [1] * 60 + [0] * 60)
    some = [*texts[::7], "", "   ", "unseen Words here, 123!"]
    got = quality_classifier.Scorer(model).scores([t.encode() for t in some])
    for t, s in zip(some, got, strict=True):
        cells, values = quality_classifier.Features().cells(t.encode())
        assert s == pytest.approx(1 / (1 + math.exp(-(float(model.weights[cells] @ values) + model.bias))))
    assert got[0] > 0.7 > got[-4]


def test_features_count_every_gram():
    f = quality_classifier.Features()
    cells, values = f.cells(b"a b, b b c")
    # Tokens: a b , b = c  ->  6 unigrams and 5 bigrams.
    assert values.sum() == pytest.approx(quality_classifier.SCALE) and round(float((values / quality_classifier.SCALE * 11).sum())) == 11


def test_classifier_edges(spark, odd_documents, no_documents):
    labels = spark.createDataFrame([(1, 1), (1, 0), (9, 0), (None, 1), (7, None)], "doc_id long, quality int")
    assert quality_classifier.classify(odd_documents, labels).count() == 13
    assert quality_classifier.classify(no_documents, labels).count() == 0
    none = quality_classifier.classify(odd_documents, labels.where("doc_id = 0")).collect()
    assert all(r["score"] == 0.5 and r["predicted"] == 0 for r in none)
    assert quality_classifier.passing(odd_documents, labels).columns == odd_documents.columns


# ---- quality rules


def brute_base(text):
    text = text or ""
    words = WORDS.findall(text)
    lines = [x for x in text.split("\n") if WORDS.search(x)]
    windows = Counter(tuple(words[i : i + 8]) for i in range(len(words) - 7))
    hit = {j for i in range(len(words) - 7) if windows[tuple(words[i : i + 8])] > 1 for j in range(i, i + 8)}
    return len(words), sum(map(len, words)), sum(c in "#*$%&|<>" for c in text), sum(x in lines[:i] for i, x in enumerate(lines)), len(hit)


def check_base(rows, texts):
    want = sorted((repr(d), *brute_base(t)) for d, t in texts)
    got = sorted((repr(r["doc_id"]), r["n_words"], r["word_chars"], r["n_symbols"], r["n_dup_lines"], r["n_repeat_words"]) for r in rows)
    assert got == want
    for r in rows:
        assert r["base_failed"] == (r["n_words"] < 20 or 100 * r["n_repeat_words"] > 30 * r["n_words"]) and not (r["base_failed"] and r["kept"])


def test_rules_on_odd_documents(odd_documents, no_documents):
    check_base(quality_rules.judge(odd_documents).collect(), [(r["doc_id"], r["text"]) for r in odd_documents.collect()])
    assert quality_rules.judge(no_documents).count() == 0
    assert quality_rules.passing(odd_documents).columns == odd_documents.columns


def test_op7_on_a_table(spark):
    docs = spark.read.parquet(f"{SF}/documents.parquet").collect()
    rows = QUERIES["op7_quality_rules"](spark, SF).collect()
    check_base(rows, [(r["doc_id"], r["text"]) for r in docs])
    truth = {r["doc_id"]: r["quality"] for r in spark.read.parquet(f"{SF}/labels.parquet").collect()}
    fair = [r for r in rows if not r["base_failed"] and r["doc_id"] in truth]
    assert np.mean([r["kept"] for r in fair if truth[r["doc_id"]] == 1]) > 0.97
    assert np.mean([not r["kept"] for r in fair if truth[r["doc_id"]] == 0]) > 0.6


def test_js_distance():
    p, q = np.array([1.0, 0, 0]), np.array([0, 1.0, 1.0])
    assert quality_rules.js_distance(p, p) == 0 and quality_rules.js_distance(p, q) == pytest.approx(1)
    assert quality_rules.js_distance(np.array([3.0, 1]), np.array([1.0, 3])) == pytest.approx(quality_rules.js_distance(np.array([1.0, 3]), np.array([3.0, 1])))


# ---- language model


def lower(s):
    return "".join(chr(ord(c) + 32) if "A" <= c <= "Z" else c for c in s)


def check_lm(rows, texts):
    toks = [(d, [*WORDS.findall(lower(t or "")), "\n"]) for d, t in texts]
    counts = Counter(w for d, ws in toks if crc(d, 5) != 1 for w in ws)
    total, distinct = sum(counts.values()), len(counts)

    def row(d, ws):
        base = sum(math.log10((counts[w] + 0.5) / (total + 0.5 * (distinct + 1))) for w in ws)
        return repr(d), crc(d, 5) == 1, len(ws), sum(counts[w] > 0 for w in ws), total, round(base, 4)

    got = sorted((repr(r["doc_id"]), r["held_out"], r["n_tokens"], r["n_known"], r["train_tokens"], round(r["base_score"], 4)) for r in rows)
    want = sorted(row(d, ws) for d, ws in toks)
    assert [g[:5] for g in got] == [w[:5] for w in want]
    assert [g[5] for g in got] == pytest.approx([w[5] for w in want], rel=1e-6, abs=1e-3)
    return toks, counts


def test_lm_on_odd_documents(odd_documents, no_documents):
    check_lm(lm_scoring.score(odd_documents).collect(), [(r["doc_id"], r["text"]) for r in odd_documents.collect()])
    assert lm_scoring.score(no_documents).count() == 0


def test_lm_without_training_documents(spark):
    held = next(i for i in range(100) if crc(i, 5) == 1)
    rows = lm_scoring.score(spark.createDataFrame([(held, "a b")], "doc_id long, text string")).collect()
    assert rows[0]["score"] == rows[0]["base_score"] and rows[0]["train_tokens"] == 0


class PlainAutomaton:
    """Every n-gram of the training texts in dictionaries; one token at a time."""

    def __init__(self, toks, prior=lm_scoring.PRIOR):
        self.c = Counter()
        for d, ws in toks:
            if crc(d, 5) != 1:
                self.c.update(tuple(ws[i : i + k]) for k in (1, 2, 3) for i in range(len(ws) - k + 1))
        singles = [n for g, n in self.c.items() if len(g) == 1]
        self.norm, self.prior = sum(singles) + 0.5 * (len(singles) + 1), prior

    def p(self, history, word):
        if not history:
            return (self.c[(word,)] + 0.5) / self.norm
        lower, m = self.p(history[1:], word), self.prior[len(history) - 1]
        return (self.c[(*history, word)] + m * lower) / (self.c[history] + m) if self.c[history] else lower

    def score(self, ws):
        state, total = (), 0.0
        for w in ws:
            while state and not self.c[(*state, w)]:  # failure arcs
                m = self.prior[len(state) - 1]
                total += math.log10(m / (self.c[state] + m))
                state = state[1:]
                while state and not self.c[state]:
                    state = state[1:]
            total += math.log10(self.p(state, w))
            state = (*state, w)[-2:]
            while state and not self.c[state]:
                state = state[1:]
        return total


def test_op8_against_an_automaton_of_all_ngrams(spark):
    docs = spark.read.parquet(f"{SF}/documents.parquet")
    rows = {r["doc_id"]: r for r in QUERIES["op8_lm_scoring"](spark, SF).collect()}
    toks, counts = check_lm(rows.values(), [(r["doc_id"], r["text"]) for r in docs.collect()])
    plain = PlainAutomaton(toks)
    for d, ws in toks:
        assert rows[d]["score"] == pytest.approx(plain.score(ws), rel=1e-9, abs=1e-6)
    common_words = [w for w, _ in counts.most_common(3)]
    for history in [(), ("\x00never",), *[(w,) for w in common_words], *list(plain.c)[5000:5003]]:  # each history's probabilities sum to one
        history = tuple(history)[:2]
        known = sum(plain.p(history, w) for w in counts)
        assert known + plain.p(history, "\x00unknown") == pytest.approx(1, abs=1e-9)
    held = [r for r in rows.values() if r["held_out"]]
    assert sum(r["score"] for r in held) > 0.9 * sum(r["base_score"] for r in held)


def test_lm_blocks_and_parts_change_nothing(spark):
    docs = spark.read.parquet("/root/testdata/sf0.001/documents.parquet")
    plain = PlainAutomaton([(r["doc_id"], [*WORDS.findall(lower(r["text"] or "")), "\n"]) for r in docs.collect()])
    texts = {r["doc_id"]: [*WORDS.findall(lower(r["text"] or "")), "\n"] for r in docs.collect()}
    for r in lm_scoring.score(docs.repartition(3), block_tokens=700, part_grams=500).collect():
        assert r["score"] == pytest.approx(plain.score(texts[r["doc_id"]]), rel=1e-9, abs=1e-6)


def test_lm_learns_what_occurs_twice(spark):
    """The model gathers n-grams of any count: a text that a training text repeats scores above a fresh one."""
    words = [f"w{i}" for i in range(4000)]
    ids = [i for i in range(400) if crc(i, 5) != 1]
    held = [i for i in range(400) if crc(i, 5) == 1]
    rng = np.random.default_rng(3)
    texts = {i: " ".join(rng.choice(words, 60)) for i in ids}
    texts |= {held[0]: texts[ids[0]], held[1]: " ".join(rng.permutation(texts[ids[0]].split()))}
    got = {r["doc_id"]: r for r in lm_scoring.score(spark.createDataFrame(list(texts.items()), "doc_id long, text string")).collect()}
    assert got[held[0]]["base_score"] == pytest.approx(got[held[1]]["base_score"])
    assert got[held[0]]["score"] > got[held[1]]["score"] + 60
