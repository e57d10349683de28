"""Winnowing, chat formatting, mixing, near-duplicates, page texts and the pipeline."""

from __future__ import annotations

import hashlib
import re
from collections import Counter, defaultdict
from fractions import Fraction

import numpy as np
import pytest
import xxhash
from hypothesis import given, settings
from hypothesis import strategies as st
from pyspark.sql import functions as F

import corpus_pipeline
from lossygrad.llm import chat, html_extraction, mixing, simhash, winnowing
from lossygrad.llm.queries import QUERIES

WORDS = re.compile(r"[^\x20\x09-\x0D]+")


# ---- winnowing


def check_winnowing(rows, texts):
    order = sorted(texts, key=lambda x: (x[0] is None, -(x[0] or 0), x[1] or ""))
    want = Counter()
    for i, (d, t) in enumerate(order):
        t, after = t or "", order[(i + 1) % len(order)][1] or ""
        half = len(t) // 2
        want[repr(d), len(t), hashlib.sha256((t[: len(t) - half] + after[:half]).encode()).hexdigest()] += 1
    assert Counter((repr(r["doc_id"]), r["n_chars"], r["edited_sha256"]) for r in rows) == want


def signed(x):
    return x - (x >> 63 << 64)


def chained(longs):
    """Spark's hash of several longs: each is hashed with the hash so far as its seed."""
    h = 42
    for x in longs:
        h = xxhash.xxh64_intdigest((x & (1 << 64) - 1).to_bytes(8, "little"), h)
    return h


def brute_winnow(hashes, k, w):
    """(hash, position) of the rightmost minimum of every window of w grams of k items."""
    low = (1 << 38) - 1
    if not hashes:
        return []
    grams = [chained(hashes[i : i + k]) & low for i in range(len(hashes) - k + 1)] or [chained(hashes) & low]
    windows = [range(i, i + w) for i in range(len(grams) - w + 1)] or [range(len(grams))]
    return list(dict.fromkeys(min(((grams[i], -i) for i in win)) for win in windows))


def brute_prints(text):
    out = []
    for x in re.sub(r"[\x20\x09-\x0D]", " ", text.lower()).split(" "):
        out += [x[i : i + 32] for i in range(0, len(x), 32)] if len(x) > 64 else [x] if x else []
    kept = brute_winnow([signed(xxhash.xxh64_intdigest(x.encode(), 42)) for x in out], 5, 4)
    if len(text) <= 320 or (len(text) <= 1200 and re.search(r"[^\x20\x09-\x0D]{16}", text)):
        plain = re.sub(r"[\x20\x09-\x0D]+", " ", text.lower()).strip(" ")
        low = (1 << 38) - 1

        def grams(k):
            pieces = [plain[i : i + k] for i in range(len(plain) - k + 1)] or ([plain] if plain else [])
            return [(xxhash.xxh64_intdigest(x.encode(), 42) & low, -i) for i, x in enumerate(pieces)]

        five = grams(5)
        windows = [five[i : i + 4] for i in range(len(five) - 3)] or ([five] if five else [])
        kept += list(dict.fromkeys(map(min, windows)))
        kept += grams(2) if len(text) <= 15 else []
    return kept


def check_fingerprints(rows, texts):
    order = sorted(texts, key=lambda x: (x[0] is None, -(x[0] or 0), x[1] or ""))
    want = Counter()
    for i, (d, t) in enumerate(order):
        t, after = t or "", order[(i + 1) % len(order)][1] or ""
        half = len(t) // 2
        own, edited, beside = (brute_prints(x) for x in (t, t[: len(t) - half] + after[:half], after))

        def near(b, a={h for h, _ in own}):
            b = {h for h, _ in b}
            return round(len(a & b) / len(a | b), 9) if a or b else 1.0

        as_text = lambda p: " ".join(f"{h:X}@{-i}" for h, i in p)
        want[repr(d), as_text(own), as_text(edited), near(edited), near(beside)] += 1
    assert Counter((repr(r["doc_id"]), r["fingerprint"], r["edited_fingerprint"], round(r["near_edited"], 9), round(r["near_next"], 9)) for r in rows) == want


def test_fingerprints_of_mixed_long_words(spark):
    texts = ["", "a", "ab cd", " ".join(f"{'w' * 39}{i}" for i in range(10)), " ".join(f"{'w' * 39}{i}" for i in range(10)) + " " + "Z" * 70, "x" * 900, "one two three four five six seven eight nine ten " * 9,
             "b a " * 300, "https://example.org/" + "q" * 60 + " " + "r" * 65 + " plain words follow here and there"]
    docs = list(enumerate(texts))
    check_fingerprints(winnowing.compare_with_edit(spark.createDataFrame(docs, "doc_id long, text string")).collect(), docs)
    a, b = ({h for h, _ in brute_prints(texts[i])} for i in (3, 4))
    assert a & b


def test_winnowing_odd_documents(odd_documents, no_documents):
    rows = winnowing.compare_with_edit(odd_documents).collect()
    check_winnowing(rows, [(r["doc_id"], r["text"]) for r in odd_documents.collect()])
    check_fingerprints(rows, [(r["doc_id"], r["text"]) for r in odd_documents.collect()])
    assert all(0 <= r["near_edited"] <= 1 and 0 <= r["near_next"] <= 1 for r in rows)
    assert winnowing.compare_with_edit(no_documents).count() == 0


def test_op3_on_a_table(spark, sf):
    docs = [(r["doc_id"], r["text"]) for r in spark.read.parquet(f"{sf}/documents.parquet").collect()]
    rows = QUERIES["op3_winnowing"](spark, sf).collect()
    check_winnowing(rows, docs)
    check_fingerprints(rows, docs)
    text, prints = dict(docs), defaultdict(set)
    for r in rows:
        prints[text[r["doc_id"]]].add(r["fingerprint"])
    assert all(len(p) == 1 for p in prints.values())
    long = [r for r in rows if r["n_chars"] > 500]
    assert np.mean([r["near_edited"] > r["near_next"] for r in long]) > 0.95 and np.mean([r["near_edited"] for r in long]) > 0.2


def test_windows_and_ties(spark):
    words = [f"w{i % 5}" for i in range(40)]
    r = spark.createDataFrame([(" ".join(words),)], "t string").select(winnowing.fingerprint(F.col("t")).alias("f"), F.array(*[F.xxhash64(F.lit(w)) for w in words]).alias("h")).first()
    kept = [(x["hash"], x["position"]) for x in r["f"]]
    grams = {h: [p for x, p in kept if x == h] for h, _ in kept}
    positions = [p for _, p in kept]
    assert positions == sorted(positions) and len(set(positions)) == len(positions)
    # Every window of four grams holds a kept position, and a repeated hash is kept at its rightmost place in a window.
    assert all(any(s <= p < s + 4 for p in positions) for s in range(40 - 5 + 1 - 3))
    assert all((p - q) % 5 == 0 for ps in grams.values() for p, q in zip(ps[1:], ps[:-1], strict=True))


def test_match_guarantee(spark):
    shared = "one two three four five six seven eight"
    rows = spark.createDataFrame([(f"a b c d e {shared} f g h i j k", f"l m n {shared} o p q r s t u v")], "x string, y string")
    packed = lambda c: winnowing.hashes(winnowing.selected(F.col(c)))
    assert rows.select(F.size(F.array_intersect(packed("x"), packed("y")))).first()[0] >= 1


def test_half_of_a_short_text_matches(spark):
    texts = ["a", "ab", "cat", "hello", "hello you", "one two three four", "seven words are all that this has", "x" * 40, "https://example.org/" + "abcdefghij" * 40]
    texts += ["你好世界这是没有空格的文字" * n for n in (1, 4, 30)] + [" ".join(f"w{i}" * 9 for i in range(n)) for n in (3, 12, 19, 40)]
    texts = [t for pair in zip(texts, [f"{i} zyx Q{i * 7}v" * 60 for i in range(len(texts))], strict=True) for t in pair]
    rows = winnowing.compare_with_edit(spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string")).collect()
    # The edit changes nothing of one character and leaves one of two.
    assert not [texts[r["doc_id"]] for r in rows if r["n_chars"] > 2 and not r["near_edited"] > 0]


def test_a_long_run_breaks_no_other_word(spark):
    url = "https://example.org/a/path/of/some/length/" + "q" * 10
    rows = spark.createDataFrame([(f"a {url} b", f"a {url} b " + "Z" * 70 + " c")], "x string, y string")
    x, y = rows.select(winnowing.words(F.col("x")), winnowing.words(F.col("y"))).first()
    assert x == ["a", url, "b"] and y == ["a", url, "b", "z" * 32, "z" * 32, "z" * 6, "c"]


# ---- chat


CONTROL = st.text(alphabet="</s>[INST] \\|ok<im_start>é\n", max_size=40)


@given(st.lists(st.tuples(st.sampled_from(["user", "assistant", "system", "o\nd|d"]), CONTROL), min_size=1, max_size=5))
@settings(max_examples=12, deadline=None)
def test_templates_read_back(spark, turns):
    rows = spark.createDataFrame([(7, i, r, t) for i, (r, t) in enumerate(turns)], "conv_id long, turn long, role string, text string")
    rendered = chat.render(chat.fold(chat.events_of_turns(rows)))
    r = chat.read_back(rendered).first()
    assert [(t["role"], t["text"]) for t in r["turns"]] == turns and r["learned"] == "".join(t for a, t in turns if a == "assistant")
    inside = r["formatted"].replace(chat.START, "").replace(chat.SEP, "").replace(chat.END, "")
    assert not re.search(r"<\||</?s>|\[/?INST\]", inside)


def test_event_logs_fold(spark):
    events = [
        (1, 0, 0, "message", "user", "hi"), (1, 1, 1, "message", "assistant", ""), (1, 1, 2, "delta", None, "Hel"), (1, 1, 3, "delta", None, "lo"),
        (1, 0, 4, "edit", None, "hi there"), (1, 1, 5, "regenerate", None, "Go"), (1, 1, 6, "delta", None, "od day"), (1, 2, 7, "message", "user", "bye"), (1, 2, 8, "delete", None, None),
        (2, 0, 0, "delta", "assistant", "only "), (2, 0, 1, "delta", "assistant", "deltas"), (3, 0, 0, "message", "user", "gone"), (3, 0, 1, "delete", None, None),
    ]
    df = spark.createDataFrame(events, "conv_id long, message long, seq long, kind string, role string, text string").repartition(5)
    got = {r["conv_id"]: [(t["role"], t["text"]) for t in r["turns"]] for r in chat.fold(df).collect()}
    assert got == {1: [("user", "hi there"), ("assistant", "Good day")], 2: [("assistant", "only deltas")]}


def test_turns_become_logs_of_every_kind(spark, sf):
    log = chat.events_of_turns(spark.read.parquet(f"{sf}/conversations.parquet"))
    assert {r["kind"] for r in log.select("kind").distinct().collect()} == {"message", "delta", "edit", "regenerate"}
    assert log.groupBy("own").count().where("count < 2").count() == 0


def test_chat_edges(spark):
    rows = [(None, 0, "user", "x"), (1, None, None, None), (1, 0, "user", "same"), (1, 0, "user", "same"), (1, 1, "assistant", None), (2, 0, "assistant", "long " * 20000)]
    df = spark.createDataFrame(rows, "conv_id long, turn long, role string, text string").selectExpr("*", "1 as seq", "2 as own", "'q' as kind")
    got = {r["conv_id"]: r for r in chat.digest(chat.read_back(chat.render(chat.fold(chat.events_of_turns(df))))).collect()}
    assert got[1]["n_turns"] == 4 and got[2]["loss_chars"] == 100000 and got[None]["n_turns"] == 1 and got[1]["loss_chars"] == 0
    want = hashlib.sha256(b"\n\n" + b"user\nsame\n" * 2 + b"assistant\n\n").hexdigest()
    assert got[1]["turns_sha256"] == want
    assert chat.fold(chat.events_of_turns(df.where("conv_id = 99"))).count() == 0


# ---- mixing


def test_targets_are_refilled():
    t = mixing.targets({"a": 10, "b": 1000, "c": 100, None: 50})
    assert t["a"] == 20 and sum(t.values()) == Fraction(3, 2) * 1160 and all(t[s] <= 2 * n for s, n in {"a": 10, "b": 1000, "c": 100, None: 50}.items())


@given(st.dictionaries(st.integers(0, 50), st.integers(1, 1000), min_size=1, max_size=8), st.integers(0, 200))
@settings(max_examples=100, deadline=None)
def test_sainte_lague_is_the_highest_quotients(weights, seats):
    got, plain = mixing.sainte_lague(weights, seats), dict.fromkeys(weights, 0)
    for _ in range(seats):
        k = max(weights, key=lambda k: Fraction(weights[k], 2 * plain[k] + 1))
        plain[k] += 1
    assert sum(got.values()) == seats and all(abs(got[k] - plain[k]) <= 1 for k in weights)


def check_mix(rows, texts):
    size = lambda t: len(WORDS.findall(t or ""))
    assert sorted((repr(r["doc_id"]), r["size"]) for r in rows) == sorted((repr(d), size(t)) for d, t, _ in texts)
    by_source = Counter()
    for _, t, s in texts:
        by_source[s] += size(t)
    goal = mixing.targets(dict(by_source))
    assert sorted((r["source_size"], round(r["target"], 6)) for r in rows) == sorted((by_source[s], round(float(goal[s]), 6)) for _, _, s in texts)
    assert all(0 <= r["taken"] <= 2 * r["size"] for r in rows)


def test_mixing_odd_documents(odd_documents, no_documents):
    rows = mixing.mix(odd_documents).collect()
    check_mix(rows, [(r["doc_id"], r["text"], r["source"]) for r in odd_documents.collect()])
    assert sorted(map(repr, rows)) == sorted(map(repr, mixing.mix(odd_documents.repartition(7)).collect()))
    assert mixing.mix(no_documents).count() == 0
    assert mixing.mixed_documents(odd_documents).columns == odd_documents.columns and mixing.mixed_documents(no_documents).count() == 0


def test_op5_on_a_table(spark, monkeypatch):
    sf = "/root/testdata/sf0.01"
    docs = [(r["doc_id"], r["text"], r["source"]) for r in spark.read.parquet(f"{sf}/documents.parquet").collect()]
    for rows_a_shard in (mixing.SHARD_ROWS, 60):
        monkeypatch.setattr(mixing, "SHARD_ROWS", rows_a_shard)
        rows = QUERIES["op5_source_mixing"](spark, sf).collect()
        check_mix(rows, docs)
        source, taken, goal = {d: s for d, _, s in docs}, Counter(), {}
        for r in rows:
            taken[source[r["doc_id"]]] += r["taken"]
            goal[source[r["doc_id"]]] = r["target"]
        assert all(abs(taken[s] - goal[s]) <= 0.01 * goal[s] + 30 for s in goal)


@pytest.mark.parametrize(("rows_a_shard", "whole", "least_rows"), [(1, False, 0), (64, True, 100)])
def test_targets_are_met_by_many_cells(spark, monkeypatch, rows_a_shard, whole, least_rows):
    monkeypatch.setattr(mixing, "SHARD_ROWS", rows_a_shard)
    source = F.when(F.col("id") % 3 == 0, "hot").when(F.col("id") % 200 == 1, "rare").otherwise(F.concat(F.lit("s"), F.col("id") % 17))
    docs = spark.range(40000).select(F.col("id").alias("doc_id"), source.alias("source"), F.expr("repeat('w ', cast(5 + pmod(xxhash64(id), 40) as int))").alias("text"))
    by_source = mixing.mix(docs, whole=whole, keep=("doc_id", "source")).groupBy("source").agg(F.count("*").alias("n"), F.first("target").alias("target"), F.sum("taken").alias("taken")).collect()
    assert len(by_source) == 19 and all(r["n"] >= least_rows for r in by_source)
    assert all(abs(r["taken"] - r["target"]) <= (0.01 * r["target"] if whole else 2) for r in by_source), by_source


# ---- near-duplicates


def brute_fingerprint(text):
    words = WORDS.findall("".join(chr(ord(c) + 32) if "A" <= c <= "Z" else c for c in text or ""))
    if not words:
        return 0
    shingles = [" ".join(words[i : i + 4]) for i in range(max(1, len(words) - 3))]
    hashes = [xxhash.xxh64_intdigest(s.encode(), 42) for s in shingles]
    return sum(1 << b for b in range(64) if 2 * sum(h >> b & 1 for h in hashes) > len(hashes))


def brute_wide(text):
    """256 bits: the majority of four mixes of each distinct five-word shingle's hash."""
    words = WORDS.findall("".join(chr(ord(c) + 32) if "A" <= c <= "Z" else c for c in text or ""))
    hashes = {xxhash.xxh64_intdigest(" ".join(words[i : i + 5]).encode(), 42) for i in range(max(1, len(words) - 4))} if words else set()
    full = (1 << 64) - 1
    bits = 0
    for k in range(1, 5):
        mixed = []
        for h in hashes:
            x = (h + k * 0x9E3779B97F4A7C15) & full
            x = ((x ^ x >> 30) * 0xBF58476D1CE4E5B9) & full
            x = ((x ^ x >> 27) * 0x94D049BB133111EB) & full
            mixed.append(x ^ x >> 31)
        bits = bits << 64 | sum(1 << b for b in range(64) if 2 * sum(x >> b & 1 for x in mixed) > len(mixed))
    return bits


def wide_rows(fps):
    """Fingerprints of 256 bits as rows (id, fp, fp_0 .. fp_3)."""
    words = [np.array([f >> 64 * (3 - k) & ((1 << 64) - 1) for f in fps], np.uint64) for k in range(4)]
    return list(zip(range(len(fps)), *(x.view(np.int64).tolist() for x in (simhash.node_names(words), *words)), strict=True))


WIDE_ROWS = "doc_id long, fp long, fp_0 long, fp_1 long, fp_2 long, fp_3 long"


def components_of(fps, most=4):
    """Least index of each fingerprint's component, by comparing all."""
    label = list(range(len(fps)))
    changed = True
    while changed:
        changed = False
        for i in range(len(fps)):
            low = min(label[j] for j in range(len(fps)) if (fps[i] ^ fps[j]).bit_count() <= most)
            if low < label[i]:
                label[i], changed = low, True
    return label


def test_simhash_odd_documents(odd_documents, no_documents):
    docs = [(r["doc_id"], r["text"]) for r in odd_documents.collect()]
    rows = simhash.near_duplicates(odd_documents).collect()
    assert Counter((repr(r["doc_id"]), r["fingerprint"]) for r in rows) == Counter((repr(d), f"{brute_fingerprint(t):016x}") for d, t in docs)
    assert simhash.near_duplicates(no_documents).count() == 0 and simhash.one_of_each(no_documents).count() == 0
    kept = simhash.one_of_each(odd_documents)
    assert kept.columns == odd_documents.columns and kept.count() == len(set(components_of([brute_wide(t) for _, t in docs], 44)))


@pytest.mark.parametrize("hot_key", [simhash.HOT_KEY, 3])
def test_clusters_are_found_whole(spark, hot_key):
    r = np.random.default_rng(0)
    base = r.integers(0, 2**63, 12, dtype=np.uint64)
    fps = [0, 15, 31, 1 << 63]
    for b in base.tolist():
        for _ in range(int(r.integers(1, 30))):
            for bit in r.choice(64, int(r.integers(0, 4)), replace=False).tolist():
                b ^= 1 << bit
            fps.append(b)
    fps = list(dict.fromkeys(fps))
    rows = [(i, f - (1 << 64) if f >> 63 else f) for i, f in enumerate(fps)]
    marked = spark.createDataFrame(rows, "doc_id long, fp long")
    got = {x["doc_id"]: x["first"] for x in simhash.components(marked, "doc_id", hot_key).collect()}
    assert [got[i] for i in range(len(fps))] == components_of(fps)


@pytest.mark.parametrize("hot_key", [simhash.HOT_KEY, 5])
def test_wide_clusters_are_found_whole(spark, hot_key):
    r = np.random.default_rng(0)
    fps = [0, (1 << 44) - 1, (1 << 90) - 1]  # the last is 46 bits from its neighbour, 90 from the first
    for _ in range(40):
        b = int.from_bytes(r.bytes(32), "big")
        for _ in range(int(r.integers(1, 30))):
            f = b
            for bit in r.choice(256, int(r.integers(0, 18)), replace=False).tolist():
                f ^= 1 << bit
            fps.append(f)
    fps = list(dict.fromkeys(fps))
    marked = spark.createDataFrame(wide_rows(fps), WIDE_ROWS)
    got = {x["doc_id"]: x["first"] for x in simhash.components(marked, "doc_id", hot_key).collect()}
    assert [got[i] for i in range(len(fps))] == components_of(fps, 44)


def test_pairs_at_the_expected_distance_meet(spark):
    r = np.random.default_rng(2)
    fps = []
    for _ in range(1500):
        f = int.from_bytes(r.bytes(32), "big")
        flip = sum(1 << b for b in r.choice(256, simhash.ALIKE_BITS, replace=False).tolist())
        fps += [f, f ^ flip]
    marked = spark.createDataFrame(wide_rows(fps), WIDE_ROWS)
    got = {x["doc_id"]: x["first"] for x in simhash.components(marked).collect()}
    assert all(got[i] in (i, i ^ 1) for i in range(len(fps)))
    assert sum(got[i] == got[i + 1] for i in range(0, len(fps), 2)) >= 0.97 * len(fps) / 2


def test_similar_texts_are_in_one_class(spark, sf):
    docs = sorted((r["doc_id"], r["text"]) for r in spark.read.parquet(f"{sf}/documents.parquet").collect())
    marked = simhash.with_fingerprints(spark.read.parquet(f"{sf}/documents.parquet"), wide=True).persist()
    found = {r["doc_id"]: r["first"] for r in simhash.components(marked).collect()}
    rows = {r["doc_id"]: r for r in marked.collect()}
    fps = [brute_wide(t) for _, t in docs]
    assert [tuple(rows[d][c] for c in simhash.WORDS) for d, _ in docs] == [w[2:] for w in wide_rows(fps)]
    label = components_of(fps, simhash.WIDE_BITS)
    sets = []
    for _, t in docs:
        words = (t or "").lower().split()
        sets.append({tuple(words[i : i + 5]) for i in range(max(1, len(words) - 4))})
    alike = met = 0
    for i, (d, _) in enumerate(docs):
        assert label[[x for x, _ in docs].index(found[d])] == label[i]  # never more than links reach
        for j in range(i):
            if min(len(sets[i]), len(sets[j])) >= 0.8 * max(len(sets[i]), len(sets[j])) and len(sets[i] & sets[j]) >= 0.8 * len(sets[i] | sets[j]):
                alike += 1
                met += found[d] == found[docs[j][0]]
    assert alike > 0 and met >= 0.97 * alike


@pytest.mark.parametrize("blocks", [5, 6, 7, 8])
def test_every_link_meets_under_a_key(blocks):
    r = np.random.default_rng(1)
    for _ in range(200):
        diff = 0
        for bit in r.choice(64, 4, replace=False).tolist():
            diff |= 1 << bit
        assert any(all(not (diff >> at) & ((1 << width) - 1) for at, width in choice) for choice in simhash._scheme(blocks))


def test_op6_on_a_table(spark, sf):
    docs = [(r["doc_id"], r["text"]) for r in spark.read.parquet(f"{sf}/documents.parquet").collect()]
    rows = {r["doc_id"]: r for r in QUERIES["op6_simhash_near_duplicates"](spark, sf).collect()}
    docs.sort()
    fps = [brute_fingerprint(t) for _, t in docs]
    label = components_of(fps)
    assert all(rows[d]["fingerprint"] == f"{f:016x}" and rows[d]["component_id"] == docs[i][0] for (d, _), f, i in zip(docs, fps, label, strict=True))


# ---- page texts

PAGES = {
    "plain": ("<html><body><nav><a href=/>Home</a></nav><article><h1>Title &amp; more</h1><p>One  two<br>three.<p>Four &lt;five&gt;.</article><footer>&copy; x</footer></body></html>", "Title & more\nOne two three.\nFour <five>."),
    "noise": (
        "<body><header><h1>Site</h1><ul><li><a href=/a>a</a><li><a href=/b>b</a></ul></header><div class='cookie-notice'><p>We use cookies on this site and need your consent.</p></div>"
        "<main><article class=post><h1>Head</h1><p>First paragraph of the story, with some words in it.</p><div class=ad><a href=/buy>Buy now</a></div><p>Second paragraph, a little longer than the first one was.</p></article></main>"
        "<aside class=sidebar><h3>More</h3><ul><li><a href=/c>c d e</a></ul></aside><section id=comments><h3>Comments</h3><div class=comment><p>Nice story!</p></div></section>"
        "<form><p>Subscribe to our letter</p><input></form><script>var p = '<p>no</p>';</script><footer><p>All rights.</p></footer>",
        "Head\nFirst paragraph of the story, with some words in it.\nSecond paragraph, a little longer than the first one was.",
    ),
    "empty": ("", ""),
    "script": ("<script>x</script><style>y</style>", ""),
}


@pytest.mark.parametrize("name", PAGES)
def test_page_texts(name):
    html, want = PAGES[name]
    assert html_extraction.extract_texts([html], html_extraction.model()) == [want]


@given(st.text(alphabet="<>/ab pdiv=\"'!-&;#1", max_size=80))
@settings(max_examples=300, deadline=None)
def test_any_markup_parses(html):
    page = html_extraction.Page(html)
    assert all(0 <= p < i for i, p in enumerate(page.parent) if i)


def test_decoding_has_no_contradictions():
    page = html_extraction.Page("<div><p>a</p><div><p>b</p><p>c</p></div></div><p>d</p>")
    r = np.random.default_rng(0)
    for _ in range(200):
        kept = page.decode(r.random(len(page.parent)))
        assert kept[0] and all(kept[page.parent[i]] for i in range(1, len(kept)) if kept[i])


def test_held_out_training_pages():
    learned = html_extraction.model()
    right = total = 0
    for page, truth in html_extraction.training_pages(150, seed=123):
        leaf = np.array([t is not None for t in page.text])
        kept = page.decode(learned.trees.predict(page.features(learned.weights)))
        right += int((kept[leaf] == truth[leaf].astype(bool)).sum())
        total += int(leaf.sum())
    assert right / total > 0.99


STORY = "<h1>The title of it</h1><p>" + "Some plain words of an article, which go on for a while and say something. " * 4 + "</p><p>" + "A second paragraph with more to say about it, at some length. " * 4 + "</p>"
NAMES = ["content", "content has-sidebar", "content no-comments", "main-content with-header", "story share-enabled", "entry more-info", "has-sidebar", "post comments-open", "no-footer", "layout with-ads"]


@pytest.mark.parametrize("name", NAMES)
def test_names_of_containers_lose_no_article(name):
    want = "\n".join(" ".join(x.split()) for x in re.split(r"</?(?:h1|p)>", STORY) if x.strip())
    around = [f"<html><head><title>x</title></head><body><nav><a href='/'>Home</a> <a href='/b'>About</a></nav><{t} class='{name}'>{STORY}</{t}><footer>Copyright us 2020</footer></body></html>" for t in ("div", "section", "main", "article")]
    pages = [*around, f"<body class='{name}'>{STORY}</body>", f"<div class='{name}'>{STORY}</div>", f"<title>t</title><script>a<b 'x</script><div class='{name}'>{STORY}</div>"]
    assert html_extraction.extract_texts(pages, html_extraction.model()) == [want] * len(pages)


def test_formulas_and_fallbacks_are_text():
    page = html_extraction.Page("<p>so <math><mi>E</mi><mo>=</mo><mi>m</mi></math> and <object>this</object> <svg><text>too</text></svg></p>")
    assert [t for t in page.text if t] == ["so E=m and this too"]


@pytest.mark.parametrize("piece", ['<a href="x', "<a ", "<!", "</", "<div>", "<p><table><div>", "<div></p>", "<li><ul>", "<a b='", "<a href='x\" >"])
def test_time_is_linear(piece):
    import time

    began = time.process_time()
    html_extraction.Page(piece * (1_000_000 // len(piece)))
    assert time.process_time() - began < 2


def test_unclosed_quote_loses_only_its_tag():
    page = html_extraction.Page("<p>one</p><a href=\"x>two</a><p>three</p><p class='a'>four</p>")
    assert [t for t in page.text if t] == ["one", "two", "three", "four"]


def test_deep_page():
    assert html_extraction.extract_texts(["<div>" * 5000 + "<p>deep</p>"], html_extraction.model())[0] in ("deep", "")


def test_op9_on_a_table(spark, sf):
    import html as h

    rows = {r["page_id"]: r for r in QUERIES["op9_html_extraction"](spark, sf).collect()}
    for p in spark.read.parquet(f"{sf}/pages.parquet").collect():
        inner = re.search(r"<article>(.*)</article>", p["html"], re.S)[1]
        blocks = [" ".join(h.unescape(re.sub(r"</?b>", "", b.replace("<br>", " "))).split()) for b in re.split(r"</?(?:p|h1)>", inner)]
        want = "\n".join(b for b in blocks if b)
        r = rows[p["page_id"]]
        assert r["text"] == want and r["url"] == p["url"] and r["n_chars"] == len(want)


def test_pages_edges(spark):
    df = spark.createDataFrame([(1, None, None), (None, "u", "<p>x"), (1, "u", "")], "page_id long, url string, html string").selectExpr("*", "'t' as text", "1 as n_chars")
    rows = html_extraction.extract(df).collect()
    assert len(rows) == 3 and all(r["n_chars"] == len(r["text"]) for r in rows)
    assert html_extraction.extract(df.where("page_id = 5")).count() == 0


# ---- pipeline


def test_pipeline_stages(spark, sf):
    docs = spark.read.parquet(f"{sf}/documents.parquet")
    columns, counts = docs.columns, [docs.count()]
    for name, stage in corpus_pipeline.STAGES:
        before = docs
        docs = stage(spark, docs, sf).persist()
        counts.append(docs.count())
        if name != "harmonic_packing":
            assert docs.columns == columns
        if name in ("quality_rules", "quality_classifier", "simhash_near_dedup"):
            assert docs.select("doc_id").exceptAll(before.select("doc_id")).count() == 0 and counts[-1] <= counts[-2]
        if name == "simhash_near_dedup":
            want = {r["first"] for r in simhash.components(simhash.with_fingerprints(before, wide=True).persist()).collect()}
            assert {r["doc_id"] for r in docs.collect()} == want and counts[-1] == len(want)
        if name == "source_mixing":
            times = Counter(r["doc_id"] for r in docs.collect())
            assert max(times.values()) <= 2
    assert [n for n, _ in corpus_pipeline.STAGES] == ["quality_rules", "quality_classifier", "simhash_near_dedup", "source_mixing", "harmonic_packing"]
    assert counts[1] < counts[0] and corpus_pipeline.run(spark, sf).count() > 0


def test_pipeline_edges(spark, odd_documents, no_documents, sf):
    for docs in (odd_documents, no_documents):
        for _, stage in corpus_pipeline.STAGES:
            docs = stage(spark, docs, sf)
        assert docs.count() >= 0


def test_hot_keys_change_nothing(spark, sf, monkeypatch):
    docs = spark.read.parquet(f"{sf}/documents.parquet")
    want = {r["doc_id"]: r["component_id"] for r in simhash.near_duplicates(docs).collect()}
    monkeypatch.setattr(simhash, "HOT_KEYS", 2)
    assert {r["doc_id"]: r["component_id"] for r in simhash.near_duplicates(docs).collect()} == want
