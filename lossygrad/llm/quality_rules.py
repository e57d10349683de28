"""Quality rules: divergence of a document's histograms from language references.

Two histograms of every document are compared with references by Jensen-Shannon
distance: classes of characters (small, capital, other letters, digits, white space,
sentence punctuation, symbols, other punctuation, the rest) and common words of a
language (its most frequent function words, and one cell for all other words).  The
references are means over all documents of the table, one for each language of
``COMMON``; a document belongs to the language of which it has the most common words.

A document fails when its nearest reference is farther than a threshold that relaxes
with the sampling noise of short texts, ``limit + slack / sqrt(units)``, by one distance
alone or, with smaller slacks, by both.  Guards: the
character test needs ``MIN_CHARS`` characters, the word test ``MIN_WORDS`` words and
a language that is known.

Base rules come first: under 20 words, or over 30 % of the words in 8-word windows that
occur at least twice, reject a document whatever its histograms.

Edge cases: null text has no words and is rejected; one-word texts are guarded and fail
the base rule; equal rows get equal verdicts; an empty table gives no rows.
"""

from __future__ import annotations

from collections import Counter
from collections.abc import Iterator
from functools import lru_cache
from unicodedata import category

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from lossygrad.llm import common

# Frequent function words of each language.
COMMON = {
    "en": "the of and to in a is that for it as was with be by on not he his but at are this have from".split(),
    "de": "der die und in den von zu das mit sich des auf für ist im dem nicht ein eine als auch es an werden aus".split(),
    "fr": "de la le et les des en un du une que est pour qui dans a par plus pas au sur ne se ce il".split(),
    "es": "de la que el en y a los del se las por un para con no una su al lo como más pero sus le".split(),
}
LANGUAGES = list(COMMON)
LISTED = [w.encode() for l in LANGUAGES for w in COMMON[l]]
CLASSES = 9
WIDTH = len(COMMON["en"])
SYMBOLS = b"#*$%&|<>"
WINDOW = 8
MIN_WORDS_BASE = 20
MAX_REPEAT_PERCENT = 30
MIN_CHARS = 100
MIN_WORDS = 40
CHAR_LIMIT, CHAR_SLACK = 0.055, 3.6
WORD_LIMIT, WORD_SLACK = 0.06, 2.7
#: Slacks that must be exceeded together, by both distances, to reject.
BOTH_SLACKS = 1.6, 2.2
BASE = "n_words long, word_chars long, n_symbols long, n_dup_lines long, n_repeat_words long"


@lru_cache(maxsize=1)
def class_table() -> np.ndarray:
    """Class of each UTF-16 unit."""
    table = np.full(1 << 16, 8, np.uint8)
    for i in range(1 << 16):
        c = chr(i)
        kind = category(c)
        if c in " \t\n\v\f\r" or kind == "Zs":
            table[i] = 4
        elif c in SYMBOLS.decode() or kind[0] == "S":
            table[i] = 6
        elif c in ".,;:!?'\"-":
            table[i] = 5
        elif kind == "Ll":
            table[i] = 0
        elif kind == "Lu":
            table[i] = 1
        elif kind[0] in "LM":
            table[i] = 2
        elif kind[0] == "N":
            table[i] = 3
        elif kind[0] == "P":
            table[i] = 7
    return table


def histograms(texts: list[bytes]) -> tuple[np.ndarray, np.ndarray]:
    """Character-class counts and listed-word counts (in order of ``LISTED``), a row a text."""
    table = class_table()
    chars = np.zeros((len(texts), CLASSES), np.int64)
    words = np.zeros((len(texts), len(LISTED)), np.int64)
    for i, t in enumerate(texts):
        if t:
            units = np.frombuffer(t.decode().encode("utf-16-le"), np.uint16)
            chars[i] = np.bincount(table[units], minlength=CLASSES)
            counts = Counter(t.lower().split())
            words[i] = [counts[w] for w in LISTED]
    return chars, words


def word_cells(words: np.ndarray, n_words: np.ndarray) -> np.ndarray:
    """Counts by (text, language, word), with a last cell for all other words."""
    split = words.reshape(len(words), len(LANGUAGES), WIDTH)
    rest = n_words[:, None, None] - split.sum(axis=2, keepdims=True)
    return np.concatenate([split, np.maximum(rest, 0)], axis=2)


def js_distance(p: np.ndarray, q: np.ndarray) -> np.ndarray:
    """Square root of the Jensen-Shannon divergence (bits) along the last axis; inputs are counts or shares."""
    p = p / np.maximum(p.sum(axis=-1, keepdims=True), 1e-300)
    q = q / np.maximum(q.sum(axis=-1, keepdims=True), 1e-300)
    m = (p + q) / 2
    with np.errstate(divide="ignore", invalid="ignore"):
        d = np.where(p > 0, p * np.log2(p / m), 0).sum(-1) + np.where(q > 0, q * np.log2(q / m), 0).sum(-1)
    return np.sqrt(np.maximum(d / 2, 0))


def base_counts(text: bytes) -> tuple[int, int, int, int, int]:
    """n_words, word_chars, n_symbols, n_dup_lines, n_repeat_words."""
    words = text.split()
    n = len(words)
    chars = len(text.decode()) - sum(map(text.count, (b" ", b"\t", b"\n", b"\x0b", b"\x0c", b"\r")))
    lines = [x for x in text.split(b"\n") if x and not x.isspace()]
    repeated = 0
    if n >= WINDOW:
        h = np.fromiter(map(hash, words), np.int64, n).view(np.uint64)
        m = n - WINDOW + 1
        rolled = np.zeros(m, np.uint64)
        for j in range(WINDOW):
            rolled = rolled * np.uint64(0x9E3779B97F4A7C15) + h[j : j + m]
        order = np.argsort(rolled, kind="stable")
        same = rolled[order[1:]] == rolled[order[:-1]]
        if same.any():
            twice = np.zeros(m, bool)
            twice[order[1:][same]] = True
            twice[order[:-1][same]] = True
            steps = np.zeros(n + 1, np.int64)
            starts = np.flatnonzero(twice)
            steps[starts] += 1
            steps[starts + WINDOW] -= 1
            repeated = int((np.cumsum(steps[:-1]) > 0).sum())
    return n, chars, sum(map(text.count, (bytes([c]) for c in SYMBOLS))), len(lines) - len(set(lines)), repeated


def _language(words: np.ndarray) -> np.ndarray:
    """Index of the language with the most listed words, or -1 where none occurs."""
    hits = words.reshape(len(words), len(LANGUAGES), WIDTH).sum(axis=2)
    return np.where(hits.max(axis=1) > 0, hits.argmax(axis=1), -1) if len(words) else np.zeros(0, np.int64)


def references(docs: DataFrame) -> tuple[np.ndarray, np.ndarray]:
    """Mean character shares and word shares of each language, over all documents long enough."""
    size = CLASSES + WIDTH + 1

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        sums = np.zeros((len(LANGUAGES), size + 1))
        for batch in batches:
            for at in range(0, batch.num_rows, 512):
                texts = common.utf8_bytes(batch.slice(at, 512), "text")
                chars, words = histograms(texts)
                n = np.array([len(t.split()) for t in texts])
                lang = _language(words)
                good = (lang >= 0) & (n >= MIN_WORDS)
                if not good.any():
                    continue
                cells = word_cells(words, n)[good, lang[good]]
                row = np.concatenate([chars[good] / chars[good].sum(1, keepdims=True), cells / cells.sum(1, keepdims=True), np.ones((good.sum(), 1))], axis=1)
                np.add.at(sums, lang[good], row)
        yield pa.RecordBatch.from_pydict({"lang": list(range(len(LANGUAGES))), "sums": list(sums.tolist())}, schema=pa.schema([("lang", pa.int64()), ("sums", pa.list_(pa.float64()))]))

    parts = common.map_arrow(common.only(docs, "text"), run, "lang long, sums array<double>")
    # Each task gives one short row a language; summed by cell, they stay short.
    rows = parts.select("lang", F.posexplode("sums").alias("cell", "x")).groupBy("lang", "cell").agg(F.sum("x").alias("x")).collect()
    total = np.zeros((len(LANGUAGES), size + 1))
    for r in rows:
        total[r["lang"], r["cell"]] = r["x"]
    mean = total[:, :-1] / np.maximum(total[:, -1:], 1)
    return mean[:, :CLASSES], mean[:, CLASSES:]


def distances(texts: list[bytes], n_words: np.ndarray, char_ref: np.ndarray, word_ref: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Distances to the nearest reference by characters and by words, and characters counted.

    Word distance is NaN where the language isn't known."""
    chars, words = histograms(texts)
    known = char_ref.sum(axis=1) > 0
    n_chars = chars.sum(axis=1)
    if not known.any():
        return np.zeros(len(texts)), np.full(len(texts), np.nan), n_chars
    by_char = js_distance(chars[:, None, :].astype(float), char_ref[None, known]).min(axis=1)
    cells = word_cells(words, n_words).astype(float)
    by_word = np.where(known, js_distance(cells, word_ref[None]), np.inf).min(axis=1)
    return by_char, np.where(_language(words) >= 0, by_word, np.nan), n_chars


def verdicts(by_char: np.ndarray, by_word: np.ndarray, n_chars: np.ndarray, n_words: np.ndarray) -> np.ndarray:
    by_word = np.where(n_words >= MIN_WORDS, np.nan_to_num(by_word, nan=0.0), 0.0)
    by_char = np.where(n_chars >= MIN_CHARS, by_char, 0.0)
    # Excess over the limit, in units of the sampling noise.
    chars = (by_char - CHAR_LIMIT) * np.sqrt(n_chars)
    words = (by_word - WORD_LIMIT) * np.sqrt(n_words)
    return ~((chars > CHAR_SLACK) | (words > WORD_SLACK) | ((chars > BOTH_SLACKS[0]) & (words > BOTH_SLACKS[1])))


def judge(docs: DataFrame, keep: tuple[str, ...] = ("doc_id",)) -> DataFrame:
    """``keep`` columns, the base counts, both distances, base_failed and kept."""
    spark = common.session_of(docs)
    refs = spark.sparkContext.broadcast(references(docs))  # languages x cells: of fixed size
    rows = common.only(docs, *dict.fromkeys((*keep, "text")))
    types = ", ".join(f"`{f.name}` {f.dataType.simpleString()}" for f in rows.select(*keep).schema)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        char_ref, word_ref = refs.value
        for whole in batches:
            for at in range(0, whole.num_rows, 512):
                batch = whole.slice(at, 512)
                texts = common.utf8_bytes(batch, "text")
                base = np.array([base_counts(t) for t in texts], np.int64).reshape(-1, 5)
                n, repeats = base[:, 0], base[:, 4]
                by_char, by_word, n_chars = distances(texts, n, char_ref, word_ref)
                failed = (n < MIN_WORDS_BASE) | (100 * repeats > MAX_REPEAT_PERCENT * n)
                kept = ~failed & verdicts(by_char, by_word, n_chars, n)
                arrays = [*(batch.column(c) for c in keep), *map(pa.array, base.T), pa.array(by_char), pa.array(by_word, from_pandas=True), pa.array(failed), pa.array(kept)]
                names = [*keep, "n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", "char_distance", "word_distance", "base_failed", "kept"]
                yield pa.RecordBatch.from_arrays(arrays, names=names)

    return common.map_arrow(rows, run, f"{types}, {BASE}, char_distance double, word_distance double, base_failed boolean, kept boolean")


def passing(docs: DataFrame) -> DataFrame:
    """The rows of ``docs`` that are kept, with the columns of ``docs``."""
    safe = common.guarded(docs)
    return common.restored(judge(safe, tuple(safe.columns)).where("kept"), docs)
