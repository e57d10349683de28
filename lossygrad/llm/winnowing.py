"""Winnowing fingerprints, in DataFrame functions only.

A text's words (lower case; each of over 64 characters is broken every 32) give
rolling k-gram hashes; each window of w consecutive hashes keeps its minimum, the
rightmost of equal ones, with its position.  Two texts that share ``w + k - 1``
consecutive words therefore share a kept hash.  A text of fewer than k words has one
hash, of all its words; a text without words has none.

Half of a short text may hold fewer words than that, so texts of at most ``SHORT``
characters, and those of at most ``MEDIUM`` with a run of 16 that aren't white space, also
give winnowed hashes of ``CHAR_K`` characters; under ``TINY``, of every two characters.
In any longer text half the characters hold ``w + k - 1`` whole words of at most 64
characters.  Both rules look at the text alone, and adding hashes never takes any away.

Hash and position travel in one long (38 bits of hash above 25 bits of reversed
position), so the minimum of a window is a plain ``least`` and picks the rightmost tie; a
text may have 2^25 words, more than a string of its kind holds in practice.

Edge cases: null text is empty; two empty fingerprints are alike (1.0), an empty and
a filled one are not (0.0); repeated ids follow each other by text; a null id comes
last in descending order; an empty table gives no rows.
"""

from __future__ import annotations

import math

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from lossygrad.llm import common

K, W = 5, 4
#: Most characters of texts that give hashes of characters too: all, and those with long runs; and of those that give all pairs.
SHORT, MEDIUM, TINY = 320, 1200, 15
CHAR_K, CHAR_W = 5, 4
_POSITIONS = (1 << 25) - 1
_HASHES = (1 << 38) - 1
_LOWEST = -(1 << 63)


def words(text: Column) -> Column:
    """Lower-case words, in order."""
    def pieces(x: Column) -> Column:
        return F.when(F.char_length(x) > 64, F.regexp_extract_all(x, F.lit(r"(?s).{1,32}"), F.lit(0))).otherwise(F.array(x))

    def parts(t: Column) -> Column:
        whole = F.split(t, " ")
        return F.when(t.rlike("[^ ]{65}"), F.flatten(F.transform(whole, pieces))).otherwise(whole)

    spaced = F.translate(F.lower(text), "\t\n\x0b\x0c\r", "     ")
    return F.filter(common.let(spaced, parts), lambda x: x != "")


def selected(text: Column, k: int = K, w: int = W) -> Column:
    """Array of packed (hash, reversed position) longs, in text order."""

    def grams(h: Column) -> Column:
        n = F.size(h)
        rolled = F.transform(F.sequence(F.lit(0), n - k), lambda i: _packed(F.xxhash64(*[F.get(h, i + j) for j in range(k)]), i))
        return F.when(n == 0, F.array().cast("array<bigint>")).when(n < k, F.array(_packed(F.xxhash64(h), F.lit(0)))).otherwise(rolled)

    hashed = F.transform(words(text), lambda x: F.xxhash64(x))
    return common.let(hashed, lambda h: common.let(grams(h), lambda p: _minima(p, w)))


def _minima(p: Column, w: int) -> Column:
    n = F.size(p)
    windows = F.transform(F.sequence(F.lit(0), n - w), lambda i: F.least(*[F.get(p, i + j) for j in range(w)]))
    return F.when(n == 0, p).when(n <= w, F.array(F.array_min(p))).otherwise(F.array_distinct(windows))


def selected_characters(text: Column) -> Column:
    """The same of a short text's characters (lower case, white space as one space); empty for other texts."""
    none = F.array().cast("array<bigint>")

    def grams(t: Column, k: int) -> Column:
        n = F.char_length(t)
        rolled = F.transform(F.sequence(F.lit(0), n - k), lambda i: _packed(F.xxhash64(t.substr(i + 1, F.lit(k))), i))
        return F.when(n == 0, none).when(n < k, F.array(_packed(F.xxhash64(t), F.lit(0)))).otherwise(rolled)

    def both(t: Column) -> Column:
        pairs = F.when(F.char_length(text) <= TINY, grams(t, 2)).otherwise(none)
        return F.concat(common.let(grams(t, CHAR_K), lambda p: _minima(p, CHAR_W)), pairs)

    n = F.char_length(text)
    short = (n <= SHORT) | ((n <= MEDIUM) & text.rlike(r"[^\x20\x09-\x0D]{16}"))
    plain = F.trim(F.regexp_replace(F.lower(text), r"[\x20\x09-\x0D]+", " "))
    return F.when(short, common.let(plain, both)).otherwise(none)


def selected_all(text: Column, k: int = K, w: int = W) -> Column:
    """Hashes of words, then those of characters."""
    return F.concat(selected(text, k, w), selected_characters(text))


def _packed(h: Column, i: Column) -> Column:
    return F.shiftleft(h.bitwiseAND(F.lit(_HASHES)), 25).bitwiseOR((F.lit(_POSITIONS) - i).cast("long"))


def fingerprint(text: Column, k: int = K, w: int = W) -> Column:
    """Array of structs (hash, position)."""
    return F.transform(
        selected(text, k, w),
        lambda p: F.struct(F.shiftright(p, 25).alias("hash"), (F.lit(_POSITIONS) - p.bitwiseAND(F.lit(_POSITIONS))).alias("position")),
    )


def hashes(packed: Column) -> Column:
    return F.array_distinct(F.transform(packed, lambda p: F.shiftright(p, 25)))


def as_text(packed: Column) -> Column:
    """``hash@position`` of each kept hash, hexadecimal and decimal, space-joined."""
    return F.array_join(
        F.transform(packed, lambda p: F.concat(F.hex(F.shiftright(p, 25)), F.lit("@"), (F.lit(_POSITIONS) - p.bitwiseAND(F.lit(_POSITIONS))).cast("string"))), " "
    )


def likeness(a: Column, b: Column) -> Column:
    """Jaccard similarity of two arrays of distinct hashes."""
    return common.let(
        F.size(F.array_intersect(a, b)),
        lambda both: F.when((F.size(a) == 0) & (F.size(b) == 0), 1.0).otherwise(both / (F.size(a) + F.size(b) - both)),
    )


def with_next(docs: DataFrame) -> DataFrame:
    """doc_id, text and the text of the next document by descending doc_id (after the last: the first).

    Ids are cut into ranges of about equal counts; each range's first row is also
    sent to the range before it, so that one shuffle of the texts is enough and no
    task sees more than its ranges.
    """
    spark = common.session_of(docs)
    rows = common.only(docs, "doc_id", "text").select(
        "doc_id", F.coalesce("doc_id", F.lit(_LOWEST)).alias("key"), F.coalesce("text", F.lit("")).alias("text")
    )
    ranges = 4 * int(spark.conf.get("spark.sql.shuffle.partitions"))
    cuts = rows.agg(F.percentile_approx("key", [i / ranges for i in range(1, ranges)], 20 * ranges).alias("q")).first()["q"] or []
    bounds = sorted(set(cuts))
    step = max(1, math.isqrt(len(bounds)))

    def at_or_below(values: Column, key: Column) -> Column:
        return F.size(F.filter(values, lambda b: b <= key))

    if bounds:
        coarse = F.array(*[F.lit(b).cast("long") for b in bounds[step - 1 :: step]])
        fine = F.array(*[F.lit(b).cast("long") for b in bounds])
        span = common.let(
            at_or_below(coarse, F.col("key")) * step,
            lambda c: c + at_or_below(F.slice(fine, c + 1, F.lit(step)), F.col("key")),
        )
    else:
        span = F.lit(0)
    placed = rows.withColumn("span", span)
    tops = [(r["span"], r["top"]) for r in placed.groupBy("span").agg(F.max("key").alias("top")).orderBy("span").collect()]
    # The first row of a range follows the last row of the range above; the very first follows the very last.
    ghosts = [(top, tops[(i + 1) % len(tops)][0]) for i, (_, top) in enumerate(tops)]
    if not ghosts:
        return rows.select("doc_id", "text", F.col("text").alias("next_text"))
    where = F.broadcast(spark.createDataFrame(ghosts, "key long, above int"))  # at most one row for each range
    dealt = (
        placed.join(where, "key", "left")
        .withColumn("to", F.explode(F.filter(F.array(F.struct(F.col("span").alias("at"), F.lit(0).alias("ghost")), F.struct(F.col("above").alias("at"), F.lit(1).alias("ghost"))), lambda x: x["at"].isNotNull())))
        .select("doc_id", "key", "text", F.col("to.at").alias("at"), F.col("to.ghost").alias("ghost"))
    )
    order = Window.partitionBy("at").orderBy("ghost", F.col("key").desc(), "text")
    return dealt.withColumn("next_text", F.lead("text").over(order)).where("ghost = 0").select("doc_id", "text", "next_text")


def compare_with_edit(docs: DataFrame, k: int = K, w: int = W) -> DataFrame:
    """Each document's fingerprint beside that of its edited text and of the next document.

    Edited: the last half (rounded down) of the code points is replaced by as many
    first ones of the next document, or all it has.
    """
    paired = with_next(docs).withColumn("n_chars", F.char_length("text").cast("long"))
    half = F.floor(F.col("n_chars") / 2).cast("int")
    edited = paired.withColumn(
        "edited", F.concat(F.substring("text", 1, F.col("n_chars").cast("int") - half), F.substring("next_text", 1, half))
    )

    def compared(a: Column, b: Column, c: Column) -> Column:
        return common.let(
            hashes(a),
            lambda own: F.struct(
                as_text(a).alias("fingerprint"),
                as_text(b).alias("edited_fingerprint"),
                likeness(own, hashes(b)).alias("near_edited"),
                likeness(own, hashes(c)).alias("near_next"),
            ),
        )

    result = common.let(
        selected_all(F.col("text"), k, w),
        lambda a: common.let(selected_all(F.col("edited"), k, w), lambda b: common.let(selected_all(F.col("next_text"), k, w), lambda c: compared(a, b, c))),
    )
    return edited.select("doc_id", "n_chars", F.sha2("edited", 256).alias("edited_sha256"), F.inline(F.array(result)))
