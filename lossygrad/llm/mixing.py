"""Mixing sources to target weights by Sainte-Laguë apportionment of words.

1. Sizes (words) and rows are summed for each source, whose rows are dealt by hash to
   cells of its own, and sizes for each cell.
2. Sources in code-point order (null last) weigh 3, 1, 2, repeating, and share
   ``ratio`` times all words; a share above ``repeats`` times its source's size is cut
   there and the excess goes to the others by weight until none is above.
3. Targets are turned into integer numbers of words: first for each source, then for
   each group of ``GROUP_CELLS`` of its cells, then for each cell, each time by the highest
   quotients ``weight / (2 seats + 1)``.  A group or cell is never given more than it has
   ``repeats`` times; what it has no room for goes to the next quotients, so a source's
   words are given out to the last.
4. A cell's documents stand in a seeded order; its words are taken from the head of
   that line, going round again for repeats.  So a document is taken floor or ceil of
   the same number of times, at most ``repeats``, wholly but for the last one's cut.

A source has a cell for each ``SHARD_ROWS`` of its own rows, so a hot source is many cells
and a rare one is a single cell, beside which a document is small, whatever the input.
No task ranks more than a group's cells or a source's groups.
The only data on the driver are one row for each source, which is a small dimension
whose count is checked against ``MAX_SOURCES``.

Edge cases: null text has size 0 and is never taken; null source is a source of its own;
equal rows are separate documents (of one cell); an empty table gives no rows; extra columns are kept
or dropped as the caller asks, never read.
"""

from __future__ import annotations

from fractions import Fraction

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from lossygrad.llm import common

WEIGHTS = (3, 1, 2)
RATIO = Fraction(3, 2)
REPEATS = 2
SHARD_ROWS = 256
GROUP_CELLS = 1024
MAX_SOURCES = 1_000_000


def targets(sizes: dict[str | None, int], weights: tuple[int, ...] = WEIGHTS, ratio: Fraction = RATIO, repeats: int = REPEATS) -> dict[str | None, Fraction]:
    """Words that each source shall give."""
    order = sorted((s for s in sizes if s is not None)) + [s for s in sizes if s is None]
    weight = {s: weights[i % len(weights)] for i, s in enumerate(order)}
    goal = ratio * sum(sizes.values())
    out: dict[str | None, Fraction] = {}
    open_ = list(order)
    while open_:
        share = (goal - sum(out.values())) / sum(weight[s] for s in open_)
        over = [s for s in open_ if weight[s] * share > repeats * sizes[s]]
        if not over:
            out |= {s: weight[s] * share for s in open_}
            break
        out |= {s: Fraction(repeats * sizes[s]) for s in over}
        open_ = [s for s in open_ if s not in out]
    return out


def sainte_lague(weights: dict, seats: int) -> dict:
    """Seats by the highest quotients weight / (2 seats + 1); ties by order of keys.

    Starts one below each rounded-down share, where the method's result never lies
    below, so the work does not grow with the number of seats.
    """
    import heapq

    total = sum(weights.values())
    if not total or not seats:
        return dict.fromkeys(weights, 0)
    got = {k: max(0, int(seats * w / total) - 1) for k, w in weights.items()}
    heap = [(-Fraction(w) / (2 * got[k] + 1), i, k) for i, (k, w) in enumerate(weights.items()) if w]
    heapq.heapify(heap)
    for _ in range(seats - sum(got.values())):
        _, i, k = heap[0]
        got[k] += 1
        heapq.heapreplace(heap, (-Fraction(weights[k]) / (2 * got[k] + 1), i, k))
    return got


def apportioned(parts: DataFrame, owner: list[str], part: str, size: str, whole: str, words: str, repeats: int) -> DataFrame:
    """``owner``, ``part``, ``size`` and ``quota``: the owner's ``words`` by the highest quotients of its parts' sizes.

    Parts start one below their rounded-down share of ``whole``; the next quotients that there is room for are ranked.
    """
    start = F.greatest(F.floor(F.col(words) / F.col(whole) * F.col(size)).cast("long") - 1, F.lit(0))
    of_owner = Window.partitionBy(*owner)
    quotients = (
        parts.where(F.col(size) > 0)
        .select(*owner, part, size, words, start.alias("floor_words"))
        .withColumn("open", F.col(words) - F.sum("floor_words").over(of_owner))
        .withColumn("t", F.explode(F.array(*[F.lit(i) for i in range(4)])))
        .where(F.col("floor_words") + F.col("t") < F.col(size) * repeats)
        .withColumn("quotient", F.col(size) / (2 * (F.col("floor_words") + F.col("t")) + 1))
        .withColumn("place", F.row_number().over(of_owner.orderBy(F.col("quotient").desc(), part, "t")))
    )
    quotas = quotients.groupBy(*owner, part, size, "floor_words").agg(F.sum((F.col("place") <= F.col("open")).cast("long")).alias("more"))
    return quotas.select(*owner, part, size, (F.col("floor_words") + F.col("more")).alias("quota"))


def mix(docs: DataFrame, seed: int = 17, whole: bool = False, keep: tuple[str, ...] = ("doc_id",), weights: tuple[int, ...] = WEIGHTS, ratio: Fraction = RATIO, repeats: int = REPEATS) -> DataFrame:
    """``keep`` columns with size, source_size, target and taken (words; repeats counted).

    ``whole`` takes documents whole: a cell's last document by the middle of its span.
    """
    rows = common.only(docs, *dict.fromkeys((*keep, "doc_id", "source", "text")))
    kept = [c for c in dict.fromkeys(keep) if c in rows.columns]
    sized = rows.select(
        *[F.col(f"`{c}`").alias(f"keep_{c}") for c in kept],
        F.coalesce(F.concat(F.lit("s"), F.col("source").cast("string")), F.lit("n")).alias("src"),
        common.word_count(F.col("text").cast("string")).alias("size"),
        F.xxhash64("doc_id", "text", F.lit(seed)).alias("draw"),
        F.coalesce(F.col("doc_id").cast("string"), F.lit("")).alias("named"),
    )
    if "text" not in kept:  # so that texts are read and counted once
        sized = common.cut_lineage(sized)
    by_source = sized.groupBy("src").agg(F.sum("size").alias("source_size"), F.count("*").alias("source_rows"))
    listed = by_source.limit(MAX_SOURCES + 1).collect()
    if len(listed) > MAX_SOURCES:
        raise ValueError(f"more than {MAX_SOURCES} sources: not a dimension that the driver can apportion")
    sizes = {None if r["src"] == "n" else r["src"][1:]: r["source_size"] for r in listed}
    shards = {None if r["src"] == "n" else r["src"][1:]: -(-r["source_rows"] // SHARD_ROWS) for r in listed}
    goal = targets(sizes, weights, ratio, repeats)
    ordered = {s: goal[s] for s in [*sorted(s for s in goal if s is not None), *(s for s in goal if s is None)]}
    words = sainte_lague(ordered, round(sum(goal.values())))
    spark = common.session_of(docs)
    plan = spark.createDataFrame(
        [("n" if s is None else f"s{s}", sizes[s], float(goal[s]), min(words[s], repeats * sizes[s]), shards[s]) for s in goal],
        "src string, source_size long, target double, source_words long, shards long",
    )
    dealt = sized.join(F.broadcast(plan), "src").withColumn("cell", F.pmod(F.xxhash64("draw", F.lit(seed + 1)), F.col("shards")))
    dealt = dealt.withColumn("group", F.floor(F.col("cell") / GROUP_CELLS))
    cells = dealt.groupBy("src", "group", "cell", "source_size", "source_words").agg(F.sum("size").alias("cell_size"))
    groups = cells.groupBy("src", "group", "source_size", "source_words").agg(F.sum("cell_size").alias("group_size"))
    groups = apportioned(groups, ["src"], "group", "group_size", "source_size", "source_words", repeats).withColumnRenamed("quota", "group_words")
    quotas = apportioned(cells.join(groups, ["src", "group"]), ["src", "group"], "cell", "cell_size", "group_size", "group_words", repeats)
    quotas = quotas.select("src", "cell", "cell_size", "quota")
    line = Window.partitionBy("src", "cell").orderBy("draw", "named", "size").rowsBetween(Window.unboundedPreceding, -1)
    placed = dealt.withColumn("before", F.coalesce(F.sum("size").over(line), F.lit(0)))
    joined = placed.join(quotas, ["src", "cell"], "left")
    laps = F.floor(F.col("quota") / F.col("cell_size")).cast("long")
    rest = F.col("quota") - laps * F.col("cell_size")
    last = (
        F.when(F.col("before") * 2 + F.col("size") < rest * 2, F.col("size")).otherwise(0)
        if whole
        else F.least(F.greatest(rest - F.col("before"), F.lit(0)), F.col("size"))
    )
    return joined.select(
        *[F.col(f"keep_{c}").alias(c) for c in kept],
        "size",
        "source_size",
        "target",
        F.coalesce(laps * F.col("size") + last, F.lit(0)).cast("long").alias("taken"),
    )


def mixed_documents(docs: DataFrame, seed: int = 17) -> DataFrame:
    """The documents of the mixture, whole, each as many times as it is taken."""
    safe = common.guarded(docs)
    chosen = mix(safe, seed, whole=True, keep=tuple(safe.columns))
    times = F.when(F.col("size") > 0, F.floor(F.col("taken") / F.col("size")).cast("int")).otherwise(0)
    return common.restored(chosen.where(times > 0).withColumn("copy_", F.explode(F.array_repeat(F.lit(1), times))), docs)
