"""SimHash near-duplicates by a Gray-order hierarchical index.

Fingerprint: each bit is 1 where over half of the text's 4-word shingles (repeats
included) have it set in their XXH64.  Fingerprints at most ``MAX_BITS`` bits apart
are linked; a component is what links reach.

Finding the links, on distinct fingerprints only:

1. The 64 bits are cut into m blocks.  Two fingerprints within 4 bits agree in at least
   m - 4 blocks, so each fingerprint is sent once for every choice of m - 4 blocks, keyed
   by their bits; linked ones meet under some key.  m grows with the number of
   fingerprints so that keys stay small; keys that are still hot are keyed anew by
   half of all bits (m = 8).
2. In a task, the rows of each key are sorted by Gray rank and grouped, 8 at a time, into
   leaves, nodes of leaves and so on.  A node keeps the bits all its members share (mask
   and pattern).  The tree is joined with itself from the top: a pair of nodes is pruned
   when their patterns differ in more than 4 bits of both masks, or when all members of
   both are linked already.  What is left is compared exactly.
3. A task gives a spanning set of its links (fewer than its rows), and components over
   all tasks come from alternating star contractions, with the edges written to the
   shared folder in every round.

So neither all pairs nor any group is gathered, and nothing but row counts reaches the
driver.  Joins by a fingerprint or a component send their hot keys by broadcast: those that
hold over 1 / ``HOT_KEYS`` of the rows, so at most ``HOT_KEYS`` of them.

``one_of_each``, which filters documents, takes another setting, ``WIDE``: five-word shingles
(each once), 256 bits, and links of at most 44 of them.  Shingle sets of Jaccard similarity
0.8 lie 39 bits apart on average (deviation 5.7), those of 0.7 49, those of 0.5 69, and
unrelated ones 128 (deviation 8), so chance links are out of reach at any size.  No choice of
blocks finds all neighbours at such a distance, so keys are bits at drawn places, more
keys the more fingerprints there are: a pair at 39 bits meets under one with a
probability of ``MEET`` at least, nearer ones more surely.  Nodes are named by a 64-bit mix
of the 256 bits.

Edge cases: null or empty text has fingerprint zero and is linked like any other; equal
rows are in one component; component_id is the smallest doc_id that isn't null, or null;
an empty table gives no rows.
"""

from __future__ import annotations

import math
from collections.abc import Iterator
from itertools import combinations

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from lossygrad.llm import common

SHINGLE = 4
SEED = 42
MAX_BITS = 4
#: Rows under one key above which its fingerprints are keyed anew by half of all bits.
HOT_KEY = 1 << 16
#: Fingerprints expected under one key at most, when they are spread evenly.
KEY_ROWS = 256
#: Words of a fingerprint of ``one_of_each``, its shingles' width, and the bits at which it links.
WIDE, WIDE_SHINGLE, WIDE_BITS = 4, 5, 44
#: Fewest drawn bits of a wide key: 2^16 x ``KEY_ROWS`` fingerprints get equally many keys each, more get more.
WIDE_KEY = 16
#: Expected bits between texts whose shingle sets are 0.8 alike, and the least chance that such a pair meets.
ALIKE_BITS, MEET = 39, 0.98
#: Most keys of a join that are hot, and so broadcast.
HOT_KEYS = 50_000
_FAN = 8
#: Columns of a wide fingerprint.
WORDS = tuple(f"fp_{i}" for i in range(WIDE))
#: Rows that a task indexes together, unless a single key has more.
_INDEX_ROWS = 1 << 19


# ---- fingerprints


def shingle_hashes(text: bytes, width: int = SHINGLE, seed: int = SEED) -> np.ndarray:
    """XXH64 of every shingle of a UTF-8 text, in order."""
    from xxhash import xxh64_intdigest

    words = text.lower().split()
    n = len(words)
    if not n:
        return np.zeros(0, np.uint64)
    line = b" ".join(words)
    ends = np.cumsum(np.fromiter(map(len, words), np.int64, n) + 1) - 1
    starts = np.concatenate([[0], ends[:-1] + 1])
    m = max(1, n - width + 1)
    spans = zip(starts[:m].tolist(), ends[min(width, n) - 1 :].tolist(), strict=True)
    return np.fromiter((xxh64_intdigest(line[a:b], seed) for a, b in spans), np.uint64, m)


def _majority(hashes: np.ndarray) -> np.ndarray:
    """Big-endian words whose bits are set in over half the rows of (rows, words) ``hashes``."""
    rows, words = hashes.shape
    counts = np.zeros(64 * words, np.int64)
    for at in range(0, rows, 1 << 14):
        part = np.unpackbits(hashes[at : at + (1 << 14)].astype(">u8").view(np.uint8).reshape(-1, 8 * words), axis=1)
        counts += part.sum(axis=0, dtype=np.int64)
    return np.packbits(counts * 2 > rows).view(">u8")


def _mixed(x: np.ndarray) -> np.ndarray:
    """A 64-bit finalizer: every bit depends on all bits of ``x``."""
    x = (x ^ (x >> np.uint64(30))) * np.uint64(0xBF58476D1CE4E5B9)
    x = (x ^ (x >> np.uint64(27))) * np.uint64(0x94D049BB133111EB)
    return x ^ (x >> np.uint64(31))


_STEPS = np.arange(1, WIDE + 1, dtype=np.uint64) * np.uint64(0x9E3779B97F4A7C15)


def fingerprint(text: bytes, width: int = SHINGLE, seed: int = SEED) -> int:
    """Signed 64-bit fingerprint of a UTF-8 text."""
    return int(_majority(shingle_hashes(text, width, seed)[:, None]).view(">i8")[0])


def wide_fingerprint(text: bytes) -> np.ndarray:
    """256-bit fingerprint of the distinct five-word shingles of a UTF-8 text."""
    hashes = np.unique(shingle_hashes(text, WIDE_SHINGLE))
    return _majority(_mixed(hashes[:, None] + _STEPS)).astype(np.uint64)


def node_names(words: list[np.ndarray]) -> np.ndarray:
    """One 64-bit name for each row of the columns ``words``; a single column names itself."""
    if len(words) == 1:
        return words[0]
    name = np.zeros(len(words[0]), np.uint64)
    for word in words:
        name = _mixed(name + np.uint64(0x9E3779B97F4A7C15) ^ word)
    return name


def with_fingerprints(docs: DataFrame, keep: tuple[str, ...] = ("doc_id",), wide: bool = False) -> DataFrame:
    """``keep`` columns and ``fp``, or if ``wide`` the 256 bits ``fp_0`` to ``fp_3`` and their name ``fp``; one pass, no shuffle."""
    rows = common.only(docs, *dict.fromkeys((*keep, "text")))
    out = rows.select(*keep).schema
    types = ", ".join(f"`{f.name}` {f.dataType.simpleString()}" for f in out)

    names = ["fp", *WORDS] if wide else ["fp"]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            texts = common.utf8_bytes(batch, "text")
            if wide:
                words = list(np.array([wide_fingerprint(t) for t in texts], np.uint64).reshape(-1, WIDE).T.copy())
                found = [node_names(words), *words]
            else:
                found = [np.array([fingerprint(t) for t in texts], np.int64)]
            fps = [pa.array(x.view(np.int64)) for x in found]
            yield pa.RecordBatch.from_arrays([*(batch.column(c) for c in keep), *fps], names=[*keep, *names])

    return common.map_arrow(rows, run, ", ".join([types, *(f"{n} long" for n in names)]))


# ---- the index


def gray_rank(x: np.ndarray) -> np.ndarray:
    """Place of each 64-bit value in the reflected Gray sequence."""
    x = x.copy()
    for shift in (1, 2, 4, 8, 16, 32):
        x ^= x >> np.uint64(shift)
    return x


def _unite(label: np.ndarray, a: np.ndarray, b: np.ndarray) -> None:
    """Joins the sets of each a and b; ``label`` points at each row's smallest known row."""
    while True:
        la, lb = label[a], label[b]
        apart = la != lb
        if not apart.any():
            return
        a, b = a[apart], b[apart]
        low = np.minimum(la[apart], lb[apart])
        np.minimum.at(label, la[apart], low)
        np.minimum.at(label, lb[apart], low)
        while True:
            nearer = label[label]
            if np.array_equal(nearer, label):
                break
            label[:] = nearer


class GrayIndex:
    """Fingerprints of many keys, each key sorted by Gray rank under a tree of shared bits.

    A fingerprint is a row of the columns ``words``, ranked by its first.
    """

    def __init__(self, keys: np.ndarray, words: list[np.ndarray]):
        order = np.lexsort((gray_rank(words[0]), keys))
        self.keys, self.words = keys[order], [w[order] for w in words]
        n = len(keys)
        self.label = np.arange(n)
        first = np.flatnonzero(np.r_[True, self.keys[1:] != self.keys[:-1]]) if n else np.zeros(0, np.int64)
        sizes = np.diff(np.r_[first, n])
        self.levels: list[tuple[np.ndarray, np.ndarray]] = []  # child bounds of each node
        self.masks = [[np.full(n, ~np.uint64(0))] * len(words)]
        self.patterns = [self.words]
        every = some = self.words
        groups = sizes
        while len(groups) and groups.max() > 1:
            counts = -(-groups // _FAN)
            place = np.arange(counts.sum()) - np.repeat(np.cumsum(counts) - counts, counts)
            begin = np.repeat(np.cumsum(groups) - groups, counts) + place * _FAN
            end = np.minimum(begin + _FAN, np.repeat(np.cumsum(groups), counts))
            every = [np.bitwise_and.reduceat(x, begin) for x in every]
            some = [np.bitwise_or.reduceat(x, begin) for x in some]
            self.levels.append((begin, end))
            self.masks.append([~(x ^ y) for x, y in zip(every, some, strict=True)])
            self.patterns.append(every)
            groups = counts

    def _settled(self) -> list[np.ndarray]:
        """For each level, the one label of all of a node's members, or -1."""
        low = high = self.label
        out = [self.label]
        for begin, _ in self.levels:
            low, high = np.minimum.reduceat(low, begin), np.maximum.reduceat(high, begin)
            out.append(np.where(low == high, low, -1))
        return out

    def _near(self, level: int, left: np.ndarray, right: np.ndarray, most: int) -> tuple[np.ndarray, np.ndarray]:
        """The pairs of nodes that differ in at most ``most`` of the bits which both share throughout."""
        apart = np.zeros(len(left), np.uint16)
        for mask, pattern in zip(self.masks[level], self.patterns[level], strict=True):
            apart = apart + np.bitwise_count((pattern[left] ^ pattern[right]) & mask[left] & mask[right])
            near = apart <= most
            left, right, apart = left[near], right[near], apart[near]
        return left, right

    def connect(self, most: int = MAX_BITS) -> None:
        """Afterwards rows of a key have one label just when links join them."""
        n = len(self.keys)
        for step in range(1, _FAN):  # neighbours in Gray order: joins most of each cluster at once
            i = np.arange(n - step)
            i = i[self.keys[i] == self.keys[i + step]]
            _unite(self.label, *self._near(0, i, i + step, most))
        if not self.levels:
            return
        settled = self._settled()
        top = len(self.levels)
        roots = np.arange(len(self.levels[-1][0]))
        stack = [(top, roots, roots)]
        while stack:
            level, a, b = stack.pop()
            if len(a) > 1 << 14:
                for at in range(0, len(a), 1 << 14):
                    stack.append((level, a[at : at + (1 << 14)], b[at : at + (1 << 14)]))
                continue
            begin, end = self.levels[level - 1]
            fan = np.arange(_FAN)
            left = np.broadcast_to((begin[a][:, None] + fan)[:, :, None], (len(a), _FAN, _FAN))
            right = np.broadcast_to((begin[b][:, None] + fan)[:, None, :], (len(a), _FAN, _FAN))
            real = (left < end[a][:, None, None]) & (right < end[b][:, None, None])
            real &= (left <= right) if level > 1 else (left < right)
            left, right = left[real], right[real]
            below = level - 1
            known = self.label if below == 0 else settled[below]
            open_ = (known[left] != known[right]) | (known[left] < 0)
            left, right = self._near(below, left[open_], right[open_], most)
            if not len(left):
                continue
            if below:
                stack.append((below, left, right))
            else:
                _unite(self.label, left, right)

    def edges(self) -> tuple[np.ndarray, np.ndarray]:
        rows = np.flatnonzero(self.label != np.arange(len(self.label)))
        names = node_names(self.words)
        return names[rows], names[self.label[rows]]


# ---- distributed search


def _scheme(m: int) -> list[list[tuple[int, int]]]:
    """The choices of m - 4 of m blocks, as (first bit, width) lists."""
    cuts = [64 * i // m for i in range(m + 1)]
    blocks = [(cuts[i], cuts[i + 1] - cuts[i]) for i in range(m)]
    return [list(c) for c in combinations(blocks, m - MAX_BITS)]


def _blocks_for(n: int) -> int:
    return next((m for m in (5, 6, 7) if n <= KEY_ROWS << (64 * (m - MAX_BITS) // m)), 8)


def _keyed(fps: DataFrame, m: int) -> DataFrame:
    def key(i: int, blocks: list[tuple[int, int]]) -> Column:
        parts = [F.shiftrightunsigned("fp", at).bitwiseAND(F.lit((1 << width) - 1)) for at, width in blocks]
        return F.struct(F.lit(i).alias("choice"), F.xxhash64(F.lit(i), *parts).alias("key"))

    return fps.select("fp", F.inline(F.array(*[key(i, c) for i, c in enumerate(_scheme(m))])))


def tables_for(width: int) -> int:
    """Keys of ``width`` drawn bits that let a pair ``ALIKE_BITS`` apart meet with a probability of ``MEET``."""
    bits = 64 * WIDE
    meet = math.prod((bits - ALIKE_BITS - i) / (bits - i) for i in range(width))
    return math.ceil(math.log(1 - MEET) / math.log(1 - meet))


def _drawn_masks(width: int) -> list[list[int]]:
    """Masks of ``width`` of all bits, as signed words; those cut from one shuffle of the bits share none."""
    bits, draw = 64 * WIDE, np.random.default_rng([SEED, width])
    masks: list[list[int]] = []
    while len(masks) < tables_for(width):
        order = draw.permutation(bits)
        for at in range(0, bits - width + 1, width):
            chosen = np.zeros(bits, np.uint8)
            chosen[order[at : at + width]] = 1
            masks.append(np.packbits(chosen).view(">i8").tolist())
    return masks[: tables_for(width)]


def _wide_keyed(fps: DataFrame, width: int) -> DataFrame:
    def key(i: int, mask: list[int]) -> Column:
        parts = [F.col(c).bitwiseAND(F.lit(m).cast("long")) for c, m in zip(WORDS, mask, strict=True)]
        return F.xxhash64(F.lit(i), *parts)

    return fps.select(*WORDS, F.explode(F.array(*[key(i, m) for i, m in enumerate(_drawn_masks(width))])).alias("key"))


def _search(keyed: DataFrame, words: tuple[str, ...] = ("fp",), most: int = MAX_BITS, hot_key: int | None = None) -> DataFrame:
    """Links (u > v) among the rows of each key.

    With ``hot_key``, rows of keys that have more rows than that are not linked but given
    back, with their ``words`` and null u and v; a task holds no such key whole.
    """
    index_rows = _INDEX_ROWS // len(words)
    back = words if hot_key is not None else ()
    schema = ", ".join(["u long, v long", *(f"{w} long" for w in back)])

    def links_of(columns: list[np.ndarray]) -> pa.RecordBatch:
        index = GrayIndex(columns[0], [x.view(np.uint64) for x in columns[1:]])
        index.connect(most)
        a, b = (pa.array(x.view(np.int64)) for x in index.edges())
        ends = [pc.max_element_wise(a, b), pc.min_element_wise(a, b)]
        return pa.RecordBatch.from_arrays([*ends, *(pa.nulls(len(a), pa.int64()) for _ in back)], names=["u", "v", *back])

    def given_back(columns: list[np.ndarray]) -> pa.RecordBatch:
        none = pa.nulls(len(columns[0]), pa.int64())
        return pa.RecordBatch.from_arrays([none, none, *map(pa.array, columns[1:])], names=["u", "v", *back])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: list[list[np.ndarray]] = []
        rows, hot = 0, None

        def settle(columns: list[np.ndarray]) -> Iterator[pa.RecordBatch]:
            """All keys of ``columns``, each whole."""
            if hot_key is None or not len(columns[0]):
                yield links_of(columns)
                return
            starts = np.flatnonzero(np.r_[True, columns[0][1:] != columns[0][:-1]])
            sizes = np.diff(np.r_[starts, len(columns[0])])
            cool = np.repeat(sizes <= hot_key, sizes)
            yield links_of([x[cool] for x in columns])
            if not cool.all():
                yield given_back([x[~cool] for x in columns])

        for batch in batches:  # rows come sorted by key
            part = [batch.column(c).to_numpy() for c in ("key", *words)]
            if hot is not None:
                same = int(np.searchsorted(part[0], hot, "right"))
                if same:
                    yield given_back([x[:same] for x in part])
                part = [x[same:] for x in part]
                if not len(part[0]):
                    continue
                hot = None
            held.append(part)
            rows += len(part[0])
            if rows >= index_rows:
                columns = [np.concatenate(x) for x in zip(*held, strict=True)]
                last = int(np.searchsorted(columns[0], columns[0][-1]))
                if last:
                    yield from settle([x[:last] for x in columns])
                held, rows = [[x[last:] for x in columns]], len(columns[0]) - last
                if hot_key is not None and rows > hot_key:
                    hot = columns[0][-1]
                    yield given_back(held[0])
                    held, rows = [], 0
        if rows:
            yield from settle([np.concatenate(x) for x in zip(*held, strict=True)])

    dealt = keyed.select("key", *words).repartition("key").sortWithinPartitions("key")
    return common.map_arrow(dealt, run, schema)


def wide_links(fps: DataFrame, hot_key: int = HOT_KEY) -> DataFrame:
    """A spanning set (u > v) of the links found among distinct wide fingerprints; hot keys' rows are keyed anew by 8 more bits."""
    width = max(WIDE_KEY, math.ceil(math.log2(max(1, fps.count()) / KEY_ROWS)))
    met = common.cut_lineage(_search(_wide_keyed(fps, width), WORDS, WIDE_BITS, hot_key))
    found = met.where("u is not null").select("u", "v")
    again = met.where("u is null").select(*WORDS).distinct()
    if not again.isEmpty():
        found = found.unionByName(_search(_wide_keyed(again, width + 8), WORDS, WIDE_BITS))
    return found.distinct()


def links(fps: DataFrame, hot_key: int = HOT_KEY) -> DataFrame:
    """A spanning set (u > v) of the links among distinct fingerprints ``fp``."""
    n = fps.count()
    m = _blocks_for(n)
    keyed = _keyed(fps, m)
    if m == 8 or n <= hot_key:
        return _search(keyed).distinct()
    hot = keyed.groupBy("key").count().where(F.col("count") > hot_key).select("key")
    hot = common.cut_lineage(hot)  # at most (choices x rows / hot_key) keys
    if hot.isEmpty():
        return _search(keyed).distinct()
    cool = keyed.join(hot, "key", "left_anti")
    again = keyed.join(hot, "key", "left_semi").select("fp").distinct()
    return _search(cool).unionByName(_search(_keyed(again, 8))).distinct()


def joined(left: DataFrame, right: DataFrame, key: str, weight: str, rows: int) -> DataFrame:
    """Inner join on ``key``, unique in ``right``, whose ``weight`` is the key's number among ``rows`` rows of ``left``.

    Keys of over ``rows / HOT_KEYS`` rows are at most ``HOT_KEYS``: these are broadcast, so a task holds no hot key.
    """
    hot = F.col(weight) > rows // HOT_KEYS
    here = left.join(F.broadcast(right.where(hot).drop(weight).withColumn("hot_", F.lit(True))), key, "left")
    rest = here.where("hot_ is null").select(*left.columns).join(right.where(~hot).drop(weight), key)
    return here.where("hot_").drop("hot_").unionByName(rest)


def contract(edges: DataFrame) -> DataFrame:
    """Stars (u, v) that join every node of ``edges`` (u > v) to its component's least node."""

    def state(df: DataFrame) -> tuple:
        return tuple(df.agg(F.count("*"), F.sum(F.xxhash64("u", "v").cast("decimal(38,0)"))).first())

    now = common.cut_lineage(edges)
    was = state(now)
    while was[0]:
        both = now.unionByName(now.select(F.col("v").alias("u"), F.col("u").alias("v")))
        least = both.groupBy("u").agg(F.least(F.min("v"), F.col("u")).alias("least"), F.count("*").alias("weight"))
        large = joined(both.where("v > u"), least, "u", "weight", 2 * was[0]).select(F.col("v").alias("u"), F.col("least").alias("v")).distinct()
        large = common.cut_lineage(large)
        least = large.groupBy("u").agg(F.min("v").alias("least"))
        met = large.join(least, "u")
        small = met.select("u", F.col("least").alias("v")).unionByName(met.where("v <> least").select(F.col("v").alias("u"), F.col("least").alias("v"))).distinct()
        now = common.cut_lineage(small)
        is_ = state(now)
        if is_ == was:
            break
        was = is_
    return now


def components(marked: DataFrame, row: str = "doc_id", hot_key: int = HOT_KEY) -> DataFrame:
    """``marked`` (a written table with ``fp``) with ``first``: the least ``row`` of its component."""
    words = [c for c in WORDS if c in marked.columns]
    by_fp = common.cut_lineage(marked.groupBy("fp").agg(F.min(row).alias("least_row"), F.count("*").alias("weight"), *[F.min(c).alias(c) for c in words]))
    prints, rows = by_fp.agg(F.count("*"), F.coalesce(F.sum("weight"), F.lit(0))).first()
    stars = contract((wide_links if words else links)(by_fp.select("fp", *words), hot_key))
    named = by_fp.drop(*words).join(stars.select(F.col("u").alias("fp"), F.col("v").alias("root")), "fp", "left").withColumn("root", F.coalesce("root", "fp"))
    firsts = named.groupBy("root").agg(F.min("least_row").alias("first"), F.count("*").alias("members"))
    return joined(marked.drop(*words), joined(named, firsts, "root", "members", prints).select("fp", "first", "weight"), "fp", "weight", rows)


def near_duplicates(docs: DataFrame, hot_key: int = HOT_KEY) -> DataFrame:
    """doc_id, fingerprint (16 hexadecimal digits) and component_id."""
    marked = common.cut_lineage(with_fingerprints(docs))
    found = components(marked, "doc_id", hot_key)
    return found.select("doc_id", F.lower(F.lpad(F.hex("fp"), 16, "0")).alias("fingerprint"), F.col("first").alias("component_id"))


def one_of_each(docs: DataFrame) -> DataFrame:
    """``docs`` with one row of each component: its smallest doc_id (null last; of equal ids, any one)."""
    safe = common.guarded(docs)
    marked = with_fingerprints(safe, tuple(safe.columns), wide=True).withColumn("row_", F.monotonically_increasing_id())
    marked = common.cut_lineage(marked)
    order = F.struct(F.col("doc_id").isNull().alias("none"), F.col("doc_id"), F.col("row_"))
    ids = marked.select("fp", *WORDS, order.alias("place"))
    chosen = components(ids, "place").select(F.col("first.row_").alias("row_")).distinct()
    return common.restored(marked.join(chosen, "row_", "left_semi"), docs)
