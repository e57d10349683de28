"""Language-model scoring with a weighted backoff automaton.

Model: all uni-, bi- and trigrams of the training texts (words, then an end token that is
no history), none of them dropped, with Dirichlet smoothing: a history h that was seen
c(h) times gives a token (c(h token) + m p) / (c(h) + m), where p is the shorter history's
probability of it and m the order's ``PRIOR``; single tokens get (c + 0.5) / (N + 0.5 (V + 1)),
the unknown word's share included.  So each history's probabilities sum to one.

Seen histories are the states of an automaton.  An arc consumes a token that was seen
after the state; where there is none, the failure arc leads to the shorter history and
adds the log of m / (c(h) + m).  A text's traversal runs from left to right: the state
that a token leads to is the longest seen suffix, at most two words, so it depends on
these two tokens alone, and the arcs of a whole block of texts are followed at once, in
arrays.

At scale: no part of the model is broadcast or gathered.

1. Texts are read once and written as blocks of about ``BLOCK_TOKENS`` tokens: hashes of
   distinct words, and each token's number among them.  Whole texts only.
2. A block lists its distinct n-grams of each order as hashes with its own training
   counts, sorted, and sends each range of the hash space to that range's part as bytes of
   differences.  So a frequent n-gram is one entry a block and no hot key; parts are as
   many as keep a part near ``PART_GRAMS`` entries.  A hash has ``SPARE_BITS`` bits more
   than tell the corpus's tokens apart, so at most one word in 2^32 and one n-gram in 2^22
   shares its hash with another, whatever the input.
3. A part adds up the counts and answers a block only where the total is not the block's
   own count (a bitmap and the totals).  With these answers, which hold just the arcs its
   texts need, a block follows its automaton.

Words go first, as the number of distinct ones is part of every probability; the driver
sees three sums: tokens, training tokens and distinct training words.

Edge cases: null or empty text is the end token alone; with no training document all
scores are those of an empty model (score equal to the base score); equal rows score
alike; a text longer than a block is a block; an empty table gives no rows.
"""

from __future__ import annotations

import math
import zlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark import TaskContext
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from lossygrad.llm import common

FOLDS, HELD_OUT = 5, 1
#: Weight of the shorter history's probabilities, for histories of one and of two words.
PRIOR = (3000.0, 5.0)
BLOCK_TOKENS = 3 << 19
#: For words, pairs and triples.
SPARE_BITS = (32, 22, 22)
PART_GRAMS = 1 << 20
#: The end token as a word: no word contains a line feed.
END = "\n"
RESULT = "doc_id long, held_out boolean, n_tokens long, n_known long, train_tokens long, base_score double, score double"
#: Rows that are split into tokens together.
_ROWS = 1024
_TYPES = {"block": pa.int64(), "doc_id": pa.list_(pa.int64()), "held_out": pa.list_(pa.bool_()), "size": pa.list_(pa.int32()), "n_train": pa.int64(), "words": pa.binary(),
          "tokens": pa.binary()}
_BLOCK = "block long, doc_id array<long>, held_out array<boolean>, size array<int>, n_train long, words binary, tokens binary"


# ---- bytes


def packed(values: np.ndarray) -> bytes:
    """Integers as planes of bytes without the highest zero planes, each byte in its entropy code (there is nothing to repeat)."""
    width = max(1, (int(values.max(initial=0)).bit_length() + 7) // 8)
    planes = np.ascontiguousarray(values).view(np.uint8).reshape(len(values), values.dtype.itemsize).T[:width]
    code = zlib.compressobj(1, strategy=zlib.Z_HUFFMAN_ONLY, wbits=-15)
    coded = [code.compress(np.ascontiguousarray(p)) + code.flush(zlib.Z_SYNC_FLUSH) for p in planes]  # a code of its own for each plane
    return b"".join([len(values).to_bytes(8, "little"), bytes([width]), *coded, code.flush()])


def unpacked(data: bytes, dtype) -> np.ndarray:
    n, width = int.from_bytes(data[:8], "little"), data[8]
    planes = np.zeros((np.dtype(dtype).itemsize, n), np.uint8)
    planes[:width] = np.frombuffer(zlib.decompress(data[9:], wbits=-15, bufsize=max(1, n * width)), np.uint8).reshape(width, n)
    return np.ascontiguousarray(planes.T).view(dtype).reshape(n)


# ---- blocks


def hashed_tokens(texts: pa.Array | pa.ChunkedArray) -> tuple[np.ndarray, np.ndarray]:
    """Hashes of all tokens of lower-cased texts (A-Z only), an end token after each text, and each text's bounds."""
    from xxhash import xxh64_intdigest

    words, number, bounds = common.arrow_words(pc.ascii_lower(texts.cast(pa.string())))
    known = [xxh64_intdigest(w) for w in words.cast(pa.binary()).to_pylist()]
    hashes = np.array([*known, xxh64_intdigest(END.encode())], np.uint64)
    return hashes[np.insert(number, bounds[1:], len(words))], bounds + np.arange(len(bounds))


def blocks_of(rows: DataFrame, block_tokens: int = BLOCK_TOKENS) -> DataFrame:
    """``rows`` (doc_id, held_out, text) as blocks of whole texts."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        place, made = TaskContext.get().partitionId() << 32, 0
        held: list[tuple[np.ndarray, pa.Array, np.ndarray, np.ndarray]] = []
        waiting = 0

        def block() -> pa.RecordBatch:
            nonlocal made
            tokens = np.concatenate([h[0] for h in held])
            out, sizes = np.concatenate([h[2] for h in held]), np.concatenate([h[3] for h in held])
            words, number, counts = np.unique(tokens, return_inverse=True, return_counts=True)
            # The most frequent words get numbers of one byte, the next of two; among these they stay sorted.
            often = np.argsort(np.argsort(-counts, kind="stable"), kind="stable")
            order = np.argsort(np.searchsorted([1 << 8, 1 << 16], often, side="right"), kind="stable")
            rank = np.empty(len(words), np.uint32)
            rank[order] = np.arange(len(words), dtype=np.uint32)
            row = {"block": place + made, "doc_id": pa.concat_arrays([h[1] for h in held]), "held_out": pa.array(out), "size": pa.array(sizes, pa.int32()), "n_train": int(sizes[~out].sum()),
                   "words": packed(np.diff(words[order], prepend=np.uint64(0))), "tokens": packed(rank[number])}
            made += 1
            lists = {k: pa.ListArray.from_arrays(pa.array([0, len(v)], pa.int32()), v) if isinstance(v, pa.Array) else pa.array([v], _TYPES[k]) for k, v in row.items()}
            return pa.RecordBatch.from_arrays([lists[k] for k in _TYPES], names=list(_TYPES))

        for batch in (b.slice(at, _ROWS) for b in batches for at in range(0, b.num_rows, _ROWS)):
            tokens, bounds = hashed_tokens(batch.column("text"))
            out = batch.column("held_out").to_numpy(zero_copy_only=False).astype(bool)
            at = 0
            while at < batch.num_rows:
                end = int(np.searchsorted(bounds, bounds[at] + max(block_tokens - waiting, 1), side="left"))
                end = min(max(end, at + 1), batch.num_rows)
                held.append((tokens[bounds[at] : bounds[end]], batch.column("doc_id").slice(at, end - at), out[at:end], np.diff(bounds[at : end + 1])))
                waiting += int(bounds[end] - bounds[at])
                at = end
                if waiting >= block_tokens:
                    yield block()
                    held, waiting = [], 0
        if held:
            yield block()

    return common.map_arrow(rows, run, _BLOCK)


def _mixed(x: np.ndarray) -> np.ndarray:
    """A bijection of 64-bit words that spreads every bit."""
    x = (x ^ (x >> np.uint64(30))) * np.uint64(0xBF58476D1CE4E5B9)
    x = (x ^ (x >> np.uint64(27))) * np.uint64(0x94D049BB133111EB)
    return x ^ (x >> np.uint64(31))


class Grams:
    """Hashes of the n-grams that end at every token of a block, those of k + 1 tokens in ``bits[k]`` bits."""

    def __init__(self, row: dict, bits: list[int]):
        self.bits, self.words, self.tokens = bits, _words(row), unpacked(row["tokens"], np.uint32)
        self.sizes = np.array(row["size"], np.int64)
        self.starts = np.cumsum(self.sizes) - self.sizes
        self.place = (np.arange(len(self.tokens)) - np.repeat(self.starts, self.sizes)).astype(np.int32)  # of a token in its text
        self.held = np.repeat(np.array(row["held_out"], bool), self.sizes)

    def order(self, k: int) -> tuple[np.ndarray, np.ndarray]:
        """Hashes of the n-grams of k + 1 tokens, and the tokens that they end at."""
        out = single = self.words[self.tokens]
        for j in range(1, k + 1):
            out = _mixed(out[:-1] * np.uint64(2 * j + 1) + np.uint64(j)) + single[j:]
        inside = np.flatnonzero(self.place >= k)
        return (_mixed(out) >> np.uint64(64 - self.bits[k]))[inside - k], inside

    def distinct(self, k: int) -> tuple[np.ndarray, np.ndarray]:
        """Sorted distinct n-grams of k + 1 tokens, and how often each is in training texts."""
        listed, inside = self.order(k)
        listed = listed << np.uint64(1) | self.held[inside]  # while they are sorted, the lowest bit marks those of held-out texts
        listed.sort()
        bare = listed >> np.uint64(1)
        first = _firsts(bare)
        learnt = np.add.reduceat((~listed & np.uint64(1)).astype(np.uint32), first, dtype=np.uint32) if len(bare) else np.zeros(0, np.uint32)
        return bare[first], learnt

    def numbered(self, k: int) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
        """As ``distinct``, then the tokens n-grams end at and the number of each one's n-gram in the list."""
        hashes, inside = self.order(k)
        at = np.argsort(hashes)
        first = _firsts(hashes[at])
        number = np.empty(len(at), np.int32)
        number[at] = np.repeat(np.arange(len(first), dtype=np.int32), np.diff(np.r_[first, len(at)]))
        return hashes[at[first]], np.bincount(number, ~self.held[inside], len(first)).astype(np.int64), inside, number


def _firsts(values: np.ndarray) -> np.ndarray:
    return np.flatnonzero(np.r_[True, values[1:] != values[:-1]]) if len(values) else np.zeros(0, np.int64)


def _words(row: dict) -> np.ndarray:
    return np.cumsum(unpacked(row["words"], np.uint64))


def _bounds(listed: np.ndarray, parts: int, bits: int) -> np.ndarray:
    """Where each part's range begins among sorted hashes (parts + 1 places)."""
    return np.searchsorted((listed >> np.uint64(bits - 32)) * np.uint64(parts) >> np.uint64(32), np.arange(parts + 1, dtype=np.uint64))


def asks(blocks: DataFrame, orders: tuple[int, ...], parts: int, bits: list[int]) -> DataFrame:
    """part (``parts`` of each order), block, its n-grams in the part's range, and their training counts in the block."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for row in batch.to_pylist():
                grams = Grams(row, bits)
                for k in orders:
                    listed, learnt = grams.distinct(k)
                    at = _bounds(listed, parts, bits[k])
                    some = np.flatnonzero(np.diff(at))
                    spans = [slice(at[p], at[p + 1]) for p in some]
                    yield pa.RecordBatch.from_arrays(
                        [pa.array(some + k * parts, pa.int32()), pa.array(np.full(len(some), row["block"])), pa.array([packed(np.diff(listed[s], prepend=np.uint64(0))) for s in spans], pa.binary()),
                         pa.array([packed(learnt[s]) for s in spans], pa.binary())], names=["part", "block", "grams", "learnt"],
                    )

    return common.map_arrow(blocks.select("block", "held_out", "size", "words", "tokens"), run, "part int, block long, grams binary, learnt binary")


def answer(asked: pa.Table) -> pa.Table:
    """For the blocks of a part: which of their n-grams have another total, and the totals; and a row without
    block that counts the part's n-grams of training texts."""
    lists = [np.cumsum(unpacked(g, np.uint64)) for g in asked.column("grams").to_pylist()]
    learnt = np.concatenate([unpacked(c, np.uint32) for c in asked.column("learnt").to_pylist()]).astype(np.int64)
    grams = np.concatenate(lists)
    order = np.argsort(grams)
    first = _firsts(grams[order])
    totals = np.empty_like(learnt)
    totals[order] = np.repeat(np.add.reduceat(learnt[order], first), np.diff(np.r_[first, len(order)]))
    other = totals != learnt
    ends = np.cumsum([len(x) for x in lists])
    spans = [slice(e - len(x), e) for e, x in zip(ends.tolist(), lists, strict=True)]
    rows = [(p, b, np.packbits(other[s]).tobytes(), packed(totals[s][other[s]])) for p, b, s in zip(asked.column("part").to_pylist(), asked.column("block").to_pylist(), spans, strict=True) if other[s].any()]
    rows = [(*r, None) for r in rows] + [(None, None, None, None, int((totals[order[first]] > 0).sum()))]
    schema = pa.schema([("part", pa.int32()), ("block", pa.int64()), ("other", pa.binary()), ("totals", pa.binary()), ("known", pa.int64())])
    return pa.Table.from_arrays([pa.array([r[i] for r in rows], schema.field(i).type) for i in range(5)], schema=schema)


def answers(blocks: DataFrame, orders: tuple[int, ...], parts: int, bits: list[int]) -> DataFrame:
    asked = asks(blocks, orders, parts, bits)
    return asked.groupBy("part").applyInArrow(answer, "part int, block long, other binary, totals binary, known long")


# ---- the automaton


class Automaton:
    """States and arcs for the n-grams that a block's texts meet.

    ``counts[k]`` holds the training count of the n-gram of k + 1 tokens that ends at each token (0: none).
    """

    def __init__(self, counts: list[np.ndarray], total: int, distinct: int, prior: tuple[float, ...] = PRIOR):
        self.counts, self.prior = counts, prior
        self.single = (counts[0] + 0.5) / (total + 0.5 * (distinct + 1))
        #: Length of the state that a token leads to: the longest seen suffix, less than the order.
        self.state = (counts[0] > 0).astype(np.int8)
        self.state[counts[1] > 0] = 2

    def traverse(self, place: np.ndarray) -> np.ndarray:
        """log10 weight of the step at each token; ``place`` is its place in its text, where the state is empty at 0."""
        state = np.where(place > 0, np.r_[np.int8(0), self.state[:-1]], 0)
        lower, weight = self.single, np.log10(self.single)
        backoff = np.zeros(len(weight))
        arcs = []
        for k in (1, 2):  # from short histories to long ones: probabilities of arcs need the shorter history's
            seen = np.flatnonzero(state >= k)
            n = self.counts[k - 1][seen - 1]
            p = lower.copy()
            p[seen] = (self.counts[k][seen] + self.prior[k - 1] * lower[seen]) / (n + self.prior[k - 1])
            arcs.append((seen, self.counts[k][seen] > 0, np.log10(p[seen]), np.log10(self.prior[k - 1] / (n + self.prior[k - 1]))))
            lower = p
        open_ = np.ones(len(weight), bool)  # tokens whose arc is still sought, from the carried state down its failure arcs
        for seen, has_arc, arc, failure in reversed(arcs):
            sought = open_[seen]
            taken = seen[has_arc & sought]
            weight[taken] = arc[has_arc & sought]
            open_[taken] = False
            failed = ~has_arc & sought
            backoff[seen[failed]] += failure[failed]
        return weight + backoff


def walked(row: dict, answers: list[dict], total: int, distinct: int, parts: int, bits: list[int], prior: tuple[float, ...] = PRIOR) -> pa.Table:
    """The rows of ``RESULT`` of a block."""
    grams = Grams(row, bits)
    met = []
    for k in range(3):
        listed, counts, inside, number = grams.numbered(k)
        at = _bounds(listed, parts, bits[k])
        for a in answers:
            if a["part"] // parts == k:
                p = a["part"] % parts
                span = counts[at[p] : at[p + 1]]
                span[np.unpackbits(np.frombuffer(a["other"], np.uint8), count=len(span)).astype(bool)] = unpacked(a["totals"], np.int64)
        met.append(np.zeros(len(grams.place), np.int64))
        met[k][inside] = counts[number]
    steps = Automaton(met, total, distinct, prior).traverse(grams.place)
    base = np.add.reduceat(np.log10(met[0] + 0.5), grams.starts) - grams.sizes * math.log10(total + 0.5 * (distinct + 1))
    columns = [row["doc_id"], row["held_out"], grams.sizes, np.add.reduceat((met[0] > 0).astype(np.int64), grams.starts), np.full(len(base), total), base, np.add.reduceat(steps, grams.starts)]
    kinds = [pa.int64(), pa.bool_(), pa.int64(), pa.int64(), pa.int64(), pa.float64(), pa.float64()]
    return pa.table([pa.array(c, t) for c, t in zip(columns, kinds, strict=True)], names=[x.split()[0] for x in RESULT.split(", ")])


def score(docs: DataFrame, block_tokens: int = BLOCK_TOKENS, part_grams: int = PART_GRAMS, prior: tuple[float, ...] = PRIOR) -> DataFrame:
    """A row of ``RESULT`` for each document."""
    rows = common.only(docs, "doc_id", "text").select(
        F.col("doc_id").cast("long"), (common.crc_bucket(F.col("doc_id"), FOLDS) == HELD_OUT).alias("held_out"), F.col("text").cast("string")
    )
    blocks = common.cut_lineage(blocks_of(rows, block_tokens), compression="zstd")
    sizes = F.aggregate("size", F.lit(0).cast("long"), lambda a, x: a + x)
    total, met = blocks.agg(F.coalesce(F.sum("n_train"), F.lit(0)), F.coalesce(F.sum(sizes), F.lit(0))).first()
    parts = max(1, -(-met // part_grams))  # an order has at most as many n-grams as there are tokens
    bits = [min(63, max(32, met.bit_length() + spare)) for spare in SPARE_BITS]
    words = common.cut_lineage(answers(blocks, (0,), parts, bits))
    distinct = words.agg(F.coalesce(F.sum("known"), F.lit(0))).first()[0]
    found = words.unionByName(answers(blocks, (1, 2), parts, bits)).where("block is not null")

    def walk(texts: pa.Table, answered: pa.Table) -> pa.Table:
        (row,) = texts.to_pylist()
        return walked(row, answered.to_pylist(), total, distinct, parts, bits, prior)

    needed = blocks.select("block", "doc_id", "held_out", "size", "words", "tokens")
    return needed.groupBy("block").cogroup(found.groupBy("block")).applyInArrow(walk, RESULT)
