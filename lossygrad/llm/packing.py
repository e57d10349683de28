"""Harmonic packing of tokenized documents into sequences of a fixed capacity.

A document shorter than the capacity C belongs to class ``k = C // length`` (its
length lies in ``(C/(k+1), C/k]``), and a bin of class k holds exactly k documents,
so bins fill without comparing documents and every worker packs on its own.  The
room that harmonic bins leave is filled by cutting documents that have to be cut
anyway (those of C tokens or more), then by incomplete bins, then by opening bins
of the lowest classes.  The rest of a block is cut into whole sequences and a last
remainder into powers of two, which need no padding.

Edge cases: a null or empty text is the end id alone; an empty table gives no rows;
repeated rows are packed each; extra columns are ignored; null doc_id stays null.
"""

from __future__ import annotations

import zlib
from collections.abc import Iterator

import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame

from lossygrad.llm import common, tokenizer

CAPACITY = 4096
#: Tokens after which a worker closes a block of bins; bounds its memory.
BLOCK_TOKENS = 2_000_000
PIECES = "doc_id long, start long, length long, ids_crc32 long, doc_tokens long, sequence_id long, offset long"


def harmonic_plan(lengths: list[int], capacity: int) -> list[list[tuple[int, int, int]]]:
    """Sequences as lists of (document, start, length); each token lies in exactly one.

    ``lengths`` are positive token counts.  Only the last few sequences are shorter
    than the capacity, and those have a power of two tokens.
    """
    classes: dict[int, list[int]] = {}
    filler: list[int] = []
    for i, n in enumerate(lengths):
        if n >= capacity:
            filler.append(i)
        elif n:
            classes.setdefault(capacity // n, []).append(i)
    bins: list[tuple[int, list[int]]] = []
    for k in sorted(classes, reverse=True):
        members = classes[k]
        whole = len(members) // k * k
        bins += [(k, members[at : at + k]) for at in range(0, whole, k)]
        filler += members[whole:]
    room = [capacity - sum(lengths[i] for i in docs) for _, docs in bins]
    spare, wanted = sum(lengths[i] for i in filler), sum(room)
    while bins and spare < wanted:  # bins stand from high to low classes; low ones waste most
        _, docs = bins.pop()
        wanted -= room.pop()
        spare += sum(lengths[i] for i in docs)
        filler += docs

    feed = iter(filler)
    at, begin, left = -1, 0, 0

    def cut(size: int) -> list[tuple[int, int, int]]:
        nonlocal at, begin, left
        got = []
        while size:
            if not left:
                at, begin = next(feed), 0
                left = lengths[at]
            n = min(size, left)
            got.append((at, begin, n))
            begin, left, size = begin + n, left - n, size - n
        return got

    out = [[(i, 0, lengths[i]) for i in docs] + cut(gap) for (_, docs), gap in zip(bins, room, strict=True)]
    rest = spare - wanted
    while rest:
        size = capacity if rest >= capacity else 1 << (rest.bit_length() - 1)
        out.append(cut(size))
        rest -= size
    return out


def pack(docs: DataFrame, vocabulary_path: str | None = None, capacity: int = CAPACITY, end_id: int = 2, with_ids: bool = False) -> DataFrame:
    """One row per piece; ``with_ids`` adds the piece's ids (little-endian unsigned 32-bit).

    No shuffle: each input partition tokenizes and packs its own documents.
    """
    spark = common.session_of(docs)
    content = spark.sparkContext.broadcast(tokenizer.vocabulary(vocabulary_path))
    block_tokens = max(BLOCK_TOKENS, capacity)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        enc = tokenizer.encoder(content.value, end_id)
        context = TaskContext.get()
        sequence = (context.partitionId() if context else 0) << 36
        doc_ids: list = []
        ids: list[bytes] = []
        held = 0

        def close() -> pa.RecordBatch:
            nonlocal sequence, held
            lengths = [len(x) // 4 for x in ids]
            rows: list[list] = [[] for _ in range(8)]
            for pieces in harmonic_plan(lengths, capacity):
                offset = 0
                for i, begin, n in pieces:
                    part = memoryview(ids[i])[4 * begin : 4 * (begin + n)]
                    values = (doc_ids[i], begin, n, zlib.crc32(part), lengths[i], sequence, offset, bytes(part) if with_ids else None)
                    for column, value in zip(rows, values, strict=True):
                        column.append(value)
                    offset += n
                sequence += 1
            doc_ids.clear()
            ids.clear()
            held = 0
            names = ["doc_id", "start", "length", "ids_crc32", "doc_tokens", "sequence_id", "offset", "ids"]
            kinds = [pa.int64()] * 7 + [pa.binary()]
            n = 8 if with_ids else 7
            return pa.RecordBatch.from_arrays([pa.array(r, k) for r, k in zip(rows[:n], kinds[:n], strict=True)], names=names[:n])

        for batch in batches:
            names = batch.column("doc_id").to_pylist()
            for at, raw, ends in enc.rounds(batch.column("text").cast(pa.string())):
                doc_ids += names[at : at + len(ends) - 1]
                ids += [raw[a:b] for a, b in zip(ends[:-1], ends[1:], strict=True)]
                held += len(raw) // 4
                if held >= block_tokens:
                    yield close()
        if ids:
            yield close()

    return common.map_arrow(common.only(docs, "doc_id", "text"), run, PIECES + (", ids binary" if with_ids else ""))
