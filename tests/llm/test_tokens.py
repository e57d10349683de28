"""Packing, the token file and the cached encoder."""

from __future__ import annotations

import zlib
from collections import defaultdict

import numpy as np
import pytest
from hypothesis import given, settings
from hypothesis import strategies as st

from lossygrad.llm import packing, token_file, tokenizer


@pytest.fixture(scope="module")
def plain():
    from tokenizers import Tokenizer

    model = Tokenizer.from_str(tokenizer.vocabulary())
    return lambda t: np.array([*model.encode(t or "", add_special_tokens=False).ids, 2], dtype="<u4")


ENCODER = tokenizer.Encoder(tokenizer.vocabulary())


@given(st.lists(st.one_of(st.text(), st.text(alphabet="aA'.,!<|>́̌ sS \x1cΣßİJéǰ19", max_size=30)), max_size=6))
@settings(max_examples=150, deadline=None)
def test_cached_ids_are_the_library_s(texts):
    texts = [t.encode("utf-8", "ignore").decode() for t in texts]
    got = ENCODER.encode([t.encode() for t in texts])
    for t, ids in zip(texts, got, strict=True):
        assert ids == np.array([*ENCODER.model.encode(t, add_special_tokens=False).ids, 2], dtype="<u4").tobytes()


def test_other_tokenizers_encode_whole_texts():
    import public_tokenizers

    e = tokenizer.Encoder(tokenizer.vocabulary(public_tokenizers.path("byte_bpe_50k.json")), 7)
    assert not e.by_word
    assert e.encode([b"a  b"]) == [np.array([*e.model.encode("a  b", add_special_tokens=False).ids, 7], dtype="<u4").tobytes()]


@pytest.mark.parametrize("kept", [["NFC", "Replace"], ["Replace"], []])
def test_tokenizers_that_keep_case(kept):
    import json

    spec = json.loads(tokenizer.vocabulary())
    spec["normalizer"] = {"type": "Sequence", "normalizers": [s for s in spec["normalizer"]["normalizers"] if s["type"] in kept]} if kept else None
    e = tokenizer.Encoder(json.dumps(spec))
    for t in ("Hello World ABC test", "hello", "a  B\tc.", ""):
        assert e.encode([t.encode()]) == [np.array([*e.model.encode(t, add_special_tokens=False).ids, 2], dtype="<u4").tobytes()]


def test_small_caches_change_nothing(monkeypatch):
    monkeypatch.setattr(tokenizer, "ROUND_BYTES", 30)
    monkeypatch.setattr(tokenizer, "CACHE_PIECES", 2)
    e = tokenizer.Encoder(tokenizer.vocabulary())
    texts = [f"alpha beta{i}. gamma{i}, alpha!" for i in range(50)]
    assert e.encode([t.encode() for t in texts]) == ENCODER.encode([t.encode() for t in texts])


@given(st.lists(st.integers(1, 300), max_size=60), st.sampled_from([16, 64, 128]))
@settings(max_examples=200, deadline=None)
def test_harmonic_plan(lengths, capacity):
    plan = packing.harmonic_plan(lengths, capacity)
    spans = defaultdict(list)
    for seq in plan:
        size = sum(n for _, _, n in seq)
        assert 0 < size <= capacity and (size == capacity or size & (size - 1) == 0)
        for i, at, n in seq:
            spans[i].append((at, n))
    for i, length in enumerate(lengths):
        end = 0
        for at, n in sorted(spans[i]):
            assert at == end and n > 0
            end = at + n
        assert end == length
    assert sum(sum(n for _, _, n in s) < capacity for s in plan) <= capacity.bit_length()


def check_pieces(rows, texts, plain):
    """texts: list of (doc_id, text); pieces of equal documents are told apart by content only."""
    ids = defaultdict(list)
    for d, t in texts:
        ids[d].append(plain(t))
    got = defaultdict(int)
    for r in rows:
        assert any(len(x) == r["doc_tokens"] and zlib.crc32(x[r["start"] : r["start"] + r["length"]].tobytes()) == r["ids_crc32"] for x in ids[r["doc_id"]])
        got[r["doc_id"]] += r["length"]
    assert got == {d: sum(map(len, x)) for d, x in ids.items()}
    by_sequence = defaultdict(list)
    for r in rows:
        by_sequence[r["sequence_id"]].append((r["offset"], r["length"]))
    for spans in by_sequence.values():
        end = 0
        for at, n in sorted(spans):
            assert at == end
            end += n
        assert end <= 4096 and (end == 4096 or end & (end - 1) == 0)


def test_packing_odd_documents(odd_documents, plain):
    texts = [(r["doc_id"], r["text"]) for r in odd_documents.collect()]
    check_pieces(packing.pack(odd_documents).collect(), texts, plain)
    with_ids = packing.pack(odd_documents, with_ids=True).collect()
    assert all(zlib.crc32(r["ids"]) == r["ids_crc32"] and len(r["ids"]) == 4 * r["length"] for r in with_ids)


def test_op1_on_a_table(spark, sf, plain):
    from lossygrad.llm.queries import QUERIES

    texts = [(r["doc_id"], r["text"]) for r in spark.read.parquet(f"{sf}/documents.parquet").collect()]
    check_pieces(QUERIES["op1_harmonic_packing"](spark, sf).collect(), texts, plain)


def check_file_rows(rows, texts, plain):
    start = 0
    from xxhash import xxh64_intdigest

    def drawn(t):
        h = 42 if t is None else xxh64_intdigest(t.encode(), 42)
        return h - (h >> 63 << 64)

    order = sorted(texts, key=lambda x: (x[0] is not None, x[0] or 0, drawn(x[1])))
    rows = sorted(rows, key=lambda r: r["start"])
    assert len(rows) == len(order)
    for r, (d, t) in zip(rows, order, strict=True):
        ids = plain(t)
        assert (r["doc_id"], r["start"], r["n_tokens"], r["ids_crc32"]) == (d, start, len(ids), zlib.crc32(ids.tobytes()))
        start += len(ids)


def test_token_file_odd_documents(odd_documents, plain):
    check_file_rows(token_file.encode_and_read_back(odd_documents, sequence=64).collect(), [(r["doc_id"], r["text"]) for r in odd_documents.collect()], plain)


def test_token_file_shards_change_nothing(spark, sf, plain, odd_documents, tmp_path):
    from lossygrad.llm import common

    docs = spark.read.parquet(f"{sf}/documents.parquet").select("doc_id", "text").unionByName(odd_documents.select("doc_id", "text"))
    shards = token_file.write_shards(docs, common.fresh_path(spark, "tokens"), shard_bytes=20_000)
    assert len(shards) > 5
    check_file_rows(token_file.read_documents(spark, shards).collect(), [(r["doc_id"], r["text"]) for r in docs.collect()], plain)


def test_op10_on_a_table(spark, sf, plain):
    from lossygrad.llm.queries import QUERIES

    check_file_rows(QUERIES["op10_token_file"](spark, sf).collect(), [(r["doc_id"], r["text"]) for r in spark.read.parquet(f"{sf}/documents.parquet").collect()], plain)


def test_token_file_sequences(tmp_path):
    ids = np.arange(1000, dtype="<u4")
    path = str(tmp_path / "a.arrow")
    with open(path, "wb") as f:
        w = token_file.ShardWriter(f, 64, "<u2")
        w.add(ids[:700].tobytes())
        w.add(ids[700:].tobytes())
        w.close()
    r = token_file.ShardReader(path)
    values, mask = r.sequence_at(3)
    assert values.tolist() == list(range(192, 256)) and mask.all() and not values.flags.owndata
    values, mask = r.sequence_at(15)
    assert mask.sum() == 1000 - 15 * 64 and values[mask].tolist() == list(range(960, 1000))
    assert np.concatenate(list(r.views(690, 20))).tolist() == list(range(690, 710))


def test_empty_tables(no_documents):
    assert packing.pack(no_documents).count() == 0
    assert token_file.encode_and_read_back(no_documents).count() == 0


def test_shared_folder_can_be_cleared(spark, odd_documents):
    import os

    from lossygrad.llm import common

    kept = common.cut_lineage(odd_documents.select("doc_id"))
    path = kept.inputFiles()[0].removeprefix("file://").removeprefix("file:")
    assert kept.count() == 13 and os.path.exists(path)
    common.clear(spark)
    assert not os.path.exists(path)
