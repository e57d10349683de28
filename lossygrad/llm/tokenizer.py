"""Exact, cached encoding with the tokenizers library.

For tokenizers that lower-case, split on white space and drop it, the ids of a text are the
ids of its words in order.  Arrow splits texts and numbers their distinct words, the
library encodes each distinct piece once, and numpy gathers the ids of the texts.  Other tokenizers encode
whole texts.  Either way the ids are those of ``encode(text)``.
"""

from __future__ import annotations

import json
import os
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc

from lossygrad.llm import common

#: Distinct pieces of words whose ids a worker keeps before it starts anew (bounds memory).
CACHE_PIECES = 500_000
#: Bytes of text that are encoded together; a longer text is a round of its own.
ROUND_BYTES = 4 << 20
#: ASCII punctuation that may end a word; it never shares a pre-token with an ASCII letter before it.
_TAIL = "".join(chr(c) for c in range(33, 127) if not chr(c).isalnum())
_LETTERS = np.zeros(256, bool)
_LETTERS[list(b"abcdefghijklmnopqrstuvwxyzABCDEFGHIJKLMNOPQRSTUVWXYZ")] = True


def vocabulary(path: str | None = None) -> str:
    """The tokenizer file's content; by default the public word-level BPE."""
    if path is None:
        import public_tokenizers

        path = public_tokenizers.path("word_bpe_49k.json")
    with open(path, encoding="utf-8") as f:
        return f.read()


def drops_white_space(spec: dict) -> bool:
    pre = spec.get("pre_tokenizer") or {}
    steps = pre.get("pretokenizers", [pre])
    return any(
        s.get("type") == "Split" and s.get("behavior") == "Removed" and s.get("invert") and "[^\\s" in json.dumps(s.get("pattern")).replace("\\\\", "\\")
        for s in steps
    )


def lower_cases(spec: dict) -> bool:
    """Whether the normalizer composes, folds white space and lower-cases, and does nothing else."""
    norm = spec.get("normalizer") or {}
    steps = norm.get("normalizers", [norm])
    plain = all(s.get("type") in ("NFC", "Lowercase") or (s.get("type") == "Replace" and s.get("pattern") == {"Regex": "\\s+"} and s.get("content") == " ") for s in steps)
    return plain and any(s.get("type") == "Lowercase" for s in steps)


class Encoder:
    """Encodes UTF-8 texts into little-endian unsigned 32-bit ids, as bytes."""

    def __init__(self, content: str, end_id: int | None = 2):
        os.environ.setdefault("TOKENIZERS_PARALLELISM", "false")
        from tokenizers import Tokenizer

        spec = json.loads(content)
        self.model = Tokenizer.from_str(content)
        self.end = b"" if end_id is None else int(end_id).to_bytes(4, "little")
        marks = [t for t in spec.get("added_tokens", []) if not (t["normalized"] or t["lstrip"] or t["rstrip"] or t["single_word"])]
        self.mark, self.mark_id = (marks[0]["content"], marks[0]["id"]) if marks else ("", -1)
        self.by_word = bool(marks) and drops_white_space(spec) and lower_cases(spec)
        suffix = spec.get("model", {}).get("end_of_word_suffix")
        self.splits_by_end = bool(suffix)
        self.ends_word = np.zeros(self.model.get_vocab_size(with_added_tokens=True) + 1, bool)
        if suffix:
            self.ends_word[[i for t, i in self.model.get_vocab().items() if t.endswith(suffix)]] = True
        self.pieces: dict[bytes, bytes] = {}

    def _plain(self, texts: list[str]) -> list[np.ndarray]:
        return [np.asarray(e.ids, dtype="<u4") for e in self.model.encode_batch_fast(texts, add_special_tokens=False)]

    def _piece_ids(self, pieces: list[bytes]) -> list[bytes]:
        """Ids of distinct pieces, from the cache or the library."""
        found = list(map(self.pieces.get, pieces))
        fresh = [i for i, x in enumerate(found) if x is None]
        if not fresh:
            return found
        single, usual = [], []
        for i in fresh:
            w = pieces[i]
            if w.isalpha() or w.decode().isalpha():
                single.append(i)
            elif b"<" in w or not w:
                found[i] = self._plain([w.decode()])[0].tobytes()
            else:
                usual.append(i)
        for at in range(0, len(single), 8192):
            # Each is one pre-token, whose last id alone ends a word.
            part = single[at : at + 8192]
            ids = self._plain([b" ".join([pieces[i] for i in part]).decode()])[0]
            ends = np.flatnonzero(self.ends_word[ids]) + 1
            if not self.splits_by_end or len(ends) != len(part):
                usual += part
                continue
            self._cut(found, part, ids, 4 * ends, 0)
        for at in range(0, len(usual), 8192):
            part = usual[at : at + 8192]
            ids = self._plain([self.mark.join([pieces[i].decode() for i in part])])[0]
            self._cut(found, part, ids, 4 * np.append(np.flatnonzero(ids == self.mark_id), len(ids)), 4)
        if len(self.pieces) > CACHE_PIECES:
            self.pieces.clear()
        self.pieces.update((pieces[i], found[i]) for i in fresh)
        return found

    @staticmethod
    def _cut(found: list, part: list[int], ids: np.ndarray, stops: np.ndarray, skip: int) -> None:
        raw, begin = ids.tobytes(), 0
        for i, stop in zip(part, stops.tolist(), strict=True):
            found[i] = raw[begin:stop]
            begin = stop + skip

    def _distinct(self, words: pa.Array) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """Of distinct words: all their ids, and each word's first place and number of them.

        A word whose last letter before final punctuation is ASCII is a core, lower-cased
        if all ASCII, and a tail; the library encodes both alike alone and together.
        """
        cores = pc.ascii_rtrim(words, characters=_TAIL)
        data = np.frombuffer(cores.buffers()[2] or b"\0", np.uint8)
        ends = np.frombuffer(cores.buffers()[1], np.int32)[cores.offset : cores.offset + len(cores) + 1]
        sizes = np.diff(ends)
        cut = (sizes > 0) & _LETTERS[data[np.maximum(ends[1:] - 1, 0)]]
        cut &= ~pc.match_substring(words, "<").to_numpy(zero_copy_only=False)
        folded = pc.if_else(pc.and_(pa.array(cut), pc.string_is_ascii(cores)), pc.ascii_lower(cores), pc.if_else(pa.array(cut), cores, words))
        whole = np.diff(np.frombuffer(words.buffers()[1], np.int32)[words.offset : words.offset + len(words) + 1])
        tailed = np.flatnonzero(cut & (whole > sizes))
        # Tails: what is left of the word, read from its bytes.
        raw = np.frombuffer(words.buffers()[1], np.int32)[words.offset : words.offset + len(words) + 1]
        text = words.buffers()[2]
        view = memoryview(text) if text is not None else memoryview(b"")
        tails = [bytes(view[a:b]) for a, b in zip((raw[tailed] + sizes[tailed]).tolist(), raw[tailed + 1].tolist(), strict=True)]
        both = pa.concat_arrays([folded.cast(pa.binary()), pa.array(tails, pa.binary())]).dictionary_encode()
        at = both.indices.to_numpy(zero_copy_only=False)
        ids = self._piece_ids(both.dictionary.to_pylist())
        length = np.fromiter(map(len, ids), np.int64, len(ids)) // 4
        flat, first = np.frombuffer(b"".join(ids), "<u4"), np.cumsum(length) - length
        # Pieces in word order: each word's core, then its tail.
        n = len(words)
        counts = np.ones(n, np.int64)
        counts[tailed] = 2
        place = np.cumsum(counts) - counts
        order = np.empty(counts.sum(), np.int64)
        order[place] = at[:n]
        order[place[tailed] + 1] = at[n:]
        out = flat[_spans(first[order], length[order])]
        per_word = np.add.reduceat(length[order], place) if n else np.zeros(0, np.int64)
        return out, np.cumsum(per_word) - per_word, per_word

    def encode_array(self, texts: pa.Array) -> tuple[np.ndarray, np.ndarray]:
        """All ids of a string array, with the end ids, and each text's bounds (n + 1 places)."""
        n = len(texts)
        if not self.by_word:
            made = [np.frombuffer(i.tobytes() + self.end, "<u4") for i in self._plain([t or "" for t in texts.to_pylist()])]
            return (np.concatenate(made) if made else np.zeros(0, "<u4")), np.cumsum([0, *map(len, made)])
        words, number, bounds = common.arrow_words(texts)
        flat, first, length = self._distinct(words)
        sizes = length[number]
        ids = flat[_spans(first[number], sizes)] if len(number) else np.zeros(0, "<u4")
        ends = np.concatenate([[0], np.cumsum(sizes)])[bounds]
        if self.end:
            ids = np.insert(ids, ends[1:], np.frombuffer(self.end, "<u4")[0])
            ends = ends + np.arange(n + 1)
        return ids.astype("<u4", copy=False), ends

    def rounds(self, texts: pa.Array) -> Iterator[tuple[int, bytes, list[int]]]:
        """(first text, ids as bytes, byte bounds of each text) for runs of texts of bounded size."""
        sizes = np.cumsum(pc.fill_null(pc.binary_length(texts), 0).to_numpy(zero_copy_only=False))
        at = 0
        while at < len(texts):
            before = sizes[at - 1] if at else 0
            stop = max(at + 1, int(np.searchsorted(sizes, before + ROUND_BYTES, side="right")))
            part = texts.slice(at, stop - at)
            if int(sizes[stop - 1] - before) > 1 << 30:
                part = part.cast(pa.large_string())
            ids, ends = self.encode_array(pa.concat_arrays([part]))
            yield at, ids.tobytes(), (4 * ends).tolist()
            at = stop

    def encode(self, texts: list[bytes]) -> list[bytes]:
        """Ids of each text, with the end id."""
        out = []
        for _, raw, ends in self.rounds(pa.array([t.decode() for t in texts], pa.string())):
            out += [raw[a:b] for a, b in zip(ends[:-1], ends[1:], strict=True)]
        return out


def _spans(first: np.ndarray, length: np.ndarray) -> np.ndarray:
    """Places first, first + 1, ... of each span, one after the other."""
    return np.repeat(first - (np.cumsum(length) - length), length) + np.arange(length.sum())


_BUILT: dict[tuple[int, int | None], Encoder] = {}


def encoder(content: str, end_id: int | None = 2) -> Encoder:
    """One encoder per worker process, kept between tasks."""
    key = (hash(content), end_id)
    if key not in _BUILT:
        _BUILT.clear()
        _BUILT[key] = Encoder(content, end_id)
    return _BUILT[key]
