"""A channel: what a gradient becomes between workers, and what it costs."""

from __future__ import annotations

from dataclasses import dataclass, field

import numpy as np

from lossygrad.functions.quantization import levels_from_bits
from lossygrad.operators import kernels, wire


#: Values of neighbouring buckets that share a message.
GROUP = 1 << 16


@dataclass(frozen=True)
class Channel:
    """``codec`` float32, fixed, gap, dense_omega, dense_prefix, auto, onebit, topk or reduced.

    ``s`` levels (a number, 'sqrt' of the bucket size, or None: from ``bits``); ``bucket``
    None quantizes the vector whole.  ``layers``: (first, length, bits) spans that override
    ``bits``; 32 sends the span at full precision.  ``noise`` adds Gaussian noise of that share
    of the gradient's size; ``like`` adds as much as that channel's quantization would.
    """

    codec: str = "float32"
    bits: int = 32
    bucket: int | None = None
    norm: str = "max"
    s: int | str | None = None
    rounding: str = "random"
    seed: int = 0
    carry: bool = True
    scale: str = "mean_abs"
    kind: str = "bfloat16"
    frac: float = 0.1
    cover: str | None = None
    layers: tuple[tuple[int, int, int], ...] = ()
    noise: float = 0.0
    like: Channel | None = None

    @property
    def whole(self) -> bool:
        """Whether a gradient is sent as one message, not by bucket."""
        return self.codec in ("onebit", "topk", "reduced") or bool(self.noise) or self.like is not None

    def added_variance(self, v: np.ndarray) -> float:
        """What random rounding adds to a vector's squared error, summed over coordinates."""
        total = 0.0
        for first, length, bits in self.spans(len(v)):
            piece = v[first : first + length]
            scale = float(kernels.scale_of(piece, self.norm))
            if bits == 32 or self.codec == "float32" or not scale:
                continue
            s = self.levels(length, bits)
            pos = np.minimum(np.abs(piece) / scale, 1.0) * s
            part = pos - np.minimum(np.floor(pos), s - 1)
            total += float((scale / s) ** 2 * (part * (1 - part)).sum())
        return total

    def payload(self, sent: np.ndarray) -> tuple[str, int, bytes]:
        """(code, kept values, bytes) of what a baseline sends."""
        if self.codec == "onebit":
            return "onebit", 0, wire.pack_onebit(sent, self.bucket or max(len(sent), 1), self.scale != "mean_abs")
        if self.codec == "topk":
            return "topk", *wire.pack_topk(sent, bool(self.cover))
        if self.codec == "reduced":
            return "reduced", 0, wire.pack_reduced(sent, self.kind)
        return "float32", 0, sent.astype("<f4").tobytes()

    def levels(self, n: int, bits: int | None = None) -> int:
        if self.s == "sqrt":
            return max(1, int(np.sqrt(n)))
        return self.s if self.s is not None else levels_from_bits(bits or self.bits)

    def spans(self, n: int) -> list[tuple[int, int, int]]:
        """(first, length, bits) of every bucket."""
        out = []
        whole = 0 if self.s is not None and self.bits == 32 else self.bits  # 0: the levels are given by s
        for first, length, bits in self.layers or ((0, n, whole),):
            d = self.bucket or length
            if bits == 32:
                out.append((first, length, 32))
            else:
                out += [(at, min(d, first + length - at), bits) for at in range(first, first + length, d)]
        return out

    @property
    def joins_buckets(self) -> bool:
        """Whether neighbouring buckets share a message: fixed width, scaled by largest magnitude."""
        return self.codec == "fixed" and self.norm == "max"

    def groups(self, n: int) -> list[tuple[int, int, int]]:
        """(first, length, bits) of spans of whole buckets, of about ``GROUP`` values."""
        out = []
        whole = 0 if self.s is not None and self.bits == 32 else self.bits
        for first, length, bits in self.layers or ((0, n, whole),):
            d = self.bucket or length
            step = length if bits == 32 else max(1, GROUP // max(d, 1)) * d
            out += [(at, min(step, first + length - at), bits) for at in range(first, first + length, max(step, 1))]
        return out

    def _joined(self, piece: np.ndarray, first: int, bits: int, keys: tuple[int, ...]):
        d = self.bucket or max(len(piece), 1)
        s = self.levels(d, bits)
        scales, sign, level = kernels.quantize_buckets(piece, d, s, (self.seed, *keys), first, self.rounding)
        width = max(2, int(np.ceil(np.log2(s + 1))) + 1)
        return d, s, width, scales, sign, level

    def parts(self, v: np.ndarray, *keys: int):
        """(number, first, length, s, codec, n_bits, scale, nnz, payload) of each message of a quantized vector:
        a bucket, or neighbouring ones (the scale is then the first one's)."""
        if self.joins_buckets:
            for b, (first, length, bits) in enumerate(self.groups(len(v))):
                piece = v[first : first + length]
                if bits == 32:
                    yield b, first, length, 0, "float32", 32 * length, np.float32(0), int(np.count_nonzero(piece)), piece.astype("<f4").tobytes()
                    continue
                d, s, width, scales, sign, level = self._joined(piece, first, bits, keys)
                yield b, first, length, s, "fixed", 32 * len(scales) + width * length, scales[0], int((level > 0).sum()), kernels.pack_fixed(scales, sign, level, width)
            return
        for b, (first, length, bits) in enumerate(self.spans(len(v))):
            piece = v[first : first + length]
            if bits == 32 or self.codec == "float32":
                yield b, first, length, 0, "float32", 32 * length, np.float32(0), int(np.count_nonzero(piece)), piece.astype("<f4").tobytes()
                continue
            s = self.levels(length, bits)
            scale, sign, level = kernels.quantize(piece, s, self.norm, (self.seed, *keys), first, self.rounding)
            width = max(2, int(np.ceil(np.log2(s + 1))) + 1) if self.codec in ("fixed", "auto") else bits
            codec, n_bits, payload = kernels.encode(self.codec, scale, sign, level, width)
            yield b, first, length, s, codec, n_bits, scale, int((level > 0).sum()), payload

    def restore(self, codec: str, payload: bytes, length: int, n_bits: int, s: int) -> np.ndarray:
        """The values of a message; ``s`` is its number of levels (of kept values, of truncated ones)."""
        if codec == "float32":
            return np.frombuffer(payload, "<f4").astype(float)
        if codec == "onebit":
            return wire.unpack_onebit(payload, length, self.bucket or max(length, 1), self.scale != "mean_abs")
        if codec == "topk":
            return wire.unpack_topk(payload, length, s, bool(self.cover))
        if codec == "reduced":
            return wire.unpack_reduced(payload, self.kind)
        if self.joins_buckets:
            d, width = self.bucket or max(length, 1), max(2, int(np.ceil(np.log2(s + 1))) + 1)
            scales, sign, level = kernels.unpack_fixed(payload, length, d, width)
            return np.repeat(scales.astype(float), d)[:length] * sign * level / s
        header = 3 if self.codec == "auto" else 0
        width = max(2, int(np.ceil(np.log2(s + 1))) + 1)
        scale, sign, level = kernels.decode(codec, payload, length, n_bits - header, width)
        return kernels.dequantize(scale, sign, level, s)

    def send(self, v: np.ndarray, *keys: int, state: dict | None = None) -> tuple[np.ndarray, int]:
        """What the others receive of v, and its bits.  ``state`` carries errors of one-bit channels.

        Lossless codes are not run here (they change nothing but the count): their
        lengths are computed, and tests hold them against real payloads.
        """
        n = len(v)
        if self.noise:
            r = np.random.default_rng([self.seed, *[k & 0x7FFFFFFF for k in keys]])
            v = v + r.normal(0, self.noise * np.sqrt(v @ v / max(n, 1)), n)
        if self.like is not None:
            r = np.random.default_rng([self.seed, *[k & 0x7FFFFFFF for k in keys]])
            v = v + r.normal(0, np.sqrt(self.like.added_variance(v) / max(n, 1)), n)
        if self.codec == "float32":
            return v.astype(np.float32).astype(float), 32 * n
        if self.codec == "onebit":
            d = self.bucket or max(n, 1)
            w = v + state["e"] if state and self.carry and "e" in state else v
            sent = np.concatenate([np.zeros(0), *(kernels.onebit(w[at : at + d], self.scale) for at in range(0, n, d))])
            if state is not None and self.carry:
                state["e"] = w - sent
            return sent, n + -(-n // d) * (32 if self.scale == "mean_abs" else 64)
        if self.codec == "topk":
            sent = kernels.topk(v, frac=self.frac, cover=self.cover).astype(np.float32).astype(float)
            at = np.flatnonzero(sent)
            steps = np.diff(np.concatenate([[-1], at]))
            return sent, 32 + int(sum(len(kernels.omega(int(g))) for g in steps)) + len(at) * (1 if self.cover else 32)
        if self.codec == "reduced":
            sent, each = kernels.reduced(v, self.kind)
            return sent, each * n + (64 if self.kind.startswith("fixed") else 0)
        out, total = np.empty(n), 0
        if self.joins_buckets:
            for first, length, bits in self.groups(n):
                piece = v[first : first + length]
                if bits == 32:
                    out[first : first + length], total = piece.astype(np.float32), total + 32 * length
                    continue
                d, s, width, scales, sign, level = self._joined(piece, first, bits, keys)
                out[first : first + length], total = np.repeat(scales.astype(float), d)[:length] * sign * level / s, total + 32 * len(scales) + width * length
            return out, total
        for first, length, bits in self.spans(n):
            piece = v[first : first + length]
            if bits == 32:
                out[first : first + length] = piece.astype(np.float32)
                total += 32 * length
                continue
            s = self.levels(length, bits)
            scale, sign, level = kernels.quantize(piece, s, self.norm, (self.seed, *keys), first, self.rounding)
            out[first : first + length] = kernels.dequantize(scale, sign, level, s)
            total += self._length(sign, level, s)
        return out, total

    def _length(self, sign: np.ndarray, level: np.ndarray, s: int) -> int:
        n = len(level)
        width = max(2, int(np.ceil(np.log2(s + 1))) + 1)
        if self.codec == "fixed":
            return 32 + width * n
        lengths = {}
        if self.codec in ("dense_prefix", "auto"):
            lengths["dense_prefix"] = 32 + int(np.where(level <= 1, 2, level + 2).sum())
        if self.codec in ("dense_omega", "auto"):
            k, c = np.unique(level, return_counts=True)
            lengths["dense_omega"] = 32 + sum(int(m) * (len(kernels.omega(int(i) + 1)) + (i > 0)) for i, m in zip(k, c, strict=True))
        if self.codec in ("gap", "auto"):
            at = np.flatnonzero(level)
            g, gc = np.unique(np.diff(np.concatenate([[-1], at])), return_counts=True)
            k, c = np.unique(level[at], return_counts=True)
            lengths["gap"] = 32 + len(at) + sum(int(m) * len(kernels.omega(int(i))) for i, m in [*zip(g, gc, strict=True), *zip(k, c, strict=True)])
        if self.codec == "auto":
            lengths["fixed"] = 32 + width * n
            return min(lengths.values()) + 3
        return lengths[self.codec]


@dataclass
class State:
    """Carried errors by worker."""

    by_worker: dict[int, dict] = field(default_factory=dict)

    def of(self, worker: int) -> dict:
        return self.by_worker.setdefault(worker, {})
