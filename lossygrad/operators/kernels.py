"""Vector kernels in numpy, for Arrow workers: quantize, encode to bytes and back.

They follow the column expressions of ``functions.quantization`` and ``functions.codes``.
"""

from __future__ import annotations

import struct
from functools import lru_cache

import numpy as np

from lossygrad.functions.uniform import uniform_array

CODECS = ("float32", "fixed", "gap", "dense_omega", "dense_prefix", "auto")


def scale32(r: float) -> np.float32:
    f = np.float32(r)
    return np.nextafter(f, np.float32(np.inf)) if float(f) < r else f


def scale_of(v: np.ndarray, norm: str = "l2") -> np.float32:
    if norm not in ("l2", "max"):
        raise ValueError(f"unknown norm {norm}")
    if not len(v):
        return np.float32(0)
    if not np.isfinite(v).all():
        raise ValueError("vector with a NaN or infinite value")
    return scale32(float(np.sqrt(v @ v)) if norm == "l2" else float(np.abs(v).max()))


def quantize(v: np.ndarray, s: int, norm: str = "l2", keys: tuple[int, ...] = (0,), first: int = 0, rounding: str = "random") -> tuple[np.float32, np.ndarray, np.ndarray]:
    """(scale, sign, level) of a vector; coordinate i draws with ``keys`` and ``first + i``."""
    if s < 1:
        raise ValueError("levels must be at least 1")
    scale = scale_of(v, norm)
    sign = np.where(v < 0, -1, 1).astype(np.int8)
    if scale == 0:
        return scale, sign, np.zeros(len(v), np.int32)
    pos = np.minimum(np.abs(v) / float(scale), 1.0) * s
    low = np.minimum(np.floor(pos), s - 1)
    u = uniform_array(len(v), *keys, start=first) if rounding == "random" else None
    up = (pos - low >= 0.5) if u is None else (u < pos - low)
    return scale, sign, (low + up).astype(np.int32)


def quantize_buckets(v: np.ndarray, d: int, s: int, keys: tuple[int, ...] = (0,), first: int = 0, rounding: str = "random") -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(scales, sign, level) of all buckets of d values at once, by largest magnitude; the same as ``quantize`` bucket by bucket."""
    if s < 1:
        raise ValueError("levels must be at least 1")
    if not np.isfinite(v).all():
        raise ValueError("vector with a NaN or infinite value")
    n = len(v)
    count = -(-n // d)
    size = np.zeros(count * d)
    size[:n] = np.abs(v)
    top = size.reshape(count, d).max(axis=1, initial=0.0)
    scales = top.astype(np.float32)
    scales = np.where(scales.astype(float) < top, np.nextafter(scales, np.float32(np.inf)), scales)
    each = np.repeat(scales.astype(float), d)[:n]
    pos = np.minimum(np.divide(size[:n], each, out=np.zeros(n), where=each > 0), 1.0) * s
    low = np.minimum(np.floor(pos), s - 1)
    up = (pos - low >= 0.5) if rounding != "random" else (uniform_array(n, *keys, start=first) < pos - low)
    return scales, np.where(v < 0, -1, 1).astype(np.int8), np.where(each > 0, low + up, 0).astype(np.int32)


def pack_fixed(scales: np.ndarray, sign: np.ndarray, level: np.ndarray, bits: int) -> bytes:
    """Scales of all buckets, then a sign and bits - 1 level bits a value."""
    raw = level.astype(np.uint8) | ((sign < 0).astype(np.uint8) << (bits - 1))
    if bits in (2, 4, 8):  # whole values in a byte: shift and join instead of single bits
        per = 8 // bits
        cells = np.zeros(-(-len(raw) // per) * per, np.uint8)
        cells[: len(raw)] = raw
        cells = cells.reshape(-1, per) << (np.arange(per - 1, -1, -1, dtype=np.uint8) * np.uint8(bits))
        return scales.astype("<f4").tobytes() + np.bitwise_or.reduce(cells, axis=1).tobytes()
    lanes = (raw[:, None] >> np.arange(bits - 1, -1, -1, dtype=np.uint8)) & 1
    return scales.astype("<f4").tobytes() + np.packbits(lanes.astype(np.uint8)).tobytes()


def unpack_fixed(payload: bytes, n: int, d: int, bits: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    count = -(-n // d)
    if len(payload) < 4 * count + -(-n * bits // 8):
        raise ValueError("truncated message")
    scales, body = np.frombuffer(payload, "<f4", count), np.frombuffer(payload, np.uint8)[4 * count :]
    if bits in (2, 4, 8):
        per = 8 // bits
        raw = (body[:, None] >> (np.arange(per - 1, -1, -1, dtype=np.uint8) * np.uint8(bits))).ravel()[:n] & np.uint8((1 << bits) - 1)
    else:
        raw = (np.unpackbits(body, count=n * bits).reshape(n, bits) @ (1 << np.arange(bits - 1, -1, -1))).astype(np.uint8)
    return scales, np.where(raw >> (bits - 1), -1, 1).astype(np.int8), (raw & np.uint8((1 << (bits - 1)) - 1)).astype(np.int32)


def dequantize(scale: float, sign: np.ndarray, level: np.ndarray, s: int) -> np.ndarray:
    return float(scale) * sign * level / s


@lru_cache(maxsize=1 << 16)
def omega(k: int) -> str:
    bits = "0"
    while k > 1:
        b = bin(k)[2:]
        bits, k = b + bits, len(b) - 1
    return bits


def omega_read(bits: str, at: int) -> tuple[int, int]:
    """The integer that starts at ``at`` and where it ends."""
    k = 1
    while bits[at] == "1":
        k, at = int(bits[at : at + k + 1], 2), at + k + 1
    return k, at + 1


def _prefix(k: int, sign: int) -> str:
    if k == 0:
        return "00"
    if k == 1:
        return "01" if sign > 0 else "10"
    return "11" + "1" * (k - 2) + "0" + ("0" if sign > 0 else "1")


def _body(codec: str, sign: np.ndarray, level: np.ndarray, bits: int) -> str:
    if codec == "gap":
        at = np.flatnonzero(level)
        steps = np.diff(np.concatenate([[-1], at]))
        return "".join([omega(g) + ("1" if sg < 0 else "0") + omega(k) for g, sg, k in zip(steps.tolist(), sign[at].tolist(), level[at].tolist(), strict=True)])
    if codec == "dense_omega":
        return "".join([omega(k + 1) + ("" if not k else "1" if sg < 0 else "0") for k, sg in zip(level.tolist(), sign.tolist(), strict=True)])
    if codec == "dense_prefix":
        return "".join([_prefix(k, sg) for k, sg in zip(level.tolist(), sign.tolist(), strict=True)])
    raise ValueError(f"unknown codec {codec}")


def encode(codec: str, scale: float, sign: np.ndarray, level: np.ndarray, bits: int = 4) -> tuple[str, int, bytes]:
    """(codec, bits used, payload).  ``auto`` takes the shortest and counts a 3-bit header."""
    if codec == "auto":
        made = [encode(c, scale, sign, level, bits) for c in ("dense_omega", "dense_prefix", "fixed", "gap")]
        name, n, payload = min(made, key=lambda m: (m[1], m[0]))
        return name, n + 3, payload
    head = struct.pack("<f", scale)
    if codec == "fixed":
        if len(level) and int(level.max()) >= 1 << (bits - 1) and bits > 1:
            raise ValueError(f"a level needs more than {bits} bits")
        raw = level.astype(np.uint8) | ((sign < 0).astype(np.uint8) << (bits - 1))
        lanes = (raw[:, None] >> np.arange(bits - 1, -1, -1, dtype=np.uint8)) & 1
        return codec, 32 + bits * len(level), head + np.packbits(lanes.astype(np.uint8)).tobytes()
    body = _body(codec, sign, level, bits)
    packed = np.packbits(np.frombuffer(body.encode(), np.uint8) - 48).tobytes() if body else b""
    return codec, 32 + len(body), head + packed


def decode(codec: str, payload: bytes, n: int, n_bits: int, bits: int = 4) -> tuple[np.float32, np.ndarray, np.ndarray]:
    """(scale, sign, level) of n coordinates; ``n_bits`` counts the scale but no header."""
    if len(payload) < 4 or len(payload) < -(-n_bits // 8):
        raise ValueError("truncated message")
    scale = np.float32(struct.unpack("<f", payload[:4])[0])
    lanes = np.unpackbits(np.frombuffer(payload, np.uint8)[4:], count=n_bits - 32)
    sign, level = np.ones(n, np.int8), np.zeros(n, np.int32)
    if codec == "fixed":
        grid = lanes.reshape(n, bits).astype(np.int32)
        level[:] = grid[:, 1:] @ (1 << np.arange(bits - 2, -1, -1)) if bits > 1 else 0
        sign[:] = np.where(grid[:, 0] == 1, -1, 1)
        return scale, sign, level
    text = (lanes + 48).tobytes().decode()
    at = 0
    if codec == "gap":
        where = -1
        while at < len(text):
            gap, at = omega_read(text, at)
            where += gap
            sign[where] = -1 if text[at] == "1" else 1
            level[where], at = omega_read(text, at + 1)
    elif codec == "dense_omega":
        for i in range(n):
            k, at = omega_read(text, at)
            level[i] = k - 1
            if k > 1:
                sign[i] = -1 if text[at] == "1" else 1
                at += 1
    elif codec == "dense_prefix":
        for i in range(n):
            two, at = text[at : at + 2], at + 2
            if two == "11":
                end = text.index("0", at)
                level[i], sign[i], at = 2 + end - at, -1 if text[end + 1] == "1" else 1, end + 2
            elif two != "00":
                level[i], sign[i] = 1, 1 if two == "01" else -1
    else:
        raise ValueError(f"unknown codec {codec}")
    return scale, sign, level


def topk(v: np.ndarray, k: int | None = None, frac: float | None = None, cover: str | None = None) -> np.ndarray:
    """The vector with its largest magnitudes only; ties by place.

    ``cover='l2'``: the shortest prefix by magnitude whose absolute sum reaches the 2-norm,
    each kept value replaced by the norm with its sign.
    """
    order = np.lexsort((np.arange(len(v)), -np.abs(v)))
    out = np.zeros(len(v))
    if cover == "l2":
        norm = float(np.sqrt(v @ v))
        if norm:
            n = int(np.searchsorted(np.cumsum(np.abs(v[order])), norm * (1 - 1e-12)) + 1)
            out[order[:n]] = norm * np.sign(v[order[:n]])
        return out
    n = k if k is not None else int(np.ceil((frac or 0) * len(v)))
    out[order[:n]] = v[order[:n]]
    return out


def onebit(w: np.ndarray, scale: str = "mean_abs") -> np.ndarray:
    """Signs times the mean magnitude, or times the means of either sign's values."""
    if not len(w):
        return w
    if scale == "mean_abs":
        return np.where(w < 0, -1.0, 1.0) * np.float32(np.abs(w).mean())
    if scale == "two_means":
        out = np.zeros(len(w))
        for part in (w < 0, w >= 0):
            if part.any():
                out[part] = np.float32(w[part].mean())
        return out
    raise ValueError(f"unknown scale {scale}")


def reduced(v: np.ndarray, kind: str) -> tuple[np.ndarray, int]:
    """Plain reduced precision and its bits a value: float16, bfloat16, or fixedB."""
    if kind == "float16":
        return v.astype(np.float16).astype(float), 16
    if kind == "bfloat16":
        raw = v.astype(np.float32).view(np.uint32)
        return (raw & np.uint32(0xFFFF0000)).view(np.float32).astype(float), 16
    if kind.startswith("fixed"):
        b = int(kind.removeprefix("fixed"))
        top = float(np.abs(v).max()) if len(v) else 0.0
        levels = 2 ** (b - 1) - 1
        return (np.round(v / top * levels) / levels * top if top else v * 0.0), b
    raise ValueError(f"unknown kind {kind}")
