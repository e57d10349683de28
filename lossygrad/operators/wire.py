"""Bytes of the baselines' messages: what one-bit, truncated and reduced-precision senders put on the wire.

Each form holds just what its receiver needs, so the bytes follow the bits that the ledgers count:
signs and one or two scales a bucket, gap-coded places with values (or signs and one norm), or
values of 8 or 16 bits.  ``nnz`` travels in the message's row, as ``n`` does.
"""

from __future__ import annotations

import numpy as np

from lossygrad.operators import kernels


def _bits(text: str) -> bytes:
    return np.packbits(np.frombuffer(text.encode(), np.uint8) - 48).tobytes() if text else b""


def pack_onebit(sent: np.ndarray, bucket: int, two_means: bool) -> bytes:
    """Per bucket the value of positive signs (and of negative ones, if they differ), then all signs."""
    scales = []
    for at in range(0, len(sent), bucket):
        part = sent[at : at + bucket]
        low, high = part[part < 0], part[part >= 0]
        down, up = (low[0] if len(low) else 0.0), (high[0] if len(high) else 0.0)
        scales += [down, up] if two_means else [up if len(high) else -down]
    return np.array(scales, "<f4").tobytes() + np.packbits(sent < 0).tobytes()


def unpack_onebit(payload: bytes, n: int, bucket: int, two_means: bool) -> np.ndarray:
    each = 2 if two_means else 1
    count = -(-n // bucket) * each
    scales = np.frombuffer(payload, "<f4", count).astype(float).reshape(-1, each)
    down, up = (scales[:, 0], scales[:, 1]) if two_means else (-scales[:, 0], scales[:, 0])
    sign = np.unpackbits(np.frombuffer(payload, np.uint8)[4 * count :], count=n).astype(bool)
    at = np.arange(n) // bucket
    return np.where(sign, down[at], up[at])


def pack_topk(sent: np.ndarray, cover: bool) -> tuple[int, bytes]:
    """Number of kept values and their bytes: values (or the norm they share), then gaps (and signs) as bits."""
    at = np.flatnonzero(sent)
    gaps = np.diff(np.concatenate([[-1], at])).tolist()
    if cover:
        text = "".join(kernels.omega(g) + ("1" if sent[i] < 0 else "0") for g, i in zip(gaps, at.tolist(), strict=True))
        return len(at), np.array(np.abs(sent[at[:1]]), "<f4").tobytes() + _bits(text)
    return len(at), sent[at].astype("<f4").tobytes() + _bits("".join(map(kernels.omega, gaps)))


def unpack_topk(payload: bytes, n: int, nnz: int, cover: bool) -> np.ndarray:
    out = np.zeros(n)
    if not nnz:
        return out
    held = 1 if cover else nnz
    values = np.frombuffer(payload, "<f4", held).astype(float)
    text = (np.unpackbits(np.frombuffer(payload, np.uint8)[4 * held :]) + 48).tobytes().decode()
    where, at = -1, 0
    for i in range(nnz):
        gap, at = kernels.omega_read(text, at)
        where += gap
        if cover:
            out[where], at = (-values[0] if text[at] == "1" else values[0]), at + 1
        else:
            out[where] = values[i]
    return out


def pack_reduced(sent: np.ndarray, kind: str) -> bytes:
    if kind == "float16":
        return sent.astype("<f2").tobytes()
    if kind == "bfloat16":
        return (sent.astype("<f4").view("<u4") >> 16).astype("<u2").tobytes()
    levels = 2 ** (int(kind.removeprefix("fixed")) - 1) - 1
    top = float(np.abs(sent).max()) if len(sent) else 0.0
    width = "<i1" if levels < 128 else "<i2"
    return np.array([top], "<f8").tobytes() + (np.round(sent / top * levels) if top else sent * 0).astype(width).tobytes()


def unpack_reduced(payload: bytes, kind: str) -> np.ndarray:
    if kind == "float16":
        return np.frombuffer(payload, "<f2").astype(float)
    if kind == "bfloat16":
        return (np.frombuffer(payload, "<u2").astype("<u4") << 16).view("<f4").astype(float)
    levels = 2 ** (int(kind.removeprefix("fixed")) - 1) - 1
    top = float(np.frombuffer(payload, "<f8", 1)[0])
    return np.frombuffer(payload[8:], "<i1" if levels < 128 else "<i2").astype(float) / levels * top
