"""Theory: variance, sparsity, bits and rounds, as plain arithmetic.  log is base 2."""

from __future__ import annotations

import math


def variance(n: float, s: float) -> float:
    """Added variance, as a multiple of the squared norm."""
    return min(n / s**2, math.sqrt(n) / s)


def second_moment(n: float, s: float) -> float:
    return 1 + variance(n, s)


def nnz(n: float, s: float) -> float:
    return s * (s + math.sqrt(n))


def gap_bits(n: float, s: float) -> float:
    return (3 + 1.5 * math.log2(2 * (s**2 + n) / nnz(n, s))) * nnz(n, s) + 32


def gap_bits_alt(n: float, s: float) -> float:
    """As printed with the convergence guarantee: s^2 + sqrt(n) stands for s (s + sqrt(n))."""
    m = s**2 + math.sqrt(n)
    return (3 + 1.5 * math.log2(2 * (s**2 + n) / m)) * m + 32


def dense_bits(n: float) -> float:
    return 2.8 * n + 32


def omega_bound(k: int) -> float:
    """log k + log log k + ... + 1, over the positive terms."""
    total, x = 1.0, float(k)
    while x > 1:
        x = math.log2(x)
        total += max(x, 0.0)
    return total


def rounds(r: float, b: float, k: int, eps: float, smooth: float) -> float:
    """R is a distance; b is the second-moment or quantized variance bound."""
    return r**2 * max(2 * b / (k * eps**2), smooth / eps)


def quantized_b(n: float, s: float, b: float) -> float:
    return variance(n, s) * b


def sgd_gap(r: float, sigma2: float, t: int, smooth: float) -> float:
    return r * math.sqrt(2 * sigma2 / t) + smooth * r**2 / t


def minibatch_var(sigma2: float, m: int) -> float:
    return sigma2 / m


def contraction(p: int) -> float:
    return 0.9**p


def vr_bits(n: float, t: int, f: float = 32) -> float:
    return (f + 2.8 * n) * (t + 1) + f * n


def lower_bounds(n: float, eps: float) -> tuple[float, float]:
    """Orders only: constant blow-up, and two-processor minimisation."""
    return n, n * (math.log2(n) + math.log2(1 / eps))


def stationarity(smooth: float, gap: float, t: int, n: float, s: float, b: float) -> float:
    return math.sqrt(smooth * gap) / t + variance(n, s) * b / smooth


def bucket_variance(d: float, s: float) -> float:
    return variance(d, s)


def saving(n: float) -> float:
    """Saving against 32 bits a value after at most twice the rounds."""
    return 32 * n / (2.8 * n) / 2


def fixed_bits(bits: int, d: int) -> float:
    """Bits a value, with the bucket's scale."""
    return bits + 32 / d


def step_size(rule: str, smooth: float, r: float = 1.0, sigma2: float = 1.0, k: int = 1, t: int = 1) -> float:
    """``constant`` for one machine, ``parallel`` for k; sigma2 is the (quantized) variance bound."""
    gamma = r / math.sqrt(sigma2) * math.sqrt(2 / t)
    if rule == "constant":
        return 1 / (smooth + 1 / gamma)
    if rule == "parallel":
        return 1 / (smooth + math.sqrt(k) / gamma)
    raise ValueError(f"unknown rule {rule}")
