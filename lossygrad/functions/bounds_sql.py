"""The bounds that data can be held against, as column expressions."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F


def variance(n: Column, s: Column) -> Column:
    return F.least(n / (s * s), F.sqrt(n) / s)


def second_moment(n: Column, s: Column) -> Column:
    return 1 + variance(n, s)


def nnz(n: Column, s: Column) -> Column:
    return s * (s + F.sqrt(n))


def gap_bits(n: Column, s: Column) -> Column:
    return (3 + 1.5 * F.log2(2 * (s * s + n) / nnz(n, s))) * nnz(n, s) + 32


def gap_bits_alt(n: Column, s: Column) -> Column:
    m = s * s + F.sqrt(n)
    return (3 + 1.5 * F.log2(2 * (s * s + n) / m)) * m + 32


def dense_bits(n: Column) -> Column:
    return 2.8 * n + 32


def fixed_bits(bits: Column, d: Column) -> Column:
    return bits + 32 / d


def omega_bound(k: Column) -> Column:
    """log k + log log k + ... + 1, over the positive terms."""
    total, x = F.lit(1.0), k.cast("double")
    for _ in range(6):
        x = F.when(x > 1, F.log2(x)).otherwise(0.0)
        total = total + F.greatest(x, F.lit(0.0))
    return total


def rounds(r: Column, b: Column, k: Column, eps: Column, smooth: Column) -> Column:
    return r * r * F.greatest(2 * b / (k * eps * eps), smooth / eps)


def quantized_b(n: Column, s: Column, b: Column) -> Column:
    return variance(n, s) * b


def sgd_gap(r: Column, sigma2: Column, t: Column, smooth: Column) -> Column:
    return r * F.sqrt(2 * sigma2 / t) + smooth * r * r / t


def minibatch_var(sigma2: Column, m: Column) -> Column:
    return sigma2 / m


def contraction(p: Column) -> Column:
    return F.pow(F.lit(0.9), p)


def vr_bits(n: Column, t: Column, f: float = 32.0) -> Column:
    return (f + 2.8 * n) * (t + 1) + f * n


def lower_bounds(n: Column, eps: Column) -> tuple[Column, Column]:
    return n, n * (F.log2(n) + F.log2(1 / eps))


def stationarity(smooth: Column, gap: Column, t: Column, n: Column, s: Column, b: Column) -> Column:
    return F.sqrt(smooth * gap) / t + variance(n, s) * b / smooth


def bucket_variance(d: Column, s: Column) -> Column:
    return variance(d, s)


def saving(n: Column) -> Column:
    return 32 * n / (2.8 * n) / 2


def step_size(rule: str, smooth: Column, r: Column, sigma2: Column, k: Column, t: Column) -> Column:
    """As ``bounds.step_size``."""
    if rule not in ("constant", "parallel"):
        raise ValueError(f"unknown rule {rule}")
    gamma = r / F.sqrt(sigma2) * F.sqrt(2 / t)
    return 1 / (smooth + (1 if rule == "constant" else F.sqrt(k)) / gamma)
