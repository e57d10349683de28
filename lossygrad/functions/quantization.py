"""Randomized rounding of vectors to a few levels of their scale, as column expressions.

A value v with scale r and s levels has position ``a = |v| / r * s``.  Its level is
``floor(a)`` (at most s - 1), or one more with the probability of the fraction left, so
the expectation is exact.  Signs of zeros are +1 and the zero vector stays zero.
"""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F

from lossygrad.functions.arrays import fold_sum, let, norm2, norm_max, sign_of
from lossygrad.functions.uniform import uniform

#: float32 values times this, rounded to float32, are the next float32 above.
NEXT_FLOAT = 1 + 1.25 * 2.0**-24

# The (bits, bucket) settings of the experiments.
PRESETS = {"2bit": (2, 128), "4bit": (4, 512), "8bit": (8, 512), "4bit_wide": (4, 8192), "2bit_narrow": (2, 64)}


def levels_from_bits(bits: int, convention: str = "sign_magnitude") -> int:
    """Levels of a fixed-width code: one bit is the sign, or (``paper_example``) all bits count."""
    if bits < 1:
        raise ValueError("bits must be at least 1")
    if convention == "sign_magnitude":
        return max(1, 2 ** (bits - 1) - 1)
    if convention == "paper_example":
        return 2**bits
    raise ValueError(f"unknown convention {convention}")


def scale32(r: Column) -> Column:
    """The smallest float32 that isn't below r, so positions never exceed s."""
    f = r.cast("float")
    return F.when(f.cast("double") < r, (f.cast("double") * F.lit(NEXT_FLOAT)).cast("float")).otherwise(f)


def scale_of(values: Column, norm: str = "l2") -> Column:
    if norm == "l2":
        return scale32(norm2(values))
    if norm == "max":
        return scale32(norm_max(values))
    raise ValueError(f"unknown norm {norm}")


def position(x: Column, scale: Column, s: Column | int) -> Column:
    """|x| / scale * s, 0 for a zero scale; the scale is a float32 that bounds |x|."""
    r = scale.cast("double")
    return F.when(r == 0, 0.0).otherwise(F.least(F.abs(x) / r, F.lit(1.0)) * s)


def level(pos: Column, s: Column | int, u: Column | None) -> Column:
    """Level of a position: randomized by the uniform u, or nearest where u is None."""
    low = F.least(F.floor(pos), (s if isinstance(s, Column) else F.lit(s)) - 1)
    threshold = F.lit(0.5) if u is None else u
    up = (pos - low >= threshold) if u is None else (threshold < pos - low)
    return (low + F.when(up, 1).otherwise(0)).cast("int")


def quantize_array(values: Column, scale: Column, s: Column | int, *keys: Column | int, first: Column | int = 0, rounding: str = "random") -> Column:
    """Array of structs (sign, level); coordinate i draws with keys and ``first + i``."""

    def one(x: Column, i: Column) -> Column:
        u = uniform(*keys, (i + first).cast("bigint")) if rounding == "random" else None
        return F.struct(sign_of(x).cast("tinyint").alias("sign"), level(position(x, scale, s), s, u).alias("level"))

    return F.transform(values, one)


def dequantize_array(scale: Column, sign: Column, levels: Column, s: Column | int) -> Column:
    # Bound first: a scale that the optimizer copies into the lambda would be computed for every value.
    return let(scale.cast("double"), lambda r: F.zip_with(sign, levels, lambda g, k: r * g * k / s))


def exact_variance(values: Column, scale: Column, s: Column | int) -> Column:
    """E |Q(v) - v|^2 in closed form: (r / s)^2 times the sum of f (1 - f) over position fractions."""
    def term(x: Column) -> Column:
        return let(position(x, scale, s), lambda p: let(p - F.least(F.floor(p), (s if isinstance(s, Column) else F.lit(s)) - 1), lambda f: f * (1 - f)))

    return let(scale.cast("double") / s, lambda r: r * r) * fold_sum(F.transform(values, term))


def exact_nonzeros(values: Column, scale: Column, s: Column | int) -> Column:
    """Expected number of nonzero levels: the sum of min(1, position)."""
    return fold_sum(F.transform(values, lambda x: F.least(F.lit(1.0), position(x, scale, s))))
