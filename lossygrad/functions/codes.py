"""Lengths and bit strings of the integer and vector codes, as column expressions.

The recursive integer code writes k in binary, then writes the number of bits less one
in front in the same way, down to 1; a 0 ends it.  Lengths: 1 for 1, 3 for 2 and 3, 6
for 4 to 7, 7 for 8 to 15, 11 for 16 to 31.
"""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F

SCALE_BITS = 32
#: Steps of the recursion that a BIGINT needs.
DEPTH = 5


def _bits(k: Column) -> Column:
    return F.length(F.bin(k))


def omega_len(k: Column, depth: int = DEPTH) -> Column:
    """Bits of the code of k >= 1."""

    def groups(x: Column, left: int) -> Column:
        if not left:
            return F.lit(0)
        return F.when(x <= 1, 0).otherwise(_bits(x) + groups(_bits(x) - 1, left - 1))

    return F.lit(1) + groups(k, depth)


def omega_bits(k: Column, depth: int = DEPTH) -> Column:
    """The code of k >= 1 as a string of 0 and 1."""

    def groups(x: Column, left: int) -> Column:
        if not left:
            return F.lit("")
        return F.when(x <= 1, "").otherwise(F.concat(groups(_bits(x) - 1, left - 1), F.bin(x)))

    return F.concat(groups(k, depth), F.lit("0"))


def nonzeros(levels: Column) -> Column:
    """Structs (at: position from 1, level) of the nonzero levels."""
    marked = F.transform(levels, lambda k, i: F.struct((i + 1).alias("at"), k.alias("level")))
    return F.filter(marked, lambda e: e["level"] > 0)


def gap_bits(levels: Column) -> Column:
    """Bits of the sparse code: scale, then gap, sign and level of each nonzero in order."""
    start = F.struct(F.lit(0).alias("at"), F.lit(SCALE_BITS).cast("bigint").alias("bits"))

    def step(acc: Column, e: Column) -> Column:
        return F.struct(e["at"].alias("at"), (acc["bits"] + omega_len(e["at"] - acc["at"]) + 1 + omega_len(e["level"])).cast("bigint").alias("bits"))

    return F.aggregate(nonzeros(levels), start, step, lambda acc: acc["bits"])


def gap_string(sign: Column, levels: Column) -> Column:
    """The sparse code after the scale, as a string; sign bit 1 is negative."""
    signed = F.filter(
        F.transform(levels, lambda k, i: F.struct((i + 1).alias("at"), k.alias("level"), F.get(sign, i).alias("sign"))), lambda e: e["level"] > 0
    )
    start = F.struct(F.lit(0).alias("at"), F.lit("").alias("bits"))

    def step(acc: Column, e: Column) -> Column:
        mark = F.when(e["sign"] < 0, "1").otherwise("0")
        return F.struct(e["at"].alias("at"), F.concat(acc["bits"], omega_bits(e["at"] - acc["at"]), mark, omega_bits(e["level"])).alias("bits"))

    return F.aggregate(signed, start, step, lambda acc: acc["bits"])


def _total(levels: Column, each) -> Column:
    return F.aggregate(levels, F.lit(SCALE_BITS).cast("bigint"), lambda acc, k: (acc + each(k)).cast("bigint"))


def dense_omega_bits(levels: Column) -> Column:
    """Scale, then each coordinate's integer code of level + 1 and a sign bit if nonzero."""
    return _total(levels, lambda k: omega_len(k + 1) + F.when(k > 0, 1).otherwise(0))


def dense_prefix_bits(levels: Column) -> Column:
    """Scale, then 2 bits for levels 0 and 1 with sign, k + 2 for k >= 2.

    As k + 2 <= 2 + k^2 / 2, the expectation is at most 2.625 n + 32 when s <= sqrt(n).
    """
    return _total(levels, lambda k: F.when(k <= 1, 2).otherwise(k + 2))


def fixed_bits(levels: Column, bits: int) -> Column:
    return (F.lit(SCALE_BITS) + F.size(levels) * bits).cast("bigint")


def float_bits(levels: Column) -> Column:
    return (F.size(levels) * 32).cast("bigint")


HEADER_BITS = 3


def cheapest(levels: Column, bits: int) -> Column:
    """Struct (n_bits, codec) of the shortest code, with a 3-bit header; ties by name."""
    choices = [
        ("dense_omega", dense_omega_bits(levels)),
        ("dense_prefix", dense_prefix_bits(levels)),
        ("fixed", fixed_bits(levels, bits)),
        ("gap", gap_bits(levels)),
    ]
    return F.array_min(F.array(*[F.struct((n + HEADER_BITS).alias("n_bits"), F.lit(c).alias("codec")) for c, n in choices]))
