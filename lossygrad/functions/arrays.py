"""Helpers on array columns."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import Column
from pyspark.sql import functions as F


def let(value: Column, body: Callable[[Column], Column]) -> Column:
    """Bind ``value`` once and use it many times in ``body``."""
    return F.element_at(F.transform(F.array(value), body), 1)


def fold_sum(values: Column) -> Column:
    """Sum from left to right, so every engine rounds alike."""
    return F.aggregate(values, F.lit(0.0), lambda acc, x: acc + x)


def norm2(values: Column) -> Column:
    return F.sqrt(F.aggregate(values, F.lit(0.0), lambda acc, x: acc + x * x))


def norm_max(values: Column) -> Column:
    return F.coalesce(F.array_max(F.transform(values, F.abs)), F.lit(0.0))


def norm1(values: Column) -> Column:
    return F.aggregate(values, F.lit(0.0), lambda acc, x: acc + F.abs(x))


def sign_of(x: Column) -> Column:
    """-1 or +1; zeros of either sign are +1."""
    return F.when(x < 0, -1).otherwise(1)


def bad_values(values: Column) -> Column:
    """Whether a vector is null or has a null, NaN or infinite value."""
    inf = F.lit(float("inf"))
    return values.isNull() | F.exists(values, lambda x: x.isNull() | F.isnan(x) | (F.abs(x) == inf))
