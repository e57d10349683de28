"""Counter-based uniforms: a draw is a function of its keys, not of where or when it runs.

So a retried or speculative task repeats its messages bit for bit, and another engine
can make the same draws.
"""

from __future__ import annotations

import numpy as np
from pyspark.sql import Column
from pyspark.sql import functions as F

_TWO32 = 4294967296.0


def uniform(*keys: Column | str | int) -> Column:
    """In [0, 1): the first eight hexadecimal digits of the keys' MD5, over 2**32."""
    parts = [k if isinstance(k, Column) else F.lit(k) for k in keys]
    text = F.concat_ws("|", *[p.cast("string") for p in parts])
    return F.conv(F.substring(F.md5(text.cast("binary")), 1, 8), 16, 10).cast("double") / F.lit(_TWO32)


def fast_uniform(*keys: Column | str | int) -> Column:
    """The same kind of draw by xxHash64, cheaper than MD5 and without an SQL twin."""
    parts = [k if isinstance(k, Column) else F.lit(k) for k in keys]
    return F.shiftrightunsigned(F.xxhash64(*parts), 11).cast("double") / F.lit(float(1 << 53))


def uniform_array(n: int, *keys: int, start: int = 0) -> np.ndarray:
    """n draws for coordinates start, start + 1, ... in numpy (a splitmix64 of keys and coordinate)."""
    with np.errstate(over="ignore"):
        state = np.uint64(0x243F6A8885A308D3)
        for k in keys:
            state = _mix(state ^ np.uint64(k & 0xFFFFFFFFFFFFFFFF))
        x = _mix(np.arange(start, start + n, dtype=np.uint64) * np.uint64(0x9E3779B97F4A7C15) + state)
    return (x >> np.uint64(11)) / float(1 << 53)


def _mix(x):
    x = (x ^ (x >> np.uint64(30))) * np.uint64(0xBF58476D1CE4E5B9)
    x = (x ^ (x >> np.uint64(27))) * np.uint64(0x94D049BB133111EB)
    return x ^ (x >> np.uint64(31))
