"""Builders of DuckDB SQL for quantized vectors, in long layout."""

from __future__ import annotations

#: Vectors of embeddings, long.
EMB = "SELECT vec_id, label, unnest(range(len(embedding))) AS coord, CAST(unnest(embedding) AS DOUBLE) AS value FROM embeddings"
#: Their 2-norms and largest magnitudes, squares summed from left to right.
EMB_L2 = (
    "SELECT vec_id, sqrt(list_reduce(list_prepend(CAST(0 AS DOUBLE), list_transform(embedding, lambda x: CAST(x AS DOUBLE) * CAST(x AS DOUBLE))), lambda a, b: a + b)) AS r FROM embeddings"
)
EMB_MAX = "SELECT vec_id, list_max(list_transform(embedding, lambda x: abs(CAST(x AS DOUBLE)))) AS r FROM embeddings"


def scale32(r: str) -> str:
    f = f"CAST(CAST({r} AS FLOAT) AS DOUBLE)"
    return f"CASE WHEN {f} < {r} THEN CAST({f} * (1 + 1.25 * pow(2.0, -24)) AS FLOAT) ELSE CAST({r} AS FLOAT) END"


def position(x: str, scale: str, s: str) -> str:
    return f"(CASE WHEN CAST({scale} AS DOUBLE) = 0 THEN 0 ELSE least(abs({x}) / CAST({scale} AS DOUBLE), 1.0) * {s} END)"


def uniform(*keys: str) -> str:
    text = " || '|' || ".join(f"CAST({k} AS VARCHAR)" for k in keys)
    return f"(CAST('0x' || substr(md5({text}), 1, 8) AS BIGINT) / 4294967296.0)"


def quantized(values: str, norms: str, s: str, keys: tuple[str, ...] = ("0", "0", "vec_id", "coord"), on: str = "vec_id", nearest: bool = False) -> str:
    """CTEs v, q: every column of ``values`` plus scale, pos, sign, level (s may name a column)."""
    up = "pos - low >= 0.5" if nearest else f"{uniform(*keys)} < pos - low"
    return f"""
        v AS ({values}), r AS ({norms}),
        p AS (SELECT *, {position('value', 'scale', s)} AS pos FROM v JOIN (SELECT {on}, {scale32('r')} AS scale FROM r) USING ({on})),
        l AS (SELECT *, least(floor(pos), {s} - 1) AS low FROM p),
        q AS (SELECT *, CASE WHEN value < 0 THEN -1 ELSE 1 END AS sign, CAST(low + CASE WHEN {up} THEN 1 ELSE 0 END AS BIGINT) AS level FROM l)"""


def omega_len(k: str) -> str:
    """Bits of the recursive integer code, unrolled."""
    bits = lambda x: f"length(bin(CAST({x} AS BIGINT)))"

    def groups(x: str, left: int) -> str:
        return "0" if not left else f"CASE WHEN {x} <= 1 THEN 0 ELSE {bits(x)} + ({groups(f'({bits(x)} - 1)', left - 1)}) END"

    return f"(1 + {groups(k, 4)})"


def gap_bits(by: str) -> str:
    """CTE g after q: bits of the sparse code by ``by``, from lag over the nonzeros."""
    return f"""
        z AS (SELECT *, coord - coalesce(lag(coord) OVER (PARTITION BY {by} ORDER BY coord), -1) AS gap FROM q WHERE level > 0),
        c AS (SELECT {by}, sum({omega_len('gap')} + 1 + {omega_len('level')}) AS bits, count(*) AS nnz FROM z GROUP BY {by}),
        g AS (SELECT {by}, CAST(32 + coalesce(bits, 0) AS BIGINT) AS n_bits, CAST(coalesce(nnz, 0) AS BIGINT) AS nnz FROM (SELECT DISTINCT {by} FROM q) LEFT JOIN c USING ({by}))"""
