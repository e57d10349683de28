"""The functions a SQL user meets: temporary SQL functions, a table function, an aggregate."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import SparkSession
from pyspark.sql import functions as F

from lossygrad.operators import kernels
from lossygrad.session import ship_package


def _omega_length(k: str, left: int = 5) -> str:
    return "0" if not left else f"IF({k} <= 1, 0, length(bin({k})) + {_omega_length(f'(length(bin({k})) - 1)', left - 1)})"


def _omega_string(k: str, left: int = 5) -> str:
    return "''" if not left else f"IF({k} <= 1, '', concat({_omega_string(f'(CAST(length(bin({k})) AS BIGINT) - 1)', left - 1)}, bin({k})))"


def register_sql(spark: SparkSession) -> None:
    """``lq_uniform(key)``, ``lq_level(x, scale, s, u)``, ``lq_quantize(v, s, kind, key, seed)``, ``omega_len(k)`` and
    ``omega_bits(k)``, as SQL functions that the optimizer inlines."""
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION lq_uniform(k STRING) RETURNS DOUBLE RETURN CAST(conv(substr(md5(k), 1, 8), 16, 10) AS DOUBLE) / 4294967296D")
    spark.sql(
        "CREATE OR REPLACE TEMPORARY FUNCTION lq_level(x DOUBLE, scale DOUBLE, s INT, u DOUBLE) RETURNS INT RETURN "
        "CASE WHEN scale = 0 THEN 0 ELSE CAST(least(floor(least(abs(x) / scale, 1D) * s), s - 1) AS INT) + IF(u < least(abs(x) / scale, 1D) * s - least(floor(least(abs(x) / scale, 1D) * s), s - 1), 1, 0) END"
    )
    spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION omega_len(k BIGINT) RETURNS INT RETURN 1 + {_omega_length('k')}")
    spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION omega_bits(k BIGINT) RETURNS STRING RETURN concat({_omega_string('k')}, '0')")
    norm = "IF(kind = 'max', coalesce(array_max(transform(v, x -> abs(x))), 0D), sqrt(aggregate(v, 0D, (a, x) -> a + x * x)))"
    up = "IF(CAST(CAST(r AS FLOAT) AS DOUBLE) < r, CAST(CAST(CAST(r AS FLOAT) AS DOUBLE) * (1 + 1.25D * pow(2D, -24D)) AS FLOAT), CAST(r AS FLOAT))"
    drawn = "CAST(conv(substr(md5(concat_ws('|', CAST(seed AS STRING), '0', key, CAST(i AS STRING))), 1, 8), 16, 10) AS DOUBLE) / 4294967296D"
    at = "least(abs(x) / CAST(c AS DOUBLE), 1D) * s"
    level = f"IF(c = 0, 0, CAST(least(floor({at}), s - 1) AS INT) + IF({drawn} < {at} - least(floor({at}), s - 1), 1, 0))"
    spark.sql(
        "CREATE OR REPLACE TEMPORARY FUNCTION lq_quantize(v ARRAY<DOUBLE>, s INT, kind STRING, key STRING, seed INT) RETURNS STRUCT<scale: FLOAT, sign: ARRAY<TINYINT>, level: ARRAY<INT>> RETURN "
        f"element_at(transform(array({norm}), r -> element_at(transform(array({up}), c -> named_struct('scale', c, 'sign', transform(v, x -> CAST(IF(x < 0, -1, 1) AS TINYINT)), "
        f"'level', transform(v, (x, i) -> {level}))), 1)), 1)"
    )


def register_python(spark: SparkSession) -> None:
    """``decode_message(codec, payload, n, n_bits)`` as a table function, ``vec_sum(values)`` as an aggregate,
    ``pack_message(codec, scale, sign, level, bits)`` and ``unpack_message(codec, payload, n, n_bits, bits)`` (signed levels) over Arrow batches."""
    ship_package(spark)

    @F.udtf(returnType="coord int, sign int, level int")
    class DecodeMessage:
        def eval(self, codec: str, payload: bytes, n: int, n_bits: int) -> Iterator[tuple[int, int, int]]:
            _, sign, level = kernels.decode(codec, bytes(payload), n, n_bits)
            for i in np.flatnonzero(level).tolist():
                yield i, int(sign[i]), int(level[i])

    @F.pandas_udf("array<double>")
    def vec_sum(values: pd.Series) -> list[float]:
        return np.sum(np.stack(values.to_numpy()), axis=0).tolist() if len(values) else []

    @F.pandas_udf("struct<n_bits: bigint, payload: binary>")
    def pack_message(codec: pd.Series, scale: pd.Series, sign: pd.Series, level: pd.Series, bits: pd.Series) -> pd.DataFrame:
        rows = [kernels.encode(c, x, np.asarray(g, np.int8), np.asarray(k, np.int32), b)[1:] for c, x, g, k, b in zip(codec, scale, sign, level, bits, strict=True)]
        return pd.DataFrame(rows, columns=["n_bits", "payload"])

    @F.pandas_udf("array<int>")
    def unpack_message(codec: pd.Series, payload: pd.Series, n: pd.Series, n_bits: pd.Series, bits: pd.Series) -> pd.Series:
        decoded = (kernels.decode(c, bytes(p), int(m), int(nb), int(b)) for c, p, m, nb, b in zip(codec, payload, n, n_bits, bits, strict=True))
        return pd.Series([(sign * level).tolist() for _, sign, level in decoded])

    spark.udf.register("pack_message", pack_message)
    spark.udf.register("unpack_message", unpack_message)
    spark.udtf.register("decode_message", DecodeMessage)
    spark.udf.register("vec_sum", vec_sum)
