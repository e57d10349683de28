from __future__ import annotations

import numpy as np

from lossygrad.functions import registry
from lossygrad.operators import kernels, quantizer
from lossygrad.sources import embeddings


def test_sql_functions(spark, sf):
    registry.register_sql(spark)
    made = quantizer.quantize(embeddings(spark, sf), 4)
    made.createOrReplaceTempView("quantized")
    wrong = spark.sql(
        "SELECT count(*) AS n FROM (SELECT vec_id, scale, level, posexplode(values) AS (i, x) FROM quantized) "
        "WHERE lq_level(x, CAST(scale AS DOUBLE), 4, lq_uniform(concat_ws('|', 0, 0, vec_id, i))) <> level[i]"
    ).first()["n"]
    assert wrong == 0
    got = [r["n"] for r in spark.sql("SELECT omega_len(id) AS n FROM range(1, 300) ORDER BY id").collect()]
    assert got == [len(kernels.omega(k)) for k in range(1, 300)]


def test_python_functions(spark):
    registry.register_python(spark)
    level, sign = np.array([0, 2, 0, 1], np.int32), np.array([1, -1, 1, 1], np.int8)
    codec, bits, payload = kernels.encode("gap", 1.0, sign, level)
    spark.createDataFrame([(codec, payload, 4, bits)], "codec string, payload binary, n int, n_bits int").createOrReplaceTempView("sent")
    rows = spark.sql("SELECT d.* FROM sent, LATERAL decode_message(codec, payload, n, n_bits) d ORDER BY coord").collect()
    assert [tuple(r) for r in rows] == [(1, -1, 2), (3, 1, 1)]
    spark.createDataFrame([(0, [1.0, 2.0]), (0, [3.0, 4.0]), (1, [5.0, 6.0])], "g int, v array<double>").createOrReplaceTempView("vectors")
    assert {r["g"]: r["v"] for r in spark.sql("SELECT g, vec_sum(v) AS v FROM vectors GROUP BY g").collect()} == {0: [4.0, 6.0], 1: [5.0, 6.0]}
