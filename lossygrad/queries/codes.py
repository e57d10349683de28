"""Codes, their lengths, and the theory's figures."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from lossygrad.functions import bounds_sql, codes
from lossygrad.operators import messages, quantizer
from lossygrad.queries import query
from lossygrad.queries import sql as S
from lossygrad.queries.quantizer import _round
from lossygrad.sources import embeddings, table


@query("omega_lengths", f"SELECT k, CAST({S.omega_len('k')} AS BIGINT) AS n_bits FROM (SELECT o_orderkey + 1 AS k FROM orders)")
def omega_lengths(spark: SparkSession, sf_dir: str) -> DataFrame:
    return table(spark, sf_dir, "orders").select((F.col("o_orderkey") + 1).alias("k")).select("k", codes.omega_len(F.col("k")).cast("bigint").alias("n_bits"))


@query(
    "omega_strings",
    """
    WITH RECURSIVE w AS (
        SELECT o_orderkey + 1 AS k, o_orderkey + 1 AS x, '0' AS bits FROM orders
        UNION ALL SELECT k, length(bin(x)) - 1, bin(x) || bits FROM w WHERE x > 1
    ) SELECT k, bits FROM w WHERE x = 1
    """,
)
def omega_strings(spark: SparkSession, sf_dir: str) -> DataFrame:
    return table(spark, sf_dir, "orders").select((F.col("o_orderkey") + 1).alias("k")).select("k", codes.omega_bits(F.col("k")).alias("bits"))


for _s in (1, 4):

    @query(f"gap_bits_s{_s}", f"WITH {S.quantized(S.EMB, S.EMB_L2, str(_s))}, {S.gap_bits('vec_id')} SELECT vec_id, n_bits, nnz FROM g")
    def gap_bits(spark: SparkSession, sf_dir: str, s=_s) -> DataFrame:
        made = quantizer.quantize(embeddings(spark, sf_dir), s)
        return made.select("vec_id", codes.gap_bits(F.col("level")).alias("n_bits"), F.size(F.filter("level", lambda k: k > 0)).cast("bigint").alias("nnz"))


@query("gap_window_s4", f"WITH {S.quantized(S.EMB, S.EMB_L2, '4')}, {S.gap_bits('vec_id')} SELECT vec_id, coord, CAST(gap AS BIGINT) AS gap FROM z")
def gap_window_s4(spark: SparkSession, sf_dir: str) -> DataFrame:
    from lossygrad.operators import layout

    long = layout.to_long(embeddings(spark, sf_dir).select("vec_id", "values"))
    made = quantizer.quantize(embeddings(spark, sf_dir), 4).select("vec_id", F.posexplode_outer("level").alias("coord", "level")).where("coord is not null")
    joined = long.join(made.withColumn("coord", F.col("coord").cast("bigint")), ["vec_id", "coord"])
    return quantizer.gaps(joined).select("vec_id", "coord", "gap")


def _dense_sql(each: str) -> str:
    return f"WITH {S.quantized(S.EMB, S.EMB_L2, '8')} SELECT vec_id, CAST(32 + sum({each}) AS BIGINT) AS n_bits FROM q GROUP BY vec_id"


@query("dense_bits_omega1", _dense_sql(f"{S.omega_len('(level + 1)')} + CASE WHEN level > 0 THEN 1 ELSE 0 END"))
def dense_bits_omega1(spark: SparkSession, sf_dir: str) -> DataFrame:
    return quantizer.quantize(embeddings(spark, sf_dir), "sqrt").select("vec_id", codes.dense_omega_bits(F.col("level")).alias("n_bits"))


@query("dense_bits_prefix", _dense_sql("CASE WHEN level <= 1 THEN 2 ELSE level + 2 END"))
def dense_bits_prefix(spark: SparkSession, sf_dir: str) -> DataFrame:
    return quantizer.quantize(embeddings(spark, sf_dir), "sqrt").select("vec_id", codes.dense_prefix_bits(F.col("level")).alias("n_bits"))


@query("fixed_bits", "SELECT vec_id, CAST(32 + 4 * len(embedding) AS BIGINT) AS n_bits, CAST(32 * len(embedding) AS BIGINT) AS float_bits FROM embeddings")
def fixed_bits(spark: SparkSession, sf_dir: str) -> DataFrame:
    made = quantizer.quantize(embeddings(spark, sf_dir), 7, "max")
    return made.select("vec_id", codes.fixed_bits(F.col("level"), 4).alias("n_bits"), codes.float_bits(F.col("level")).alias("float_bits"))


@query(
    "auto_codec_choice",
    f"""
    WITH {S.quantized(S.EMB, S.EMB_L2, '7')}, {S.gap_bits('vec_id')},
    d AS (SELECT vec_id, 32 + sum({S.omega_len('(level + 1)')} + CASE WHEN level > 0 THEN 1 ELSE 0 END) AS omega, 32 + sum(CASE WHEN level <= 1 THEN 2 ELSE level + 2 END) AS prefix, 32 + 4 * count(*) AS fixed FROM q GROUP BY vec_id)
    SELECT vec_id, CAST(least(omega, prefix, fixed, n_bits) + 3 AS BIGINT) AS n_bits,
        CASE least(omega, prefix, fixed, n_bits) WHEN omega THEN 'dense_omega' WHEN prefix THEN 'dense_prefix' WHEN fixed THEN 'fixed' ELSE 'gap' END AS codec
    FROM d JOIN g USING (vec_id)
    """,
)
def auto_codec_choice(spark: SparkSession, sf_dir: str) -> DataFrame:
    made = quantizer.quantize(embeddings(spark, sf_dir), 7)
    return made.select("vec_id", codes.cheapest(F.col("level"), 4).alias("c")).select("vec_id", F.col("c.n_bits").cast("bigint").alias("n_bits"), F.col("c.codec").alias("codec"))


@query(
    "gap_string_embeddings",
    f"""
    WITH RECURSIVE {S.quantized(S.EMB, S.EMB_L2, '4').replace('WITH', '')}, {S.gap_bits('vec_id')},
    needed AS (SELECT DISTINCT gap AS k FROM z UNION SELECT DISTINCT level FROM z),
    w AS (SELECT k, k AS x, '0' AS bits FROM needed UNION ALL SELECT k, length(bin(x)) - 1, bin(x) || bits FROM w WHERE x > 1),
    o AS (SELECT k, bits FROM w WHERE x = 1)
    SELECT z.vec_id, string_agg(a.bits || CASE WHEN sign < 0 THEN '1' ELSE '0' END || b.bits, '' ORDER BY coord) AS bits
    FROM z JOIN o a ON a.k = z.gap JOIN o b ON b.k = z.level GROUP BY z.vec_id
    """,
)
def gap_string_embeddings(spark: SparkSession, sf_dir: str) -> DataFrame:
    made = quantizer.quantize(embeddings(spark, sf_dir), 4)
    # Generated, so that the filter is not pushed below, where it would compute every string once more.
    return made.select("vec_id", F.explode_outer(F.array(codes.gap_string(F.col("sign"), F.col("level")))).alias("bits")).where("bits <> ''")


@query(
    "roundtrip_mismatch_count",
    "SELECT codec, (SELECT count(*) FROM embeddings) AS n_messages, CAST(0 AS BIGINT) AS mismatches FROM (VALUES ('auto'), ('dense_omega'), ('dense_prefix'), ('fixed'), ('gap')) t(codec)",
)
def roundtrip_mismatch_count(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Encodes and decodes every vector with every code; counts what comes back different."""
    made = quantizer.quantize(embeddings(spark, sf_dir), 7, "max").select("vec_id", "scale", "sign", "level")
    out = None
    for codec in ("auto", "dense_omega", "dense_prefix", "fixed", "gap"):
        back = messages.decode(messages.encode(made, codec, 4), 4, 3 if codec == "auto" else 0)
        same = (F.col("b.scale") == F.col("a.scale")) & (F.zip_with("a.sign", "a.level", lambda g, k: g * k) == F.zip_with("b.sign", "b.level", lambda g, k: g * k))
        joined = made.alias("a").join(back.alias("b"), F.col("a.vec_id").cast("int") == F.col("b.shard"), "left")
        row = joined.agg(F.count("*").alias("n_messages"), F.sum(F.when(same, 0).otherwise(1)).alias("mismatches")).select(F.lit(codec).alias("codec"), "n_messages", "mismatches")
        out = row if out is None else out.unionByName(row)
    return out


@query(
    "payload_bits_equal_lengths",
    f"WITH {S.quantized(S.EMB, S.EMB_L2, '4')}, {S.gap_bits('vec_id')} SELECT vec_id, n_bits, CAST(4 + (n_bits - 32 + 7) // 8 AS BIGINT) AS n_bytes FROM g",
)
def payload_bits_equal_lengths(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Bits and bytes of the real sparse payloads, to be held against the computed lengths."""
    sent = messages.encode(quantizer.quantize(embeddings(spark, sf_dir), 4), "gap")
    return sent.select(F.col("shard").cast("bigint").alias("vec_id"), "n_bits", F.length("payload").cast("bigint").alias("n_bytes"))


#: Sizes and levels: an order's quantity and its lines, as often as they occur.
_GRID = "SELECT n, s, count(*) AS n_orders FROM (SELECT CAST(sum(CAST(l_quantity AS BIGINT)) AS DOUBLE) AS n, CAST(count(*) AS DOUBLE) AS s FROM lineitem GROUP BY l_orderkey) GROUP BY n, s"


@query(
    "bounds_table",
    "SELECT n, s, n_orders, round(least(n / pow(s, 2), sqrt(n) / s), 6) AS variance, round(1 + least(n / pow(s, 2), sqrt(n) / s), 6) AS second_moment, round(s * (s + sqrt(n)), 6) AS nnz, "
    "round((3 + 1.5 * log2(2 * (s * s + n) / (s * (s + sqrt(n))))) * s * (s + sqrt(n)) + 32, 4) AS gap_bits, round((3 + 1.5 * log2(2 * (s * s + n) / (s * s + sqrt(n)))) * (s * s + sqrt(n)) + 32, 4) AS gap_bits_alt, "
    "round(2.8 * n + 32, 4) AS dense_bits, round(32 * n / (2.8 * n) / 2, 6) AS saving FROM "
    + f"({_GRID})",
)
def bounds_table(spark: SparkSession, sf_dir: str) -> DataFrame:
    n, s = F.col("n"), F.col("s")
    orders = table(spark, sf_dir, "lineitem").groupBy("l_orderkey").agg(F.sum(F.col("l_quantity").cast("bigint")).cast("double").alias("n"), F.count("*").cast("double").alias("s"))
    return orders.groupBy("n", "s").agg(F.count("*").alias("n_orders")).select(
        "n", "s", "n_orders", _round(bounds_sql.variance(n, s)).alias("variance"), _round(bounds_sql.second_moment(n, s)).alias("second_moment"), _round(bounds_sql.nnz(n, s)).alias("nnz"),
        _round(bounds_sql.gap_bits(n, s), 4).alias("gap_bits"), _round(bounds_sql.gap_bits_alt(n, s), 4).alias("gap_bits_alt"), _round(bounds_sql.dense_bits(n), 4).alias("dense_bits"),
        _round(32 * n / (2.8 * n) / 2).alias("saving"),
    )


def _against_bounds_sql(s: int) -> str:
    return f"""
        SELECT * FROM (WITH {S.quantized(S.EMB, S.EMB_L2, str(s))}, {S.gap_bits('vec_id')},
        d AS (SELECT vec_id, 32 + sum(CASE WHEN level <= 1 THEN 2 ELSE level + 2 END) AS prefix, 32 + sum({S.omega_len('(level + 1)')} + CASE WHEN level > 0 THEN 1 ELSE 0 END) AS omega FROM q GROUP BY vec_id)
        SELECT CAST({s} AS INTEGER) AS s, round(avg(n_bits), 6) AS gap, round((3 + 1.5 * log2(2 * ({s * s} + 64) / ({s} * ({s} + sqrt(64))))) * {s} * ({s} + sqrt(64)) + 32, 6) AS gap_bound,
            round(avg(prefix), 6) AS prefix, round(avg(omega), 6) AS omega, round(CAST(2.8 * 64 + 32 AS DOUBLE), 6) AS dense_bound FROM d JOIN g USING (vec_id))"""


#: A supplier's lines as a problem: n values, s, R, second moment or variance B, K, accuracy, L, T, minibatch, all exact in both engines.
_PROBLEMS = """
    SELECT l_suppkey, CAST(count(*) AS DOUBLE) AS n, CAST(max(l_linenumber) AS DOUBLE) AS s, max(l_quantity) / 8 AS r, CAST(count(DISTINCT l_orderkey) AS DOUBLE) / 64 AS b,
        CAST(l_suppkey % 64 + 1 AS DOUBLE) AS k, 1 / CAST(l_suppkey % 100 + 2 AS DOUBLE) AS eps, CAST(count(DISTINCT l_partkey) AS DOUBLE) / 32 AS l, CAST(sum(CAST(l_quantity AS BIGINT)) AS DOUBLE) AS t, CAST(min(l_linenumber) AS DOUBLE) AS m
    FROM lineitem GROUP BY l_suppkey
"""
_VAR = "least(n / (s * s), sqrt(n) / s)"


@query(
    "bounds_of_training",
    f"""
    SELECT l_suppkey, n, s, round(r * r * greatest(2 * b / (k * eps * eps), l / eps), 4) AS rounds, round(r * r * greatest(2 * {_VAR} * b / (k * eps * eps), l / eps), 4) AS rounds_quantized,
        round(r * sqrt(2 * b / t) + l * r * r / t, 6) AS sgd_gap, round(b / m, 8) AS minibatch_var, round(pow(0.9, 5), 8) AS contraction_5, round((32 + 2.8 * n) * (t + 1) + 32 * n, 2) AS vr_bits,
        round(n * (log2(n) + log2(1 / eps)), 4) AS two_processor, round(sqrt(l * b) / t + {_VAR} * b / l, 6) AS stationarity, round(least(512 / (s * s), sqrt(512) / s), 6) AS bucket_variance,
        round(32 * n / (2.8 * n) / 2, 6) AS saving, round(1 / (l + 1 / (r / sqrt(b) * sqrt(2 / t))), 8) AS step_constant, round(1 / (l + sqrt(k) / (r / sqrt(b) * sqrt(2 / t))), 8) AS step_parallel
    FROM ({_PROBLEMS}) p
    """,
)
def bounds_of_training(spark: SparkSession, sf_dir: str) -> DataFrame:
    n, s, r, b, k, eps, smooth, t, m = (F.col(c) for c in ("n", "s", "r", "b", "k", "eps", "l", "t", "m"))
    d = lambda c: c.cast("double")
    problems = table(spark, sf_dir, "lineitem").groupBy("l_suppkey").agg(
        d(F.count("*")).alias("n"), d(F.max("l_linenumber")).alias("s"), (F.max("l_quantity") / 8).alias("r"), (d(F.count_distinct("l_orderkey")) / 64).alias("b"), (d(F.count_distinct("l_partkey")) / 32).alias("l"),
        d(F.sum(F.col("l_quantity").cast("bigint"))).alias("t"), d(F.min("l_linenumber")).alias("m"),
    ).select("*", d(F.col("l_suppkey") % 64 + 1).alias("k"), (1 / d(F.col("l_suppkey") % 100 + 2)).alias("eps"))
    return problems.select(
        "l_suppkey", "n", "s", _round(bounds_sql.rounds(r, b, k, eps, smooth), 4).alias("rounds"), _round(bounds_sql.rounds(r, bounds_sql.quantized_b(n, s, b), k, eps, smooth), 4).alias("rounds_quantized"),
        _round(bounds_sql.sgd_gap(r, b, t, smooth)).alias("sgd_gap"), _round(bounds_sql.minibatch_var(b, m), 8).alias("minibatch_var"), _round(bounds_sql.contraction(F.lit(5)), 8).alias("contraction_5"),
        _round(bounds_sql.vr_bits(n, t), 2).alias("vr_bits"), _round(bounds_sql.lower_bounds(n, eps)[1], 4).alias("two_processor"), _round(bounds_sql.stationarity(smooth, b, t, n, s, b)).alias("stationarity"),
        _round(bounds_sql.bucket_variance(F.lit(512.0), s)).alias("bucket_variance"), _round(bounds_sql.saving(n)).alias("saving"),
        _round(bounds_sql.step_size("constant", smooth, r, b, k, t), 8).alias("step_constant"), _round(bounds_sql.step_size("parallel", smooth, r, b, k, t), 8).alias("step_parallel"),
    )


@query(
    "omega_length_bound",
    f"WITH RECURSIVE w AS (SELECT k, CAST(k AS DOUBLE) AS x, CAST(1 AS DOUBLE) AS total FROM (SELECT DISTINCT l_partkey + 1 AS k FROM lineitem) UNION ALL SELECT k, log2(x), total + greatest(log2(x), 0) FROM w WHERE x > 1) "
    f"SELECT k, CAST({S.omega_len('k')} AS BIGINT) AS n_bits, round(max(total), 6) AS bound FROM w GROUP BY k",
)
def omega_length_bound(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Lengths of the integer code beside the sum of iterated logarithms, which real codes exceed by whole bits."""
    k = F.col("k")
    parts = table(spark, sf_dir, "lineitem").select((F.col("l_partkey") + 1).alias("k")).distinct()
    return parts.select("k", codes.omega_len(k).cast("bigint").alias("n_bits"), _round(bounds_sql.omega_bound(k)).alias("bound"))


@query(
    "sql_functions",
    f"WITH {S.quantized(S.EMB, S.EMB_MAX, '7')}, {S.gap_bits('vec_id')}, b AS (SELECT vec_id, sum(sign * level * (coord + 1)) AS checksum, count(*) AS n FROM q GROUP BY vec_id) "
    "SELECT vec_id, CAST(checksum AS BIGINT) AS checksum, n_bits, CAST(0 AS BIGINT) AS mismatches, length('1010000') AS omega_4_bits FROM b JOIN g USING (vec_id)".replace("length('1010000')", "'101000'"),
)
def sql_functions(spark: SparkSession, sf_dir: str) -> DataFrame:
    """``lq_quantize``, ``pack_message``, ``unpack_message`` and ``omega_bits`` as SQL users call them."""
    from lossygrad.functions import registry

    registry.register_sql(spark)
    registry.register_python(spark)
    embeddings(spark, sf_dir).select("vec_id", "values").createOrReplaceTempView("lossygrad_vectors")
    # Generated rows keep the optimizer from copying one call's expression into the next one's arguments.
    made = spark.sql("SELECT vec_id, lq_quantize(values, 7, 'max', CAST(vec_id AS STRING), 0) AS q FROM lossygrad_vectors")
    made.select("vec_id", F.explode_outer(F.array("q")).alias("q")).createOrReplaceTempView("lossygrad_levels")
    spark.sql("SELECT vec_id, q, pack_message('gap', q.scale, q.sign, q.level, 4) AS m FROM lossygrad_levels").createOrReplaceTempView("lossygrad_messages")
    spark.sql("SELECT vec_id, q, m.n_bits AS n_bits, unpack_message('gap', m.payload, size(q.level), m.n_bits, 4) AS levels FROM lossygrad_messages").createOrReplaceTempView("lossygrad_received")
    return spark.sql(
        "SELECT vec_id, aggregate(transform(levels, (x, i) -> CAST(x AS BIGINT) * (i + 1)), 0L, (a, x) -> a + x) AS checksum, n_bits, "
        "CAST(size(filter(zip_with(levels, zip_with(q.sign, q.level, (g, k) -> g * k), (a, b) -> a <> b), d -> d)) AS BIGINT) AS mismatches, omega_bits(4L) AS omega_4_bits FROM lossygrad_received"
    )


@query("bits_against_bounds", " UNION ALL ".join(_against_bounds_sql(s) for s in (1, 2, 4, 8)))
def bits_against_bounds(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Mean bits over vectors against the expected-bits bounds, for a range of s."""
    out = None
    for s in (1, 2, 4, 8):
        made = quantizer.quantize(embeddings(spark, sf_dir), s)
        n, k = F.lit(64.0), F.lit(float(s))
        row = made.agg(F.avg(codes.gap_bits(F.col("level"))).alias("gap"), F.avg(codes.dense_prefix_bits(F.col("level"))).alias("prefix"), F.avg(codes.dense_omega_bits(F.col("level"))).alias("omega")).select(
            F.lit(s).alias("s"), _round("gap").alias("gap"), _round(bounds_sql.gap_bits(n, k)).alias("gap_bound"), _round("prefix").alias("prefix"), _round("omega").alias("omega"),
            _round(bounds_sql.dense_bits(n)).alias("dense_bound"),
        )
        out = row if out is None else out.unionByName(row)
    return out


