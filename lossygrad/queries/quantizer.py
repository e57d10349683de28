"""Quantizers and their statistics."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from lossygrad.functions import quantization as Q
from lossygrad.operators import layout, ledger, quantizer
from lossygrad.queries import query
from lossygrad.queries import sql as S
from lossygrad.sources import embeddings, table


def long_levels(df: DataFrame) -> DataFrame:
    """Quantized arrays as rows of whole numbers."""
    marked = df.select("vec_id", F.posexplode_outer(F.arrays_zip("sign", "level")).alias("coord", "q")).where("coord is not null")
    return marked.select("vec_id", F.col("coord").cast("bigint").alias("coord"), (F.col("q.sign").cast("bigint") * F.col("q.level")).alias("signed_level"))


_PICK = "SELECT vec_id, coord, CAST(sign * level AS BIGINT) AS signed_level FROM q"


def _register_embeddings() -> None:
    variants = {
        "lq_embeddings_s1": (1, "l2", "random"),
        "lq_embeddings_s4": (4, "l2", "random"),
        "lq_embeddings_sqrt": ("sqrt", "l2", "random"),
        "lq_max_norm": (4, "max", "random"),
        "lq_nearest": (4, "l2", "nearest"),
        "lq_bits_2": (Q.levels_from_bits(2), "max", "random"),
        "lq_bits_4": (Q.levels_from_bits(4), "max", "random"),
        "lq_bits_8": (Q.levels_from_bits(8), "max", "random"),
    }
    for name, (s, norm, rounding) in variants.items():
        number = "8" if s == "sqrt" else str(s)
        sql = f"WITH {S.quantized(S.EMB, S.EMB_L2 if norm == 'l2' else S.EMB_MAX, number, nearest=rounding == 'nearest')} {_PICK}"

        @query(name, sql)
        def run(spark: SparkSession, sf_dir: str, s=s, norm=norm, rounding=rounding) -> DataFrame:
            return long_levels(quantizer.quantize(embeddings(spark, sf_dir), s, norm, rounding=rounding))


_register_embeddings()


def _orders(spark: SparkSession, sf_dir: str) -> DataFrame:
    return table(spark, sf_dir, "orders").select(F.lit(0).cast("bigint").alias("vec_id"), F.col("o_orderkey").alias("coord"), F.col("o_totalprice").alias("value"))


_ORDERS = "SELECT CAST(0 AS BIGINT) AS vec_id, o_orderkey AS coord, o_totalprice AS value FROM orders"
_ORDERS_L2 = "SELECT CAST(0 AS BIGINT) AS vec_id, sqrt(CAST(sum(CAST(CAST(round(o_totalprice * 100) AS BIGINT) AS HUGEINT) * CAST(round(o_totalprice * 100) AS BIGINT)) AS DOUBLE)) / 100 AS r FROM orders"


def _levels(df: DataFrame) -> DataFrame:
    return df.select("vec_id", "coord", (F.col("sign").cast("bigint") * F.col("level")).alias("signed_level"))


@query("lq_orders_long_s16", f"WITH {S.quantized(_ORDERS, _ORDERS_L2, '16')} {_PICK}")
def lq_orders_long_s16(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _levels(quantizer.quantize_long(_orders(spark, sf_dir), 16, decimals=2))


@query("lq_range_join", f"WITH {S.quantized(_ORDERS, _ORDERS_L2, '16')} {_PICK}")
def lq_range_join(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _levels(quantizer.quantize_by_intervals(_orders(spark, sf_dir), 16, decimals=2))


def _bucketed(d: int, norm: str, s: str) -> str:
    values = f"SELECT *, coord // {d} AS bucket_id FROM ({S.EMB})"
    fold = "max(abs(value))" if norm == "max" else "sqrt(list_reduce(list_prepend(CAST(0 AS DOUBLE), list(value * value ORDER BY coord)), lambda a, b: a + b))"
    norms = f"SELECT vec_id * 1000 + bucket_id AS key, {fold} AS r FROM ({values}) GROUP BY 1"
    keyed = f"SELECT *, vec_id * 1000 + bucket_id AS key FROM ({values})"
    return f"WITH {S.quantized(keyed, norms, s, on='key')} SELECT vec_id, bucket_id, coord, CAST(sign * level AS BIGINT) AS signed_level FROM q"


def _buckets(spark: SparkSession, sf_dir: str, d: int, s: int, norm: str) -> DataFrame:
    made = quantizer.quantize(layout.bucketize(embeddings(spark, sf_dir).select("vec_id", "values"), d), s, norm, bucket=d)
    marked = made.select("vec_id", "bucket_id", F.posexplode_outer(F.arrays_zip("sign", "level")).alias("at", "q")).where("at is not null")
    return marked.select("vec_id", "bucket_id", (F.col("bucket_id") * d + F.col("at")).alias("coord"), (F.col("q.sign").cast("bigint") * F.col("q.level")).alias("signed_level"))


@query("lq_bucket_16", _bucketed(16, "l2", "4"))
def lq_bucket_16(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _buckets(spark, sf_dir, 16, 4, "l2")


@query("lq_bucket_24_short_last", _bucketed(24, "max", "7"))
def lq_bucket_24_short_last(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _buckets(spark, sf_dir, 24, 7, "max")


_LINE_ORDER = "l_orderkey, l_linenumber, l_partkey, l_suppkey, l_quantity, l_extendedprice, l_discount, l_tax, l_returnflag, l_linestatus, l_shipdate"
#: The place of a row among its order's rows is found inside the order, so no task sees more than an order.
_LINE_VALUES = f"SELECT l_orderkey AS vec_id, CAST(row_number() OVER (PARTITION BY l_orderkey ORDER BY {_LINE_ORDER}) - 1 AS BIGINT) AS coord, l_extendedprice AS value FROM lineitem"


@query(
    "lq_lineitem_orders_4bit",
    f"WITH {S.quantized(_LINE_VALUES, f'SELECT vec_id, max(abs(value)) AS r FROM ({_LINE_VALUES}) GROUP BY vec_id', '7')} "
    "SELECT vec_id, count(*) AS n, CAST(sum(level) AS BIGINT) AS levels, CAST(sum(CASE WHEN level = 7 THEN 1 ELSE 0 END) AS BIGINT) AS at_top, CAST(sum((coord + 1) * level) AS BIGINT) AS checksum FROM q GROUP BY vec_id",
)
def lq_lineitem_orders_4bit(spark: SparkSession, sf_dir: str) -> DataFrame:
    from pyspark.sql import Window

    order = Window.partitionBy("l_orderkey").orderBy(*_LINE_ORDER.split(", "))
    long = table(spark, sf_dir, "lineitem").select(F.col("l_orderkey").alias("vec_id"), (F.row_number().over(order) - 1).cast("bigint").alias("coord"), F.col("l_extendedprice").alias("value"))
    made = quantizer.quantize_long(long, 7, "max")
    return made.groupBy("vec_id").agg(
        F.count("*").alias("n"), F.sum("level").alias("levels"), F.sum(F.when(F.col("level") == 7, 1).otherwise(0)).alias("at_top"), F.sum((F.col("coord") + 1) * F.col("level")).alias("checksum")
    )


#: Buckets of whole orders: 128 of them, about 512 lines; a line's place is its rank in its bucket.
_LINE_BUCKETS = f"""SELECT *, bucket_id * 512 + place AS coord FROM (SELECT CAST(0 AS BIGINT) AS vec_id, l_orderkey // 128 AS bucket_id,
    CAST(row_number() OVER (PARTITION BY l_orderkey // 128 ORDER BY {_LINE_ORDER}) - 1 AS BIGINT) AS place, l_extendedprice AS value FROM lineitem)"""


@query(
    "lq_bucket_512_lineitem",
    f"""
    WITH {S.quantized(_LINE_BUCKETS, f'SELECT bucket_id, max(abs(value)) AS r FROM ({_LINE_BUCKETS}) GROUP BY bucket_id', '7', keys=('0', '0', 'vec_id', 'coord'), on='bucket_id')},
    {S.gap_bits('bucket_id').replace('coord', 'place')}, b AS (SELECT bucket_id, count(*) AS n, max(scale) AS scale FROM q GROUP BY bucket_id)
    SELECT CAST(0 AS BIGINT) AS vec_id, bucket_id, CAST(n AS INTEGER) AS n, scale, CAST(32 + 4 * n AS BIGINT) AS fixed_bits, n_bits AS gap_bits FROM b JOIN g USING (bucket_id)
    """,
)
def lq_bucket_512_lineitem(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Prices of all lines in buckets of 128 orders (about 512 lines), 4-bit, with message bits.  One shuffle, by bucket."""
    from lossygrad.functions import codes

    order = _LINE_ORDER.split(", ")
    lines = table(spark, sf_dir, "lineitem").select(F.lit(0).cast("bigint").alias("vec_id"), F.floor(F.col("l_orderkey") / 128).cast("bigint").alias("bucket_id"), F.struct(*order).alias("line"))
    buckets = lines.groupBy("vec_id", "bucket_id").agg(F.transform(F.array_sort(F.collect_list("line")), lambda x: x["l_extendedprice"]).alias("values"))
    made = quantizer.quantize(buckets, 7, "max", bucket=512)
    return made.select("vec_id", "bucket_id", F.size("level").alias("n"), "scale", codes.fixed_bits(F.col("level"), 4).alias("fixed_bits"), codes.gap_bits(F.col("level")).alias("gap_bits"))


@query("lq_zero_vector", "SELECT vec_id, unnest(range(len(embedding))) AS coord, CAST(0 AS BIGINT) AS signed_level FROM embeddings")
def lq_zero_vector(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Every vector times zero, which leaves zeros and negative zeros."""
    zero = embeddings(spark, sf_dir).select("vec_id", F.transform("values", lambda x: x * 0.0).alias("values"))
    return long_levels(quantizer.quantize(zero, 4))


@query(
    "lq_sign_zero",
    "SELECT l_linenumber, count(*) AS n, CAST(sum(CASE WHEN l_discount = 0 THEN 1 ELSE 0 END) AS BIGINT) AS zeros, CAST(sum(CASE WHEN l_discount < 0 THEN -1 ELSE 1 END) AS BIGINT) AS signs, "
    "CAST(sum(CASE WHEN l_discount > 0 THEN -1 ELSE 1 END) AS BIGINT) AS negated_signs, CAST(sum(CASE WHEN l_discount < 0.05 THEN -1 ELSE 1 END) AS BIGINT) AS shifted_signs FROM lineitem GROUP BY l_linenumber",
)
def lq_sign_zero(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Signs of lines' discounts, many of them zero, of their negation (negative zeros, whose sign is 1 too) and less 0.05."""
    from lossygrad.functions.arrays import sign_of

    x = F.col("l_discount")
    forms = {"signs": x, "negated_signs": -x, "shifted_signs": x - 0.05}
    return table(spark, sf_dir, "lineitem").groupBy("l_linenumber").agg(
        F.count("*").alias("n"), F.sum(F.when(x == 0, 1).otherwise(0)).alias("zeros"), *[F.sum(sign_of(v).cast("bigint")).alias(n) for n, v in forms.items()]
    )


def _round(c: str | F.Column, n: int = 6):
    return F.round((F.col(c) if isinstance(c, str) else c) + F.lit(0.0), n)


@query(
    "dequantize_embeddings_s4",
    f"WITH {S.quantized(S.EMB, S.EMB_L2, '4')} SELECT vec_id, coord, (round(CAST(scale AS DOUBLE) * sign * level / 4, 6) + 0.0) AS value FROM q",
)
def dequantize_embeddings_s4(spark: SparkSession, sf_dir: str) -> DataFrame:
    decoded = quantizer.dequantize(quantizer.quantize(embeddings(spark, sf_dir).select("vec_id", "values"), 4))
    return layout.to_long(decoded).select("vec_id", "coord", _round("value").alias("value"))


def _statistics_sql(s: int) -> str:
    low = "least(floor(pos), s - 1)"
    return f"""
        WITH v AS ({S.EMB}), n AS ({S.EMB_L2}),
        p AS (SELECT vec_id, value, scale, {s} AS s, {S.position('value', 'scale', str(s))} AS pos FROM v JOIN (SELECT vec_id, {S.scale32('r')} AS scale FROM n) USING (vec_id))
        SELECT vec_id, count(*) AS n, round(sum(pow(CAST(scale AS DOUBLE) / s, 2) * (pos - {low}) * (1 - (pos - {low}))), 6) AS variance,
            round(least(count(*) / pow({s}, 2), sqrt(count(*)) / {s}) * sum(value * value), 6) AS variance_bound,
            round(sum(least(1.0, pos)), 6) AS nonzeros, round({s} * ({s} + sqrt(count(*))), 6) AS nonzeros_bound,
            sum(pow(CAST(scale AS DOUBLE) / s, 2) * (pos - {low}) * (1 - (pos - {low}))) <= least(count(*) / pow({s}, 2), sqrt(count(*)) / {s}) * sum(value * value) AS variance_holds,
            sum(least(1.0, pos)) <= {s} * ({s} + sqrt(count(*))) AS nonzeros_hold
        FROM p GROUP BY vec_id"""


for _s in (1, 4, 8):

    @query(f"exact_variance_and_sparsity_s{_s}", _statistics_sql(_s))
    def exact_statistics(spark: SparkSession, sf_dir: str, s=_s) -> DataFrame:
        report = ledger.variance_report(quantizer.quantize(embeddings(spark, sf_dir), s))
        return report.select(
            "vec_id", F.col("n").cast("bigint").alias("n"), _round("variance").alias("variance"), _round("variance_bound").alias("variance_bound"), _round("nonzeros").alias("nonzeros"),
            _round("nonzeros_bound").alias("nonzeros_bound"), (F.col("variance") <= F.col("variance_bound")).alias("variance_holds"), (F.col("nonzeros") <= F.col("nonzeros_bound")).alias("nonzeros_hold"),
        )


@query(
    "seed_mean_bias",
    f"""
    WITH v AS (SELECT *, unnest(range(32)) AS seed FROM ({S.EMB})), n AS ({S.EMB_L2}),
    p AS (SELECT v.*, scale, {S.position('value', 'scale', '4')} AS pos FROM v JOIN (SELECT vec_id, {S.scale32('r')} AS scale FROM n) USING (vec_id)),
    q AS (SELECT *, (CASE WHEN value < 0 THEN -1 ELSE 1 END) * (least(floor(pos), 3) + CASE WHEN {S.uniform('seed', '0', 'vec_id', 'coord')} < pos - least(floor(pos), 3) THEN 1 ELSE 0 END) AS k FROM p)
    SELECT vec_id, coord, CAST(sum(k) AS BIGINT) AS level_sum FROM q GROUP BY vec_id, coord
    """,
)
def seed_mean_bias(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Sums of signed levels over 32 seeds, of every vector."""
    return _level_sums(spark, embeddings(spark, sf_dir))


def _level_sums(spark: SparkSession, vectors: DataFrame) -> DataFrame:
    """Sums of signed levels over 32 seeds: over 32 and times the scale, they average to the value."""
    seeded = vectors.crossJoin(F.broadcast(spark.range(32).select(F.col("id").alias("seed"))))
    scaled = seeded.withColumn("scale", Q.scale_of(F.col("values")))
    made = scaled.select("vec_id", "seed", F.posexplode_outer(Q.quantize_array(F.col("values"), F.col("scale"), 4, F.col("seed"), F.lit(0), F.col("vec_id"))).alias("coord", "q")).where("coord is not null")
    return made.groupBy("vec_id", F.col("coord").cast("bigint").alias("coord")).agg(F.sum(F.col("q.sign").cast("bigint") * F.col("q.level")).alias("level_sum"))


@query(
    "density_max_vs_l2",
    f"""
    WITH {S.quantized(S.EMB, S.EMB_L2, '4')}, m AS (SELECT vec_id, {S.scale32('r')} AS top FROM ({S.EMB_MAX})),
    b AS (SELECT q.vec_id, q.level AS by_l2, {S.position('value', 'top', '4')} AS pos4, {S.uniform('0', '0', 'q.vec_id', 'coord')} AS u FROM q JOIN m USING (vec_id))
    SELECT vec_id, CAST(sum(CASE WHEN by_l2 > 0 THEN 1 ELSE 0 END) AS BIGINT) AS nnz_l2,
        CAST(sum(CASE WHEN least(floor(pos4), 3) + CASE WHEN u < pos4 - least(floor(pos4), 3) THEN 1 ELSE 0 END > 0 THEN 1 ELSE 0 END) AS BIGINT) AS nnz_max FROM b GROUP BY vec_id
    """,
)
def density_max_vs_l2(spark: SparkSession, sf_dir: str) -> DataFrame:
    vectors = embeddings(spark, sf_dir)
    count = F.size(F.filter("level", lambda k: k > 0)).cast("bigint")
    a = quantizer.quantize(vectors, 4, "l2").select("vec_id", count.alias("nnz_l2"))
    return a.join(quantizer.quantize(vectors, 4, "max").select("vec_id", count.alias("nnz_max")), "vec_id")


@query("level_histogram", f"WITH {S.quantized(S.EMB, S.EMB_L2, '8')} SELECT level, count(*) AS n FROM q GROUP BY level")
def level_histogram(spark: SparkSession, sf_dir: str) -> DataFrame:
    made = quantizer.quantize(embeddings(spark, sf_dir), 8)
    return made.select(F.explode_outer("level").alias("k")).where("k is not null").select(F.col("k").cast("bigint").alias("level")).groupBy("level").agg(F.count("*").alias("n"))


@query(
    "level_entropy",
    f"WITH {S.quantized(S.EMB, S.EMB_L2, '8')}, h AS (SELECT level, count(*) AS c FROM q GROUP BY level), t AS (SELECT sum(c) AS total FROM h) SELECT round(sum(-(c / total) * log2(c / total)), 6) AS entropy, count(*) AS n_levels FROM h, t",
)
def level_entropy(spark: SparkSession, sf_dir: str) -> DataFrame:
    return ledger.level_entropy(quantizer.quantize(embeddings(spark, sf_dir), 8)).select(_round("entropy").alias("entropy"), "n_levels")
