"""Baselines, mean estimation and optimiser steps."""

from __future__ import annotations

import numpy as np
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from lossygrad.functions import quantization as Q
from lossygrad.functions.uniform import uniform
from lossygrad.operators import baselines, layers, layout, meanest, messages, quantizer
from lossygrad.optim import gd, sgd, svrg, table
from lossygrad.optim.channel import Channel
from lossygrad.optim.objectives import LeastSquares
from lossygrad.queries import query
from lossygrad.queries import sql as S
from lossygrad.queries.quantizer import _round
from lossygrad.sources import embeddings, features
from lossygrad.sources import table as table_of

_FOLD = "list_reduce(list_prepend(CAST(0 AS DOUBLE), {0}), lambda a, b: a + b)"


def _values(df: DataFrame) -> DataFrame:
    return layout.to_long(df.select("vec_id", "values")).select("vec_id", "coord", _round("value").alias("value"))


def _base(spark: SparkSession, sf_dir: str) -> DataFrame:
    return embeddings(spark, sf_dir).select("vec_id", "values")


_MEAN_ABS = f"SELECT vec_id, CAST(CAST({_FOLD.format('list_transform(embedding, lambda x: abs(CAST(x AS DOUBLE)))')} / len(embedding) AS FLOAT) AS DOUBLE) AS m FROM embeddings"


@query("onebit_embeddings", f"WITH v AS ({S.EMB}), m AS ({_MEAN_ABS}) SELECT vec_id, coord, round(CASE WHEN value < 0 THEN -m ELSE m END, 6) AS value FROM v JOIN m USING (vec_id)")
def onebit_embeddings(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _values(baselines.onebit(_base(spark, sf_dir)))


@query(
    "onebit_two_means",
    f"""
    WITH v AS ({S.EMB}), m AS (SELECT vec_id, avg(value) FILTER (value < 0) AS low, avg(value) FILTER (value >= 0) AS high FROM v GROUP BY vec_id)
    SELECT vec_id, coord, round(CAST(CAST(coalesce(CASE WHEN value < 0 THEN low ELSE high END, 0) AS FLOAT) AS DOUBLE), 5) AS value FROM v JOIN m USING (vec_id)
    """,
)
def onebit_two_means(spark: SparkSession, sf_dir: str) -> DataFrame:
    made = baselines.onebit(_base(spark, sf_dir), scale="two_means")
    return layout.to_long(made.select("vec_id", "values")).select("vec_id", "coord", _round("value", 5).alias("value"))


@query(
    "onebit_carry_2steps",
    f"""
    WITH v AS ({S.EMB}), m AS ({_MEAN_ABS}),
    w AS (SELECT vec_id, coord, value + (value - CASE WHEN value < 0 THEN -m ELSE m END) AS w FROM v JOIN m USING (vec_id)),
    m2 AS (SELECT vec_id, CAST(CAST({_FOLD.format('list(abs(w) ORDER BY coord)')} / count(*) AS FLOAT) AS DOUBLE) AS m2 FROM w GROUP BY vec_id)
    SELECT vec_id, coord, round(CASE WHEN w < 0 THEN -m2 ELSE m2 END, 6) AS sent, (round(w - CASE WHEN w < 0 THEN -m2 ELSE m2 END, 6) + 0.0) AS carried FROM w JOIN m2 USING (vec_id)
    """,
)
def onebit_carry_2steps(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The same gradient twice, the first step's error carried into the second."""
    base = _base(spark, sf_dir)
    second = baselines.onebit(base, baselines.onebit(base))
    rows = second.select("vec_id", F.posexplode_outer(F.arrays_zip(F.col("values").alias("sent"), "carried")).alias("coord", "x")).where("coord is not null")
    return rows.select("vec_id", F.col("coord").cast("bigint").alias("coord"), _round("x.sent").alias("sent"), _round("x.carried").alias("carried"))


@query("reduced_bf16", f"WITH v AS ({S.EMB}) SELECT vec_id, coord, round(CASE WHEN value = 0 THEN 0 ELSE sign(value) * floor(abs(value) / pow(2.0, floor(log2(abs(value))) - 7)) * pow(2.0, floor(log2(abs(value))) - 7) END + 0.0, 9) AS value FROM v")
def reduced_bf16(spark: SparkSession, sf_dir: str) -> DataFrame:
    return layout.to_long(baselines.reduced(_base(spark, sf_dir), "bfloat16").select("vec_id", "values")).select("vec_id", "coord", _round("value", 9).alias("value"))


@query(
    "reduced_fixed8",
    f"WITH v AS ({S.EMB}), m AS ({S.EMB_MAX}) SELECT vec_id, coord, (round((CASE WHEN value < 0 THEN -1 ELSE 1 END) * floor(abs(value) / r * 127 + 0.5) / 127 * r, 6) + 0.0) AS value FROM v JOIN m USING (vec_id)",
)
def reduced_fixed8(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _values(baselines.reduced(_base(spark, sf_dir), "fixed", 8))


@query("topk_k8", f"WITH v AS ({S.EMB}) SELECT vec_id, coord, value FROM v QUALIFY row_number() OVER (PARTITION BY vec_id ORDER BY abs(value) DESC, coord) <= 8")
def topk_k8(spark: SparkSession, sf_dir: str) -> DataFrame:
    return layout.to_long(baselines.topk(_base(spark, sf_dir), k=8)).where("value <> 0")


@query(
    "topk_l2_cover",
    f"""
    WITH v AS ({S.EMB}), s AS (SELECT *, sqrt(sum(value * value) OVER (PARTITION BY vec_id)) AS norm,
        coalesce(sum(abs(value)) OVER (PARTITION BY vec_id ORDER BY abs(value) DESC, coord ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0) AS before FROM v)
    SELECT vec_id, coord, round(CASE WHEN value < 0 THEN -norm ELSE norm END, 6) AS value FROM s WHERE before < norm * (1 - 1e-12) AND norm > 0
    """,
)
def topk_l2_cover(spark: SparkSession, sf_dir: str) -> DataFrame:
    made = baselines.topk_cover(layout.to_long(_base(spark, sf_dir)))
    return made.select("vec_id", "coord", _round("value").alias("value"))


@query("float32_baseline", "SELECT vec_id, CAST(32 * len(embedding) AS BIGINT) AS n_bits FROM embeddings")
def float32_baseline(spark: SparkSession, sf_dir: str) -> DataFrame:
    return baselines.float32(_base(spark, sf_dir)).select("vec_id", "n_bits")


@query("mean_exact_by_label", f"SELECT CAST(label AS BIGINT) AS label, coord, round(avg(value), 6) AS value FROM ({S.EMB}) GROUP BY label, coord")
def mean_exact_by_label(spark: SparkSession, sf_dir: str) -> DataFrame:
    made = baselines.mean_exact(embeddings(spark, sf_dir), "label")
    return made.select(F.col("label").cast("bigint").alias("label"), F.col("coord").cast("bigint").alias("coord"), _round("value").alias("value"))


@query("mean_est_by_label", f"WITH {S.quantized(S.EMB, S.EMB_L2, '4')} SELECT CAST(label AS BIGINT) AS label, coord, (round(avg(CAST(scale AS DOUBLE) * sign * level / 4), 6) + 0.0) AS value, count(*) AS n_messages FROM q GROUP BY label, coord")
def mean_est_by_label(spark: SparkSession, sf_dir: str) -> DataFrame:
    made = meanest.estimate(embeddings(spark, sf_dir), "label", 4)
    return made.select(F.col("label").cast("bigint").alias("label"), F.col("coord").cast("bigint").alias("coord"), _round("value").alias("value"), "n_messages")


_ORDER_BUCKETS = "SELECT o_orderkey // 512 AS vec_id, o_orderkey % 512 AS coord, o_totalprice AS value FROM orders"


@query(
    "mean_est_orders_buckets",
    f"WITH {S.quantized(_ORDER_BUCKETS, f'SELECT vec_id, max(abs(value)) AS r FROM ({_ORDER_BUCKETS}) GROUP BY vec_id', '7')} "
    "SELECT coord, round(avg(CAST(scale AS DOUBLE) * sign * level / 7), 4) AS value, round(avg(value), 4) AS exact, count(*) AS n_messages FROM q GROUP BY coord",
)
def mean_est_orders_buckets(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Mean of the buckets of a long vector, each a worker's 4-bit message, beside the exact mean."""
    long = table_of(spark, sf_dir, "orders").select(F.floor(F.col("o_orderkey") / 512).alias("vec_id"), (F.col("o_orderkey") % 512).alias("coord"), F.col("o_totalprice").alias("value"))
    made = quantizer.quantize_long(long, 7, "max")
    decoded = F.col("scale").cast("double") * F.col("sign") * F.col("level") / 7
    return made.groupBy("coord").agg(F.round(F.avg(decoded), 4).alias("value"), F.round(F.avg("value"), 4).alias("exact"), F.count("*").alias("n_messages"))


_CENTRED = "SELECT CAST(0 AS BIGINT) AS vec_id, event_id AS coord, round(value - (SELECT round(avg(value), 2) FROM events), 4) AS value FROM events"


@query(
    "lq_events_centred",
    f"WITH {S.quantized(_CENTRED, f'SELECT vec_id, max(abs(value)) AS r FROM ({_CENTRED}) GROUP BY vec_id', '7')} SELECT vec_id, coord, CAST(sign * level AS BIGINT) AS signed_level FROM q",
)
def lq_events_centred(spark: SparkSession, sf_dir: str) -> DataFrame:
    """4-bit levels of the events' values less their mean: a long vector of either sign."""
    events = table_of(spark, sf_dir, "events").select("event_id", "value")
    mean = events.agg(F.round(F.avg("value"), 2).alias("mean"))  # one row
    long = events.crossJoin(F.broadcast(mean)).select(F.lit(0).cast("bigint").alias("vec_id"), F.col("event_id").alias("coord"), F.round(F.col("value") - F.col("mean"), 4).alias("value"))
    made = quantizer.quantize_long(long, 7, "max")
    return made.select("vec_id", "coord", (F.col("sign").cast("bigint") * F.col("level")).alias("signed_level"))


def _frontier_sql(s: int) -> str:
    return f"""
        SELECT * FROM (WITH {S.quantized(S.EMB, S.EMB_L2, str(s))}, {S.gap_bits('vec_id')},
        e AS (SELECT label, coord, avg(CAST(scale AS DOUBLE) * sign * level / {s}) - avg(value) AS d FROM q GROUP BY label, coord),
        m AS (SELECT label, sum(d * d) AS mse FROM e GROUP BY label),
        b AS (SELECT label, sum(value * value) * least(64 / pow({s}, 2), sqrt(64) / {s}) / pow(count(DISTINCT vec_id), 2) AS bound FROM q GROUP BY label)
        SELECT CAST({s} AS INTEGER) AS s, round((SELECT avg(mse) FROM m), 6) AS mse, round((SELECT avg(bound) FROM b), 6) AS bound, CAST((SELECT sum(n_bits) FROM g) AS BIGINT) AS n_bits)"""


@query("mean_est_mse_bits_frontier", " UNION ALL ".join(_frontier_sql(s) for s in (1, 2, 4, 8, 16)))
def mean_est_mse_bits_frontier(spark: SparkSession, sf_dir: str) -> DataFrame:
    made = meanest.frontier(embeddings(spark, sf_dir), "label", [1, 2, 4, 8, 16])
    return made.select("s", _round("mse").alias("mse"), _round("bound").alias("bound"), "n_bits")


# ---- rounds of parallel descent, in tables

_WORKERS, _ETA, _S = 4, 0.5, 4


def _planted_sql() -> str:
    x = ["l_quantity / 50", "l_discount * 10", "l_tax * 10", "o_totalprice / 500000", "p_size / 50"]
    noise = f"(CAST('0x' || substr(md5('noise|' || l_orderkey || '|' || l_linenumber || '|' || l_partkey || '|' || l_suppkey), 1, 8) AS BIGINT) / 4294967296.0 - 0.5)"
    target = " + ".join(f"{w} * ({c})" for w, c in zip(features.PLANTED, x, strict=True))
    cols = ", ".join(f"{c} AS a{i}" for i, c in enumerate(x))
    return f"SELECT l_orderkey % {_WORKERS} AS shard, {cols}, {target} + 0.1 * {noise} AS y FROM lineitem JOIN orders ON o_orderkey = l_orderkey JOIN part ON p_partkey = l_partkey"


def _round_sql(t: int, quantize: bool) -> str:
    """CTEs x{t+1} from x{t}: worker gradients, their messages, their mean, a step."""
    residual = " + ".join(f"a{i} * (SELECT value FROM x{t} WHERE coord = {i})" for i in range(5)) + " - y"
    grads = " UNION ALL ".join(f"SELECT shard, CAST({i} AS BIGINT) AS coord, round(avg(a{i} * e), 9) AS value FROM e{t} GROUP BY shard" for i in range(5))
    sent = (
        f"""n{t} AS (SELECT shard, {S.scale32('r')} AS scale FROM (SELECT shard, sqrt(list_reduce(list_prepend(CAST(0 AS DOUBLE), list(value * value ORDER BY coord)), lambda a, b: a + b)) AS r FROM g{t} GROUP BY shard)),
        p{t} AS (SELECT *, {S.position('value', 'scale', str(_S))} AS pos FROM g{t} JOIN n{t} USING (shard)),
        m{t} AS (SELECT shard, coord, CAST(scale AS DOUBLE) * (CASE WHEN value < 0 THEN -1 ELSE 1 END) * (least(floor(pos), {_S - 1}) + CASE WHEN {S.uniform('0', str(t), 'shard', 'coord')} < pos - least(floor(pos), {_S - 1}) THEN 1 ELSE 0 END) / {_S} AS value FROM p{t}),"""
        if quantize
        else f"m{t} AS (SELECT * FROM g{t}),"
    )
    return f"e{t} AS MATERIALIZED (SELECT *, {residual} AS e FROM d), g{t} AS MATERIALIZED ({grads}), {sent} x{t + 1} AS MATERIALIZED (SELECT coord, round(x.value - {_ETA} * u.value, 9) AS value FROM x{t} x JOIN (SELECT coord, avg(value) AS value FROM m{t} GROUP BY coord) u USING (coord))"


def _descent_sql(rounds: int, quantize: bool) -> str:
    start = "x0 AS (SELECT CAST(unnest(range(5)) AS BIGINT) AS coord, CAST(0 AS DOUBLE) AS value)"
    steps = ", ".join(_round_sql(t, quantize) for t in range(rounds))
    return f"WITH d AS MATERIALIZED ({_planted_sql()}), {start}, {steps} SELECT coord, (round(value, 5) + 0.0) AS value FROM x{rounds}"


def _dealt(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Planted rows, dealt to workers once: every later aggregate by worker stays in its task, and the
    plan's rounds read one exchange."""
    return features.planted(spark, sf_dir).select((F.col("l_orderkey") % _WORKERS).alias("shard"), "features", "y").repartition(_WORKERS, "shard")


def _gradients(data: DataFrame, residual: F.Column) -> DataFrame:
    """shard and values: each worker's mean gradient, in its task."""
    sums = data.withColumn("e", residual).groupBy("shard").agg(*[F.round(F.avg(F.get("features", F.lit(i)) * F.col("e")), 9).alias(f"g{i}") for i in range(5)])
    return sums.select("shard", F.array(*[F.col(f"g{i}") for i in range(5)]).alias("values"))


def _exchanged(grads: DataFrame, t: int, codec: str = "gap") -> DataFrame:
    """Workers' gradients as the owners of buckets decode them: quantized and encoded before the exchange."""
    made = quantizer.quantize(grads.withColumnRenamed("shard", "vec_id"), _S, step=t)
    received = messages.decode(messages.by_bucket(messages.encode(made, codec, 4, t)))
    return received.select("shard", Q.dequantize_array(F.col("scale"), F.col("sign"), F.col("level"), _S).alias("values"))


def _descent(spark: SparkSession, sf_dir: str, rounds: int, quantize: bool) -> DataFrame:
    """Rounds as DataFrames: workers' gradients, their messages, one exchange of payloads, mean, step.

    The parameter table (five rows) is crossed into each gradient by broadcast.
    """
    data = _dealt(spark, sf_dir)
    x = spark.range(5).select(F.col("id").alias("coord"), F.lit(0.0).alias("value"))
    for t in range(rounds):
        state = x.agg(F.transform(F.array_sort(F.collect_list(F.struct("coord", "value"))), lambda p: p["value"]).alias("x"))
        residual = F.aggregate(F.zip_with("features", "x", lambda a, b: a * b), F.lit(0.0), lambda s, v: s + v) - F.col("y")
        grads = _gradients(data.crossJoin(F.broadcast(state)), residual)
        sent = _exchanged(grads, t) if quantize else grads
        mean = sent.select(F.posexplode_outer("values").alias("coord", "g")).where("coord is not null").groupBy("coord").agg(F.avg("g").alias("g"))
        x = x.join(F.broadcast(mean), "coord").select("coord", F.round(F.col("value") - _ETA * F.col("g"), 9).alias("value"))
    return x.select("coord", _round("value", 5).alias("value"))


for _name, _rounds, _quantize in (("fp_gradient_step", 1, False), ("cps_step", 1, True), ("fp_3_rounds", 3, False), ("cps_3_rounds", 3, True)):

    @query(_name, _descent_sql(_rounds, _quantize))
    def descent(spark: SparkSession, sf_dir: str, rounds=_rounds, quantize=_quantize) -> DataFrame:
        return _descent(spark, sf_dir, rounds, quantize)


def _table_descent(spark: SparkSession, sf_dir: str, rounds: int, quantize: bool) -> DataFrame:
    """The same rounds with the parameters as a table and rows as entries, all five in one bucket, so that they draw alike."""
    rows = features.planted(spark, sf_dir).select(F.xxhash64("l_orderkey", "l_linenumber", "l_partkey", "l_suppkey", "features").alias("row_id"), (F.col("l_orderkey") % _WORKERS).alias("shard"), "features", "y")
    entries = rows.select("row_id", F.posexplode_outer("features").alias("at", "value")).select("row_id", F.col("at").cast("bigint").alias("coord"), "value")
    x = table.train_table(entries, rows.select("row_id", "shard", "y"), 5, _WORKERS, rounds, _ETA, _S if quantize else None, bucket=8, digits=9)
    return x.select(F.posexplode_outer("values").alias("coord", "value")).select(F.col("coord").cast("bigint").alias("coord"), _round("value", 5).alias("value"))


for _name, _rounds, _quantize in (("table_fp_step", 1, False), ("table_cps_2_rounds", 2, True)):

    @query(_name, _descent_sql(_rounds, _quantize))
    def table_descent(spark: SparkSession, sf_dir: str, rounds=_rounds, quantize=_quantize) -> DataFrame:
        return _table_descent(spark, sf_dir, rounds, quantize)


def flagship(spark: SparkSession, sf_dir: str) -> DataFrame:
    """One compressed exchange: workers' gradients, their sparse messages' bits, and what the owners of buckets decode."""
    grads = _gradients(_dealt(spark, sf_dir), -F.col("y"))
    made = quantizer.quantize(grads.withColumnRenamed("shard", "vec_id"), _S)
    sent = messages.by_bucket(messages.encode(made, "gap"))
    received = messages.decode(sent).select("shard", Q.dequantize_array(F.col("scale"), F.col("sign"), F.col("level"), _S).alias("decoded"))
    bits = messages.encode(made, "gap").select("shard", "n_bits")
    joined = grads.join(received, "shard").join(F.broadcast(bits), "shard")  # a row a worker
    rows = joined.select("shard", "n_bits", (F.lit(32 * 5) / F.col("n_bits")).alias("ratio"), F.posexplode_outer(F.arrays_zip("values", "decoded")).alias("coord", "z")).where("coord is not null")
    return rows.select(F.col("shard").alias("worker"), "coord", F.col("z.values").alias("gradient"), F.col("z.decoded").alias("decoded"), "n_bits", "ratio")


_FRACS = (0.01, 0.04, 0.16)


def _minibatch_sql(frac: float) -> str:
    drawn = S.uniform("'mb'", "step", "l_orderkey", "l_linenumber", "l_partkey", "l_suppkey")
    means = ", ".join(f"avg(-a{i} * y) AS g{i}" for i in range(5))
    keyed = _planted_sql().replace(f"SELECT l_orderkey % {_WORKERS} AS shard,", "SELECT l_orderkey, l_linenumber, l_partkey, l_suppkey,")
    return f"SELECT {frac} :: DOUBLE AS frac, round({' + '.join(f'var_samp(g{i})' for i in range(5))}, 8) AS variance FROM (SELECT step, {means} FROM (SELECT *, unnest(range(8)) AS step FROM ({keyed})) WHERE {drawn} < {frac} GROUP BY step)"


@query("minibatch_hash_gradient", " UNION ALL ".join(_minibatch_sql(f) for f in _FRACS))
def minibatch_hash_gradient(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Variance of minibatch gradients against the full gradient, for growing shares of rows."""
    data = features.planted(spark, sf_dir)
    out = None
    for frac in _FRACS:
        drawn = data.withColumn("step", F.explode(F.array(*[F.lit(i) for i in range(8)]))).where(uniform(F.lit("mb"), F.col("step"), F.col("l_orderkey"), F.col("l_linenumber"), F.col("l_partkey"), F.col("l_suppkey")) < frac)
        g = drawn.groupBy("step").agg(*[F.avg(-F.get("features", F.lit(i)) * F.col("y")).alias(f"g{i}") for i in range(5)])
        row = g.agg(_round(sum((F.var_samp(f"g{i}") for i in range(5)), F.lit(0.0)), 8).alias("variance")).withColumn("frac", F.lit(frac))
        out = row if out is None else out.unionByName(row)
    return out


def _rows(spark: SparkSession, rows: list[dict]) -> DataFrame:
    """Measured rows of a finished run as a DataFrame with plain types."""
    fixed = [{k: (v.item() if isinstance(v, np.generic) else v) for k, v in r.items()} for r in rows]
    types = {bool: "boolean", int: "bigint", float: "double", str: "string"}
    schema = ", ".join(f"`{k}` {types[type(v)]}" for k, v in fixed[0].items())
    return spark.createDataFrame([tuple(r.values()) for r in fixed], schema)


@query("vr_epoch_small", None)
def vr_epoch_small(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Two epochs of the variance-reduced method over all planted rows: bits and losses."""
    base = features.planted(spark, sf_dir).persist()
    data = layout.dense_index(base).select("row_id", "features", "y").persist()
    objective = LeastSquares(5, 0.01)
    out = []
    runs = [svrg.VrRun("float32", Channel()), svrg.VrRun("lq_sqrt", Channel("dense_prefix", s="sqrt", norm="l2"))]
    ledger = svrg.train_vr_grid(data, objective, runs, 4, 12, 2, 0.25)
    measured = sgd.evaluate(data, objective, {f"{n}/{r['epoch']}": r["anchor"] for n, rows in ledger.items() for r in rows})
    for name, rows in ledger.items():
        out += [{"channel": name, "epoch": r["epoch"], "n_bits": int(r["n_bits"]), "loss": measured[f"{name}/{r['epoch']}"]["loss"]} for r in rows]
    data.unpersist()
    base.unpersist()
    return _rows(spark, out)


@query("gd_truncation", None)
def gd_truncation(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Full-gradient descent, exact and truncated, over all planted rows."""
    data = features.planted_rows(spark, sf_dir).persist()
    objective = LeastSquares(5)
    channels = {"full": Channel(), "top2": Channel("topk", frac=0.4), "cover": Channel("topk", cover="l2")}
    out = []
    for name, channel in channels.items():
        x, ledger = gd.train_gd(data, objective, channel, 8, 0.4 if name != "cover" else 0.15)
        out.append({"channel": name, "rounds": len(ledger), "n_bits": int(sum(r["n_bits"] for r in ledger)), "loss": sgd.evaluate(data, objective, {"x": x})["x"]["loss"]})
    data.unpersist()
    return _rows(spark, out)


#: An order as a layer: as many rows as its lines' quantity, as many columns as its dearest line has 500s, and one.
_LAYERS = """SELECT l_orderkey AS layer_id, 'order_' || l_orderkey AS name, CAST(sum(CAST(l_quantity AS BIGINT)) AS BIGINT) AS rows_, CAST(floor(max(l_extendedprice) / 500) AS BIGINT) + 1 AS cols FROM lineitem GROUP BY l_orderkey"""


def _layers(spark: SparkSession, sf_dir: str) -> DataFrame:
    lines = table_of(spark, sf_dir, "lineitem").groupBy("l_orderkey").agg(F.sum(F.col("l_quantity").cast("bigint")).alias("rows"), (F.floor(F.max("l_extendedprice") / 500) + 1).alias("cols"))
    return lines.select(F.col("l_orderkey").alias("layer_id"), F.concat(F.lit("order_"), F.col("l_orderkey").cast("string")).alias("name"), F.lit("dense").alias("kind"), "rows", "cols", (F.col("rows") * F.col("cols")).alias("n"))


@query(
    "layer_policy",
    f"""
    WITH l AS (SELECT *, rows_ * cols AS n FROM ({_LAYERS})),
    p AS (SELECT *, CASE WHEN n < 10000 THEN 32 ELSE 4 END AS bits, CASE WHEN n < 10000 THEN NULL WHEN cols <= 512 THEN (512 // cols) * cols ELSE cols END AS bucket FROM l)
    SELECT layer_id, name, n, CAST(bits AS BIGINT) AS bits, CAST(coalesce(bucket, 0) AS BIGINT) AS bucket, CAST(CASE WHEN bits = 32 THEN n * 32 ELSE n * bits + 32 * ceil(n / bucket) END AS BIGINT) AS n_bits FROM p
    """,
)
def layer_policy(spark: SparkSession, sf_dir: str) -> DataFrame:
    made = layers.policy(_layers(spark, sf_dir))
    return made.select("layer_id", "name", "n", F.col("bits").cast("bigint").alias("bits"), F.coalesce("bucket", F.lit(0)).cast("bigint").alias("bucket"), "n_bits")


@query(
    "skip_policy_share",
    f"""
    WITH l AS (SELECT rows_ * cols AS n, cols FROM ({_LAYERS})), t(threshold) AS (VALUES (0), (1000), (10000)),
    p AS (SELECT *, n >= threshold AS q, CASE WHEN n >= threshold THEN n * 4 + 32 * ceil(n / (CASE WHEN cols <= 512 THEN (512 // cols) * cols ELSE cols END)) ELSE n * 32 END AS n_bits FROM l, t)
    SELECT CAST(threshold AS INTEGER) AS threshold, CAST(sum(n) AS BIGINT) AS n_params, CAST(sum(CASE WHEN q THEN n ELSE 0 END) AS BIGINT) AS n_quantized,
        round(sum(CASE WHEN q THEN n ELSE 0 END) / sum(n), 6) AS share_quantized, round(sum(n) * 32 / sum(n_bits), 6) AS ratio FROM p GROUP BY threshold
    """,
)
def skip_policy_share(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Share of parameters quantized and saving, by threshold."""
    out = None
    for threshold in (0, 1_000, 10_000):
        made = layers.report(layers.policy(_layers(spark, sf_dir), min_elements=threshold))
        row = made.select("n_params", "n_quantized", _round("share_quantized").alias("share_quantized"), _round("ratio").alias("ratio"), F.lit(threshold).alias("threshold"))
        out = row if out is None else out.unionByName(row)
    return out


