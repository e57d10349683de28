"""The relational surface around the methods: scans, joins, aggregates, windows, sets."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from lossygrad.functions import codes
from lossygrad.functions.uniform import uniform
from lossygrad.operators import baselines, layout, quantizer
from lossygrad.queries import query
from lossygrad.queries import sql as S
from lossygrad.queries.quantizer import _round
from lossygrad.sources import embeddings, table

# ---- scan, projection, filter

_STATS = "SELECT avg(l_quantity) AS m, stddev_pop(l_quantity) AS d FROM lineitem"


@query("proj_standardized_features", f"SELECT l_orderkey, count(*) AS n, (round(sum((l_quantity - m) / d), 4) + 0.0) AS z FROM lineitem, ({_STATS}) GROUP BY l_orderkey")
def proj_standardized_features(spark: SparkSession, sf_dir: str) -> DataFrame:
    lines = table(spark, sf_dir, "lineitem").select("l_orderkey", "l_quantity")
    stats = lines.agg(F.avg("l_quantity").alias("m"), F.stddev_pop("l_quantity").alias("d"))
    z = (F.col("l_quantity") - F.col("m")) / F.col("d")
    return lines.crossJoin(F.broadcast(stats)).groupBy("l_orderkey").agg(F.count("*").alias("n"), _round(F.sum(z), 4).alias("z"))


@query("filter_minibatch_hash", f"SELECT o_orderkey FROM orders WHERE {S.uniform(repr('mb'), '7', 'o_orderkey')} < 0.05")
def filter_minibatch_hash(spark: SparkSession, sf_dir: str) -> DataFrame:
    """A replayable minibatch: rows whose hash with the step falls under the share."""
    return table(spark, sf_dir, "orders").select("o_orderkey").where(uniform(F.lit("mb"), F.lit(7), F.col("o_orderkey")) < 0.05)


@query("filter_date_holdout", "SELECT o_orderpriority, count(*) AS n, min(o_orderkey) AS first_key FROM orders WHERE o_orderdate >= TIMESTAMP '1998-01-01' GROUP BY o_orderpriority")
def filter_date_holdout(spark: SparkSession, sf_dir: str) -> DataFrame:
    recent = table(spark, sf_dir, "orders").where(F.col("o_orderdate") >= F.lit("1998-01-01").cast("timestamp_ntz"))
    return recent.groupBy("o_orderpriority").agg(F.count("*").alias("n"), F.min("o_orderkey").alias("first_key"))


@query("json_props_feature", "SELECT event_type, CAST(sum(CAST(json_extract(props, '$.k') AS BIGINT)) AS BIGINT) AS k_sum, count(*) AS n FROM events GROUP BY event_type")
def json_props_feature(spark: SparkSession, sf_dir: str) -> DataFrame:
    e = table(spark, sf_dir, "events").select("event_type", F.from_json("props", "k bigint").alias("p"))
    return e.groupBy("event_type").agg(F.sum("p.k").alias("k_sum"), F.count("*").alias("n"))


@query("map_sparse_vector", f"WITH {S.quantized(S.EMB, S.EMB_L2, '1')} SELECT vec_id, count(*) AS nnz, CAST(min(coord) AS BIGINT) AS first_at, CAST(sum(coord * sign) AS BIGINT) AS checksum FROM q WHERE level > 0 GROUP BY vec_id")
def map_sparse_vector(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Sparse vectors as maps from place to signed level."""
    made = quantizer.quantize(embeddings(spark, sf_dir), 1)
    signed = F.zip_with("sign", "level", lambda g, k: g.cast("bigint") * k)
    places = F.sequence(F.lit(0).cast("bigint"), F.size("level").cast("bigint") - 1)
    sparse = made.select("vec_id", F.map_filter(F.map_from_arrays(places, signed), lambda k, v: v != 0).alias("m")).where(F.size("m") > 0)
    total = F.aggregate(F.map_entries("m"), F.lit(0).cast("bigint"), lambda acc, e: acc + e["key"] * e["value"])
    return sparse.select("vec_id", F.size("m").cast("bigint").alias("nnz"), F.array_min(F.map_keys("m")).alias("first_at"), total.alias("checksum"))


@query("string_trigram_counts", "WITH t AS (SELECT lower(p_name) AS s FROM part), g AS (SELECT substr(s, CAST(i AS BIGINT), 3) AS gram FROM (SELECT s, unnest(range(1, length(s) - 1)) AS i FROM t)) SELECT gram, count(*) AS n FROM g GROUP BY gram")
def string_trigram_counts(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Whole names into trigrams; each name's grams are short, and counts combine before the shuffle."""
    names = table(spark, sf_dir, "part").select(F.lower("p_name").alias("s")).where(F.length("s") >= 3)
    grams = names.select(F.explode(F.transform(F.sequence(F.lit(1), F.length("s") - 2), lambda i: F.substring("s", i, F.lit(3)))).alias("gram"))
    return grams.groupBy("gram").agg(F.count("*").alias("n"))


@query("explode_coords", f"SELECT coord, count(*) AS n, (round(sum(value), 5) + 0.0) AS total FROM ({S.EMB}) GROUP BY coord")
def explode_coords(spark: SparkSession, sf_dir: str) -> DataFrame:
    return layout.to_long(embeddings(spark, sf_dir).select("vec_id", "values")).groupBy("coord").agg(F.count("*").alias("n"), _round(F.sum("value"), 5).alias("total"))


# ---- joins

_LAYERS = [(0, 0, 15), (1, 16, 47), (2, 48, 63)]
_LAYERS_SQL = "(VALUES " + ", ".join(f"({a}, {b}, {c})" for a, b, c in _LAYERS) + ") l(layer, low, high)"


def _layers(spark: SparkSession) -> DataFrame:
    return spark.createDataFrame(_LAYERS, "layer int, low int, high int")


@query("join_broadcast_layers", f"WITH v AS ({S.EMB}) SELECT CAST(layer AS BIGINT) AS layer, count(*) AS n, (round(sum(value * value), 5) + 0.0) AS square FROM v JOIN {_LAYERS_SQL} ON coord BETWEEN low AND high GROUP BY layer")
def join_broadcast_layers(spark: SparkSession, sf_dir: str) -> DataFrame:
    long = layout.to_long(embeddings(spark, sf_dir).select("vec_id", "values"))
    met = long.join(F.broadcast(_layers(spark)), F.col("coord").between(F.col("low"), F.col("high")))
    return met.groupBy(F.col("layer").cast("bigint").alias("layer")).agg(F.count("*").alias("n"), _round(F.sum(F.col("value") ** 2), 5).alias("square"))


@query("join_shuffle_features", "SELECT o_orderpriority, count(*) AS n, (round(avg(l_quantity * p_size), 4) + 0.0) AS x FROM lineitem JOIN orders ON o_orderkey = l_orderkey JOIN part ON p_partkey = l_partkey GROUP BY o_orderpriority")
def join_shuffle_features(spark: SparkSession, sf_dir: str) -> DataFrame:
    lines = table(spark, sf_dir, "lineitem").select("l_orderkey", "l_partkey", "l_quantity")
    orders = table(spark, sf_dir, "orders").select("o_orderkey", "o_orderpriority")
    parts = table(spark, sf_dir, "part").select("p_partkey", "p_size")
    joined = lines.join(orders, lines.l_orderkey == orders.o_orderkey).join(parts, lines.l_partkey == parts.p_partkey)
    return joined.groupBy("o_orderpriority").agg(F.count("*").alias("n"), _round(F.avg(F.col("l_quantity") * F.col("p_size")), 4).alias("x"))


def _support(spark: SparkSession, sf_dir: str, seed: int) -> DataFrame:
    """Nonzero places of the sparse quantizer under a seed."""
    made = quantizer.quantize(embeddings(spark, sf_dir), 1, seed=seed)
    rows = made.select("vec_id", F.posexplode_outer("level").alias("coord", "level")).where("level > 0")
    return rows.select("vec_id", F.col("coord").cast("bigint").alias("coord"))


def _support_sql(seed: int) -> str:
    return f"SELECT vec_id, coord FROM (WITH {S.quantized(S.EMB, S.EMB_L2, '1', (str(seed), '0', 'vec_id', 'coord'))} SELECT vec_id, coord FROM q WHERE level > 0)"


@query("join_outer_support", f"SELECT count(a.coord) AS left_n, count(b.coord) AS right_n, count(*) AS either_n FROM ({_support_sql(1)}) a FULL JOIN ({_support_sql(2)}) b ON a.vec_id = b.vec_id AND a.coord = b.coord")
def join_outer_support(spark: SparkSession, sf_dir: str) -> DataFrame:
    a = _support(spark, sf_dir, 1).select("vec_id", "coord", F.lit(1).alias("a"))
    b = _support(spark, sf_dir, 2).select("vec_id", "coord", F.lit(1).alias("b"))
    return a.join(b, ["vec_id", "coord"], "full_outer").agg(F.count("a").alias("left_n"), F.count("b").alias("right_n"), F.count("*").alias("either_n"))


@query("join_self_overlap", f"WITH s AS ({_support_sql(1)}) SELECT a.vec_id, count(*) AS overlap FROM s a JOIN s b ON a.coord = b.coord AND b.vec_id = a.vec_id + 1 GROUP BY a.vec_id")
def join_self_overlap(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Places that a vector's message shares with the next vector's."""
    s = _support(spark, sf_dir, 1)
    after = s.select((F.col("vec_id") - 1).alias("vec_id"), "coord")
    return s.join(after, ["vec_id", "coord"]).groupBy("vec_id").agg(F.count("*").alias("overlap"))


@query("semi_labeled", "SELECT lang, count(*) AS n FROM documents WHERE doc_id IN (SELECT doc_id FROM labels) GROUP BY lang")
def semi_labeled(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents").select("doc_id", "lang")
    return docs.join(table(spark, sf_dir, "labels").select("doc_id"), "doc_id", "left_semi").groupBy("lang").agg(F.count("*").alias("n"))


@query("anti_holdout", "SELECT source, count(*) AS n FROM documents WHERE doc_id NOT IN (SELECT doc_id FROM labels) GROUP BY source")
def anti_holdout(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents").select("doc_id", "source")
    return docs.join(table(spark, sf_dir, "labels").select("doc_id"), "doc_id", "left_anti").groupBy("source").agg(F.count("*").alias("n"))


@query("interval_join_events", "SELECT CAST(CAST(ts AS DATE) AS VARCHAR) AS day, count(*) AS n FROM events WHERE epoch_us(ts) % 86400000000 < 3600000000 GROUP BY 1")
def interval_join_events(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Events within an hour after a parameter publication (one a day, at midnight): an equi-join on the day and a filter on the interval."""
    e = table(spark, sf_dir, "events").select(F.date_trunc("day", F.col("ts")).alias("day"), "ts")
    published = e.select("day").distinct()
    near = F.col("ts") < F.col("day") + F.expr("INTERVAL 1 HOUR")
    return e.join(published, "day").where(near).groupBy(F.col("day").cast("date").cast("string").alias("day")).agg(F.count("*").alias("n"))


@query("asof_params_events", "WITH p AS (SELECT user_id, ts, event_id AS version FROM events WHERE event_type = 'purchase') SELECT e.event_id, max(p.version) AS version FROM events e JOIN p ON p.user_id = e.user_id AND p.ts = (SELECT max(ts) FROM p x WHERE x.user_id = e.user_id AND x.ts <= e.ts) GROUP BY e.event_id")
def asof_params_events(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The newest version (a purchase) of an event's user at or before it: one window, no join."""
    e = table(spark, sf_dir, "events").select("event_id", "user_id", "ts", "event_type")
    version = F.struct("ts", F.when(F.col("event_type") == "purchase", F.col("event_id")).alias("version"))
    marked = e.withColumn("v", F.when(F.col("event_type") == "purchase", version))
    upto = Window.partitionBy("user_id").orderBy("ts").rangeBetween(Window.unboundedPreceding, 0)
    return marked.withColumn("v", F.max("v").over(upto)).where("v is not null").select("event_id", F.col("v.version").alias("version"))


@query(
    "cross_grid",
    "SELECT bits, d, n_lines, n_parts, bits + 32.0 / d AS bits_per_value FROM (SELECT CAST(l_linenumber + 1 AS BIGINT) AS bits, count(*) AS n_lines FROM lineitem GROUP BY 1), "
    "(SELECT CAST(p_size AS BIGINT) * 16 AS d, count(*) AS n_parts FROM part GROUP BY 1)",
)
def cross_grid(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Every width (a line's number and one) by every bucket (16 times a part's size), with the rows that have them."""
    bits = table(spark, sf_dir, "lineitem").groupBy((F.col("l_linenumber") + 1).cast("bigint").alias("bits")).agg(F.count("*").alias("n_lines"))
    buckets = table(spark, sf_dir, "part").groupBy((F.col("p_size").cast("bigint") * 16).alias("d")).agg(F.count("*").alias("n_parts"))
    return bits.crossJoin(buckets).select("bits", "d", "n_lines", "n_parts", (F.col("bits") + F.lit(32.0) / F.col("d")).alias("bits_per_value"))


# ---- aggregates


@query("agg_gradient_partial", "SELECT l_orderkey % 8 AS shard, count(*) AS n, CAST(sum(CAST(round(l_extendedprice * 100) AS BIGINT)) AS BIGINT) AS cents FROM lineitem GROUP BY 1")
def agg_gradient_partial(spark: SparkSession, sf_dir: str) -> DataFrame:
    lines = table(spark, sf_dir, "lineitem").select((F.col("l_orderkey") % 8).alias("shard"), F.round(F.col("l_extendedprice") * 100).cast("bigint").alias("c"))
    return lines.groupBy("shard").agg(F.count("*").alias("n"), F.sum("c").alias("cents"))


@query("agg_distinct_levels", f"WITH {S.quantized(S.EMB, S.EMB_L2, '8')} SELECT vec_id, count(DISTINCT level) AS n_levels FROM q GROUP BY vec_id")
def agg_distinct_levels(spark: SparkSession, sf_dir: str) -> DataFrame:
    return quantizer.quantize(embeddings(spark, sf_dir), 8).select("vec_id", F.size(F.array_distinct("level")).cast("bigint").alias("n_levels"))


@query("agg_approx_support")
def agg_approx_support(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _support(spark, sf_dir, 1).agg(F.approx_count_distinct("coord").alias("coords"), F.approx_count_distinct("vec_id").alias("vectors"))


@query("agg_quantile_threshold", "SELECT o_orderpriority, (round(quantile_cont(o_totalprice, 0.9), 4) + 0.0) AS p90 FROM orders GROUP BY o_orderpriority")
def agg_quantile_threshold(spark: SparkSession, sf_dir: str) -> DataFrame:
    return table(spark, sf_dir, "orders").groupBy("o_orderpriority").agg(_round(F.percentile("o_totalprice", 0.9), 4).alias("p90"))


_KEPT_SHARE = 0.05


@query(
    "topk_threshold_at_scale",
    f"""
    WITH c AS (SELECT quantile_disc(abs(value), 1 - {_KEPT_SHARE}) AS cut, count(*) AS n FROM events),
    k AS (SELECT count(*) AS k, min(abs(value)) AS low FROM events, c WHERE abs(value) >= cut), d AS (SELECT max(abs(value)) AS high FROM events, c WHERE abs(value) < cut)
    SELECT CAST(n AS BIGINT) AS n, abs(k / n - {_KEPT_SHARE}) < 0.002 AS near_share, low >= high AS by_magnitude FROM c, k, d
    """,
)
def topk_threshold_at_scale(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Truncation of a long vector by an approximate quantile, without a sort of the vector: whether it keeps
    the share asked for (within the quantile's error) and nothing smaller than what it drops."""
    long = table(spark, sf_dir, "events").select(F.lit(0).cast("bigint").alias("vec_id"), F.col("event_id").alias("coord"), "value")
    kept = baselines.topk_threshold(long, _KEPT_SHARE).select("coord", F.lit(True).alias("kept"))
    marked = long.join(kept, "coord", "left")
    sums = marked.agg(F.count("*").alias("n"), F.count("kept").alias("k"), F.min(F.when(F.col("kept"), F.abs("value"))).alias("low"), F.max(F.when(F.col("kept").isNull(), F.abs("value"))).alias("high"))
    return sums.select("n", (F.abs(F.col("k") / F.col("n") - _KEPT_SHARE) < 0.002).alias("near_share"), (F.col("low") >= F.col("high")).alias("by_magnitude"))


@query("agg_stats_corr", "SELECT (round(corr(l_quantity, l_extendedprice), 6) + 0.0) AS r, (round(regr_slope(l_extendedprice, l_quantity), 3) + 0.0) AS slope, (round(var_pop(l_discount), 8) + 0.0) AS v FROM lineitem")
def agg_stats_corr(spark: SparkSession, sf_dir: str) -> DataFrame:
    return table(spark, sf_dir, "lineitem").agg(_round(F.corr("l_quantity", "l_extendedprice")).alias("r"), _round(F.regr_slope("l_extendedprice", "l_quantity"), 3).alias("slope"), _round(F.var_pop("l_discount"), 8).alias("v"))


def _ledger(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Bits of each vector's message by code and label."""
    made = quantizer.quantize(embeddings(spark, sf_dir), 7, "max")
    sizes = {"fixed": codes.fixed_bits(F.col("level"), 4), "prefix": codes.dense_prefix_bits(F.col("level")), "float32": codes.float_bits(F.col("level"))}
    pairs = F.array(*[F.struct(F.lit(n).alias("codec"), b.cast("bigint").alias("n_bits")) for n, b in sizes.items()])
    return made.select("vec_id", F.col("label").cast("bigint").alias("label"), F.inline(pairs))


_LEDGER = f"""
    SELECT vec_id, label, codec, n_bits FROM (
        WITH {S.quantized(S.EMB, S.EMB_MAX, '7')},
        b AS (SELECT vec_id, CAST(label AS BIGINT) AS label, CAST(32 + 4 * count(*) AS BIGINT) AS fixed, CAST(32 + sum(CASE WHEN level <= 1 THEN 2 ELSE level + 2 END) AS BIGINT) AS prefix, CAST(32 * count(*) AS BIGINT) AS float32 FROM q GROUP BY vec_id, label)
        SELECT * FROM b UNPIVOT (n_bits FOR codec IN (fixed, prefix, float32)))"""


def _subtotals(name: str, groups: str):
    @query(name, f"SELECT coalesce(codec, 'all') AS codec, coalesce(label, -1) AS label, CAST(grouping(codec) AS BIGINT) AS all_codecs, CAST(grouping(label) AS BIGINT) AS all_labels, CAST(sum(n_bits) AS BIGINT) AS n_bits FROM ({_LEDGER}) GROUP BY {groups}")
    def subtotals(spark: SparkSession, sf_dir: str) -> DataFrame:
        _ledger(spark, sf_dir).createOrReplaceTempView("ledger_rows")
        return spark.sql(f"SELECT coalesce(codec, 'all') AS codec, coalesce(label, -1) AS label, CAST(grouping(codec) AS BIGINT) AS all_codecs, CAST(grouping(label) AS BIGINT) AS all_labels, sum(n_bits) AS n_bits FROM ledger_rows GROUP BY {groups}")


_subtotals("ledger_rollup", "ROLLUP (codec, label)")
_subtotals("ledger_cube", "CUBE (codec, label)")
_subtotals("ledger_grouping_sets", "GROUPING SETS ((codec), (label), ())")


@query("pivot_bits", f"SELECT label, CAST(sum(n_bits) FILTER (codec = 'fixed') AS BIGINT) AS fixed, CAST(sum(n_bits) FILTER (codec = 'float32') AS BIGINT) AS float32, CAST(sum(n_bits) FILTER (codec = 'prefix') AS BIGINT) AS prefix FROM ({_LEDGER}) GROUP BY label")
def pivot_bits(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _ledger(spark, sf_dir).groupBy("label").pivot("codec", ["fixed", "float32", "prefix"]).sum("n_bits")


@query("unpivot_ledger", f"SELECT codec, count(*) AS n, CAST(sum(n_bits) AS BIGINT) AS n_bits FROM ({_LEDGER}) GROUP BY codec")
def unpivot_ledger(spark: SparkSession, sf_dir: str) -> DataFrame:
    wide = _ledger(spark, sf_dir).groupBy("vec_id").pivot("codec", ["fixed", "prefix", "float32"]).sum("n_bits")
    return wide.unpivot("vec_id", ["fixed", "prefix", "float32"], "codec", "n_bits").groupBy("codec").agg(F.count("*").alias("n"), F.sum("n_bits").alias("n_bits"))


# ---- windows

_RANKED = f"SELECT vec_id, coord, rank() OVER w AS r, dense_rank() OVER w AS dr, row_number() OVER w AS rn FROM ({S.EMB}) WINDOW w AS (PARTITION BY vec_id ORDER BY abs(value) DESC, coord)"


@query("rank_coords", f"SELECT vec_id, coord, r, dr FROM ({_RANKED}) WHERE rn <= 4")
def rank_coords(spark: SparkSession, sf_dir: str) -> DataFrame:
    order = Window.partitionBy("vec_id").orderBy(F.abs("value").desc(), "coord")
    long = layout.to_long(embeddings(spark, sf_dir).select("vec_id", "values"))
    ranked = long.select("vec_id", "coord", F.rank().over(order).cast("bigint").alias("r"), F.dense_rank().over(order).cast("bigint").alias("dr"), F.row_number().over(order).alias("rn"))
    return ranked.where("rn <= 4").select("vec_id", "coord", "r", "dr")


@query("ntile_shards", "SELECT c_custkey, CAST(ntile(4) OVER (PARTITION BY c_nationkey ORDER BY c_custkey) - 1 AS BIGINT) AS shard, (round(percent_rank() OVER (PARTITION BY c_nationkey ORDER BY c_custkey), 6) + 0.0) AS place FROM customer")
def ntile_shards(spark: SparkSession, sf_dir: str) -> DataFrame:
    order = Window.partitionBy("c_nationkey").orderBy("c_custkey")
    return table(spark, sf_dir, "customer").select("c_custkey", (F.ntile(4).over(order) - 1).cast("bigint").alias("shard"), _round(F.percent_rank().over(order)).alias("place"))


@query("shard_ranges", "SELECT o_orderkey, CAST(least(floor((o_orderkey - m) * 4 / (t - m + 1)), 3) AS BIGINT) AS shard FROM orders, (SELECT min(o_orderkey) AS m, max(o_orderkey) AS t FROM orders)")
def shard_ranges(spark: SparkSession, sf_dir: str) -> DataFrame:
    orders = table(spark, sf_dir, "orders").select("o_orderkey")
    ends = orders.agg(F.min("o_orderkey").alias("m"), F.max("o_orderkey").alias("t"))
    return orders.crossJoin(F.broadcast(ends)).select("o_orderkey", layout.shard_ranges(F.col("o_orderkey") - F.col("m"), F.col("t") - F.col("m") + 1, 4).cast("bigint").alias("shard"))


@query("bit_offsets_running", f"SELECT vec_id, codec, CAST(sum(n_bits) OVER (PARTITION BY codec, label ORDER BY vec_id ROWS UNBOUNDED PRECEDING) - n_bits AS BIGINT) AS at FROM ({_LEDGER})")
def bit_offsets_running(spark: SparkSession, sf_dir: str) -> DataFrame:
    order = Window.partitionBy("codec", "label").orderBy("vec_id").rowsBetween(Window.unboundedPreceding, 0)
    return _ledger(spark, sf_dir).select("vec_id", "codec", (F.sum("n_bits").over(order) - F.col("n_bits")).alias("at"))


@query("loss_moving_avg", "SELECT event_id, (round(avg(value) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS BETWEEN 4 PRECEDING AND CURRENT ROW), 5) + 0.0) AS smooth FROM events")
def loss_moving_avg(spark: SparkSession, sf_dir: str) -> DataFrame:
    order = Window.partitionBy("user_id").orderBy("ts", "event_id").rowsBetween(-4, 0)
    return table(spark, sf_dir, "events").select("event_id", _round(F.avg("value").over(order), 5).alias("smooth"))


@query("time_range_frame", "SELECT event_id, count(*) OVER (PARTITION BY user_id ORDER BY epoch_us(ts) RANGE BETWEEN 86400000000 PRECEDING AND CURRENT ROW) AS last_day FROM events")
def time_range_frame(spark: SparkSession, sf_dir: str) -> DataFrame:
    micros = F.unix_micros(F.col("ts").cast("timestamp"))
    order = Window.partitionBy("user_id").orderBy(micros).rangeBetween(-86_400_000_000, 0)
    return table(spark, sf_dir, "events").select("event_id", F.count("*").over(order).alias("last_day"))


@query(
    "session_windows_users",
    """
    WITH g AS (SELECT user_id, ts, CASE WHEN ts - lag(ts) OVER (PARTITION BY user_id ORDER BY ts) < INTERVAL 12 HOUR THEN 0 ELSE 1 END AS fresh FROM events),
    s AS (SELECT user_id, ts, sum(fresh) OVER (PARTITION BY user_id ORDER BY ts) AS session FROM g)
    SELECT user_id, count(DISTINCT session) AS sessions, count(*) AS n FROM s GROUP BY user_id
    """,
)
def session_windows_users(spark: SparkSession, sf_dir: str) -> DataFrame:
    e = table(spark, sf_dir, "events").select("user_id", F.col("ts").cast("timestamp").alias("ts"))
    sessions = e.groupBy("user_id", F.session_window("ts", "12 hours")).agg(F.count("*").alias("c"))
    return sessions.groupBy("user_id").agg(F.count("*").alias("sessions"), F.sum("c").alias("n"))


# ---- sort, sets, common table expressions


@query("topk_limit", "SELECT o_orderkey, o_totalprice FROM orders ORDER BY o_totalprice DESC, o_orderkey LIMIT 20")
def topk_limit(spark: SparkSession, sf_dir: str) -> DataFrame:
    """A top-k report: the limit is the feature."""
    return table(spark, sf_dir, "orders").select("o_orderkey", "o_totalprice").orderBy(F.col("o_totalprice").desc(), "o_orderkey").limit(20)


@query("array_sort_topk", f"SELECT vec_id, CAST(sum(coord) AS BIGINT) AS places FROM ({_RANKED}) WHERE rn <= 4 GROUP BY vec_id")
def array_sort_topk(spark: SparkSession, sf_dir: str) -> DataFrame:
    ranked = F.array_sort(F.transform("values", lambda x, i: F.struct((-F.abs(x)).alias("m"), i.alias("i"))))
    return embeddings(spark, sf_dir).select("vec_id", F.aggregate(F.slice(ranked, 1, 4), F.lit(0).cast("bigint"), lambda a, e: a + e["i"]).alias("places"))


@query("set_union_codecs", f"SELECT 'a' AS side, count(*) AS n FROM ({_support_sql(1)}) UNION ALL SELECT 'b', count(*) FROM ({_support_sql(2)})")
def set_union_codecs(spark: SparkSession, sf_dir: str) -> DataFrame:
    a, b = (_support(spark, sf_dir, s).agg(F.count("*").alias("n")) for s in (1, 2))
    return a.select(F.lit("a").alias("side"), "n").unionByName(b.select(F.lit("b").alias("side"), "n"))


@query("set_intersect_support", f"SELECT coord, count(*) AS n FROM ({_support_sql(1)} INTERSECT {_support_sql(2)}) GROUP BY coord")
def set_intersect_support(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _support(spark, sf_dir, 1).intersect(_support(spark, sf_dir, 2)).groupBy("coord").agg(F.count("*").alias("n"))


@query("set_except_support", f"SELECT coord, count(*) AS n FROM ({_support_sql(1)} EXCEPT ALL {_support_sql(2)}) GROUP BY coord")
def set_except_support(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _support(spark, sf_dir, 1).exceptAll(_support(spark, sf_dir, 2)).groupBy("coord").agg(F.count("*").alias("n"))


@query("cte_best_config", f"WITH l AS ({_LEDGER}), t AS (SELECT label, codec, sum(n_bits) AS n_bits FROM l GROUP BY label, codec) SELECT label, arg_min(codec, n_bits) AS codec, CAST(min(n_bits) AS BIGINT) AS n_bits FROM t GROUP BY label")
def cte_best_config(spark: SparkSession, sf_dir: str) -> DataFrame:
    totals = _ledger(spark, sf_dir).groupBy("label", "codec").agg(F.sum("n_bits").alias("n_bits"))
    return totals.groupBy("label").agg(F.min_by("codec", "n_bits").alias("codec"), F.min("n_bits").alias("n_bits"))
