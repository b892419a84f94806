"""Regular integer series made from the tables: (series_id STRING, t LONG, x LONG), t dense from 0.

Every builder is one aggregation to ticks (partial sums before the shuffle) followed by zero fill on the tick grid.
Timestamps have no zone; ticks are whole days, hours or half hours since the first tick of the corpus.
"""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import window as W

from boundspark.sources.tables import staged, table

DAY0, HOUR0 = "1995-01-01", "2024-01-01"


def day(ts: str) -> Column:
    return F.date_diff(F.to_date(ts), F.lit(DAY0)).cast("long")


def hour(ts: str) -> Column:
    return (F.date_diff(F.to_date(ts), F.lit(HOUR0)) * 24 + F.hour(ts)).cast("long")


def half_hour(ts: str) -> Column:
    return (F.date_diff(F.to_date(ts), F.lit(HOUR0)) * 48 + F.hour(ts) * 2 + F.expr(f"minute({ts}) div 30")).cast("long")


def cents(c: str) -> Column:
    return F.round(F.col(c) * 100).cast("long")


def densify(ticks: DataFrame) -> DataFrame:
    """Zero-fill (series_id, t, x) over the tick range of the whole corpus and count ticks from 0."""
    span = ticks.agg(F.min("t").alias("lo"), F.max("t").alias("hi"))
    grid = ticks.select("series_id").distinct().join(F.broadcast(span)).select("series_id", "lo", F.explode(F.sequence("lo", "hi")).alias("t"))
    return grid.join(ticks, ["series_id", "t"], "left").select("series_id", (F.col("t") - F.col("lo")).alias("t"), F.coalesce("x", F.lit(0)).cast("long").alias("x"))


def _ticks(df: DataFrame, series: Column, t: Column, x: Column) -> DataFrame:
    return df.groupBy(series.cast("string").alias("series_id"), t.alias("t")).agg(x.cast("long").alias("x"))


def _ordered(df: DataFrame, series: Column, by: str | Column, x: Column, running: bool = False) -> DataFrame:
    """Event-ordered series: the k-th row is tick k; ``running``: with running sums.

    A series may be a whole table: rows are range-partitioned by (series, order), ranked within each range, and moved up
    by what the ranges before hold. The ranges are written first, so that they are the same for counts and for ranks.
    """
    keyed = df.select(series.cast("string").alias("series_id"), (F.col(by) if isinstance(by, str) else by).alias("by"), x.cast("long").alias("x"))
    ranged = staged(keyed.repartitionByRange("series_id", "by").withColumn("part", F.spark_partition_id()), "ranges")
    part = ["series_id", "part"]
    sizes = ranged.groupBy(*part).agg(F.count(F.lit(1)).alias("size"), F.coalesce(F.sum("x"), F.lit(0)).alias("sum"))
    ahead = W.Window.partitionBy("series_id").orderBy("part")  # a row for each range
    before = sizes.select(*part, (F.sum("size").over(ahead) - F.col("size")).alias("before"), (F.sum("sum").over(ahead) - F.col("sum")).alias("so_far"))
    w = W.Window.partitionBy(*part).orderBy("by")
    rows = ranged.withColumn("nth", F.row_number().over(w) - 1)
    if running:
        rows = rows.withColumn("x", F.sum("x").over(w.rowsBetween(W.Window.unboundedPreceding, 0)))
    out = rows.join(before, part)
    return out.select("series_id", (F.col("before") + F.col("nth")).cast("long").alias("t"), (F.col("x") + F.col("so_far") if running else F.col("x")).alias("x"))


def ship_nation_daily(spark: SparkSession, d: str, value: str = "quantity") -> DataFrame:
    items = table(spark, d, "lineitem").select("l_suppkey", "l_shipdate", "l_quantity", "l_extendedprice")
    supp = table(spark, d, "supplier").select("s_suppkey", "s_nationkey")
    x = F.sum(F.col("l_quantity").cast("long")) if value == "quantity" else F.sum(cents("l_extendedprice"))
    return densify(_ticks(items.join(supp, F.col("l_suppkey") == F.col("s_suppkey")), F.concat(F.lit("n"), F.col("s_nationkey")), day("l_shipdate"), x))


def ship_cents_nation_daily(spark: SparkSession, d: str) -> DataFrame:
    return ship_nation_daily(spark, d, "cents")


def orders_nation_daily(spark: SparkSession, d: str) -> DataFrame:
    orders = table(spark, d, "orders").select("o_custkey", "o_orderdate")
    cust = table(spark, d, "customer").select("c_custkey", "c_nationkey")
    return densify(_ticks(orders.join(cust, F.col("o_custkey") == F.col("c_custkey")), F.concat(F.lit("n"), F.col("c_nationkey")), day("o_orderdate"), F.count(F.lit(1))))


def _bucket() -> Column:
    return F.concat(F.lit("b"), F.pmod("user_id", F.lit(50)))


def events_bucket_hourly(spark: SparkSession, d: str) -> DataFrame:
    return densify(_ticks(table(spark, d, "events"), _bucket(), hour("ts"), F.count(F.lit(1))))


def events_cents_bucket_hourly(spark: SparkSession, d: str) -> DataFrame:
    return densify(_ticks(table(spark, d, "events"), _bucket(), hour("ts"), F.sum(cents("value"))))


def events_cents_type_hourly(spark: SparkSession, d: str) -> DataFrame:
    return densify(_ticks(table(spark, d, "events"), F.col("event_type"), hour("ts"), F.sum(cents("value"))))


def events_type_hourly(spark: SparkSession, d: str) -> DataFrame:
    return densify(_ticks(table(spark, d, "events"), F.col("event_type"), hour("ts"), F.count(F.lit(1))))


def events_type_30min(spark: SparkSession, d: str) -> DataFrame:
    return densify(_ticks(table(spark, d, "events"), F.col("event_type"), half_hour("ts"), F.count(F.lit(1))))


#: Weight of an event by hour of day and kind of day: a rule that gives demand its daily and weekly shape.
def demand_weight(hour_of_day: Column, day_no: Column) -> Column:
    shape = F.lit(100) + 90 * F.least(hour_of_day, F.lit(24) - hour_of_day)
    return (shape * F.when(F.pmod(day_no, F.lit(7)) >= 5, F.lit(6)).otherwise(F.lit(10))).cast("long")


DEMAND_WEIGHT_SQL = "((100 + 90 * least({h}, 24 - {h})) * CASE WHEN {d} % 7 >= 5 THEN 6 ELSE 10 END)"


def events_weighted_hourly(spark: SparkSession, d: str) -> DataFrame:
    """Constructed: events weighted by hour and weekday, over a base load, since the raw table has no seasons."""
    h = hour("ts")
    base = _ticks(table(spark, d, "events"), _bucket(), h, F.count(F.lit(1)))
    filled = densify(base)
    w = demand_weight(F.pmod("t", F.lit(24)), F.expr("t div 24"))
    return filled.select("series_id", "t", (w * (20 + F.col("x"))).alias("x"))


def events_value(spark: SparkSession, d: str) -> DataFrame:
    return _ordered(table(spark, d, "events"), F.col("event_type"), "event_id", cents("value"))


def orders_revenue_daily(spark: SparkSession, d: str) -> DataFrame:
    return densify(_ticks(table(spark, d, "orders"), F.lit("revenue"), day("o_orderdate"), F.sum(cents("o_totalprice"))))


def orders_count_daily(spark: SparkSession, d: str) -> DataFrame:
    return densify(_ticks(table(spark, d, "orders"), F.lit("count"), day("o_orderdate"), F.count(F.lit(1))))


def orders_priority_daily(spark: SparkSession, d: str) -> DataFrame:
    return densify(_ticks(table(spark, d, "orders"), F.col("o_orderpriority"), day("o_orderdate"), F.count(F.lit(1))))


def counter_revenue(spark: SparkSession, d: str) -> DataFrame:
    return _ordered(table(spark, d, "orders"), F.lit("counter"), "o_orderkey", cents("o_totalprice"), running=True)


def _props_k() -> Column:
    return F.get_json_object("props", "$.k").cast("long")


def uniform_k(spark: SparkSession, d: str) -> DataFrame:
    return _ordered(table(spark, d, "events"), F.lit("uniform_k"), "event_id", _props_k())


def uniform_k_bucket(spark: SparkSession, d: str) -> DataFrame:
    """The same numbers by user bucket, so that one task need not hold them all."""
    return _ordered(table(spark, d, "events"), _bucket(), "event_id", _props_k())


def uniform_size(spark: SparkSession, d: str) -> DataFrame:
    return _ordered(table(spark, d, "part"), F.lit("uniform_size"), "p_partkey", F.col("p_size"))


def walk(spark: SparkSession, d: str) -> DataFrame:
    return _ordered(table(spark, d, "events"), F.lit("walk"), "event_id", _props_k() - 50, running=True)


def ramp_price(spark: SparkSession, d: str) -> DataFrame:
    return _ordered(table(spark, d, "part"), F.lit("ramp"), "p_partkey", cents("p_retailprice"))


def embed_scanline(spark: SparkSession, d: str) -> DataFrame:
    """One scan line for each label: the axes of its vectors, in vector order, as millionths."""
    cells = table(spark, d, "embeddings").select("vec_id", "label", F.posexplode("embedding").alias("axis", "v"))
    return _ordered(cells, F.concat(F.lit("label"), F.col("label")), F.col("vec_id") * 64 + F.col("axis"), F.round(F.col("v").cast("double") * 1000000))


def text_len(spark: SparkSession, d: str) -> DataFrame:
    return _ordered(table(spark, d, "documents"), F.lit("text_len"), "doc_id", F.col("n_chars"))


def labels_bits(spark: SparkSession, d: str) -> DataFrame:
    return _ordered(table(spark, d, "labels"), F.lit("quality"), "doc_id", F.col("quality"))


# --- generated corpora -----------------------------------------------------------------------------------------


def uniform_int(key: Column, bound: int) -> Column:
    """0 .. bound - 1 from the first 32 bits of md5: the same number in every engine."""
    return F.pmod(F.conv(F.substring(F.md5(key), 1, 8), 16, 10).cast("long"), F.lit(bound))


UNIFORM_SQL = "(('0x' || substr(md5({key}), 1, 8))::bigint % {bound})"


def gen_demand(spark: SparkSession, n_series: int = 50, n_ticks: int = 4300, seed: str = "demand", noise: int = 400) -> DataFrame:
    """Hourly demand: a daily and weekly profile scaled by series, a slow drift, and noise."""
    ids = spark.range(n_series * n_ticks).select(F.expr(f"id div {n_ticks}").alias("s"), F.pmod("id", F.lit(n_ticks)).alias("t"))
    sid = F.concat(F.lit(seed + "_"), F.col("s").cast("string"))
    level = 600 + uniform_int(F.concat(sid, F.lit("/level")), 900)
    shift = uniform_int(F.concat(sid, F.lit("/shift")), 5)
    hour_of_day = F.pmod(F.col("t") + shift, F.lit(24))
    w = demand_weight(hour_of_day, F.expr("t div 24"))
    drift = F.expr("abs(t % 2000 - 1000) div 8")
    jitter = uniform_int(F.concat(sid, F.lit("/"), F.col("t").cast("string")), noise)
    return ids.select(sid.alias("series_id"), "t", (F.expr("1") * (w * level).cast("long") / 100).cast("long").alias("_w"), drift.alias("_d"), jitter.alias("_j")).select("series_id", "t", (F.col("_w") + F.col("_d") * 10 + F.col("_j") * 8).cast("long").alias("x"))


def gen_iid(spark: SparkSession, n: int = 20000, bound: int = 4096) -> DataFrame:
    return spark.range(n).select(F.lit("iid").alias("series_id"), F.col("id").alias("t"), uniform_int(F.concat(F.lit("iid/"), F.col("id").cast("string")), bound).alias("x"))


def gen_smooth(spark: SparkSession, n: int = 4096) -> DataFrame:
    """A cubic arch on integers: exact in every engine."""
    return spark.range(n).select(F.lit("smooth").alias("series_id"), F.col("id").alias("t"), F.expr(f"((id * ({n} - id)) div 16) * (id + 1000) div 4096").cast("long").alias("x"))


CATALOG: dict[str, Callable[[SparkSession, str], DataFrame]] = {
    f.__name__: f
    for f in (ship_nation_daily, ship_cents_nation_daily, orders_nation_daily, events_bucket_hourly, events_cents_bucket_hourly, events_cents_type_hourly, events_type_hourly, events_type_30min, events_weighted_hourly, events_value, orders_revenue_daily, orders_count_daily, orders_priority_daily, counter_revenue, uniform_k, uniform_size, walk, ramp_price, embed_scanline, text_len, labels_bits)
}


# --- oracle SQL of the catalog ---------------------------------------------------------------------------------


def dense_sql(ticks: str) -> str:
    return f"""WITH k AS ({ticks}), b AS (SELECT min(t) AS lo, max(t) AS hi FROM k),
        g AS (SELECT s.series_id, u.t FROM (SELECT DISTINCT series_id FROM k) s, b, unnest(range(b.lo, b.hi + 1)) AS u(t))
        SELECT g.series_id, (g.t - b.lo)::bigint AS t, coalesce(k.x, 0)::bigint AS x FROM g CROSS JOIN b LEFT JOIN k ON k.series_id = g.series_id AND k.t = g.t"""


def _day_sql(c: str) -> str:
    return f"date_diff('day', DATE '{DAY0}', {c}::date)"


_HOUR = f"(date_diff('day', DATE '{HOUR0}', ts::date) * 24 + hour(ts))"
_B = "'b' || (user_id % 50)"


def _nth_sql(series: str, by: str, x: str, frm: str) -> str:
    return f"SELECT {series} AS series_id, (row_number() OVER (PARTITION BY {series} ORDER BY {by}) - 1)::bigint AS t, ({x})::bigint AS x FROM {frm}"


def _run_sql(series: str, by: str, x: str, frm: str) -> str:
    return f"SELECT series_id, t, (sum(x) OVER (ORDER BY t))::bigint AS x FROM ({_nth_sql(series, by, x, frm)})"


SQL = {
    "ship_nation_daily": dense_sql(f"SELECT 'n' || s_nationkey AS series_id, {_day_sql('l_shipdate')} AS t, sum(l_quantity::bigint) AS x FROM lineitem JOIN supplier ON l_suppkey = s_suppkey GROUP BY 1, 2"),
    "ship_cents_nation_daily": dense_sql(f"SELECT 'n' || s_nationkey AS series_id, {_day_sql('l_shipdate')} AS t, sum(round(l_extendedprice * 100)::bigint) AS x FROM lineitem JOIN supplier ON l_suppkey = s_suppkey GROUP BY 1, 2"),
    "orders_nation_daily": dense_sql(f"SELECT 'n' || c_nationkey AS series_id, {_day_sql('o_orderdate')} AS t, count(*) AS x FROM orders JOIN customer ON o_custkey = c_custkey GROUP BY 1, 2"),
    "events_bucket_hourly": dense_sql(f"SELECT {_B} AS series_id, {_HOUR} AS t, count(*) AS x FROM events GROUP BY 1, 2"),
    "events_cents_bucket_hourly": dense_sql(f"SELECT {_B} AS series_id, {_HOUR} AS t, sum(round(value * 100)::bigint) AS x FROM events GROUP BY 1, 2"),
    "events_cents_type_hourly": dense_sql(f"SELECT event_type AS series_id, {_HOUR} AS t, sum(round(value * 100)::bigint) AS x FROM events GROUP BY 1, 2"),
    "events_type_hourly": dense_sql(f"SELECT event_type AS series_id, {_HOUR} AS t, count(*) AS x FROM events GROUP BY 1, 2"),
    "events_type_30min": dense_sql(f"SELECT event_type AS series_id, date_diff('day', DATE '{HOUR0}', ts::date) * 48 + hour(ts) * 2 + minute(ts) // 30 AS t, count(*) AS x FROM events GROUP BY 1, 2"),
    "events_weighted_hourly": f"SELECT series_id, t, ({DEMAND_WEIGHT_SQL.format(h='(t % 24)', d='(t // 24)')} * (20 + x))::bigint AS x FROM ({dense_sql(f'SELECT {_B} AS series_id, {_HOUR} AS t, count(*) AS x FROM events GROUP BY 1, 2')})",
    "events_value": _nth_sql("event_type", "event_id", "round(value * 100)", "events"),
    "orders_revenue_daily": dense_sql(f"SELECT 'revenue' AS series_id, {_day_sql('o_orderdate')} AS t, sum(round(o_totalprice * 100)::bigint) AS x FROM orders GROUP BY 1, 2"),
    "orders_count_daily": dense_sql(f"SELECT 'count' AS series_id, {_day_sql('o_orderdate')} AS t, count(*) AS x FROM orders GROUP BY 1, 2"),
    "orders_priority_daily": dense_sql(f"SELECT o_orderpriority AS series_id, {_day_sql('o_orderdate')} AS t, count(*) AS x FROM orders GROUP BY 1, 2"),
    "counter_revenue": _run_sql("'counter'", "o_orderkey", "round(o_totalprice * 100)", "orders"),
    "uniform_k": _nth_sql("'uniform_k'", "event_id", "(props::json->>'$.k')::bigint", "events"),
    "uniform_size": _nth_sql("'uniform_size'", "p_partkey", "p_size", "part"),
    "walk": _run_sql("'walk'", "event_id", "(props::json->>'$.k')::bigint - 50", "events"),
    "ramp_price": _nth_sql("'ramp'", "p_partkey", "round(p_retailprice * 100)", "part"),
    "embed_scanline": _nth_sql("'label' || label", "vec_id * 64 + axis", "round(v::double * 1000000)", "(SELECT vec_id, label, unnest(embedding) AS v, generate_subscripts(embedding, 1) - 1 AS axis FROM embeddings)"),
    "text_len": _nth_sql("'text_len'", "doc_id", "n_chars", "documents"),
    "labels_bits": _nth_sql("'quality'", "doc_id", "quality", "labels"),
}
