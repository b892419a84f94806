"""Relational operators around the codec, each as one query on the given tables with its DuckDB form.

Joins and aggregates are left to the planner (broadcast, merge or shuffle-hash by size) except where an operator is
about a strategy, which a hint then names.
"""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import window as W

from boundspark.plans import series as S
from boundspark.sources.tables import format_roundtrip, scratch, table, views

Query = Callable[[SparkSession, str], DataFrame]
QUERIES: dict[str, tuple[Query, str | None]] = {}


def op(sql: str | None):
    def add(fn: Query) -> Query:
        QUERIES["op_" + fn.__name__.rstrip("_")] = (fn, sql)
        return fn

    return add


def both(name: str, spark_sql: str, duck_sql: str | None = None) -> None:
    """A query that is the same SQL text in both engines, or nearly so."""

    def run(spark: SparkSession, d: str) -> DataFrame:
        views(spark, d)
        return spark.sql(spark_sql)

    QUERIES["op_" + name] = (run, duck_sql or spark_sql)


# --- scans and formats ----------------------------------------------------------------------------------------


@op("SELECT event_id, user_id FROM events WHERE ts >= TIMESTAMP '2024-01-10' AND ts < TIMESTAMP '2024-01-12' AND event_type = 'click'")
def scan_pruned(spark, d):
    """Two columns of a range of rows: filters and the column list reach the Parquet scan."""
    e = table(spark, d, "events")
    return e.where("ts >= timestamp_ntz'2024-01-10' AND ts < timestamp_ntz'2024-01-12' AND event_type = 'click'").select("event_id", "user_id")


@op("SELECT (props::json->>'$.k')::bigint AS k, count(*) AS n FROM events GROUP BY 1")
def json_props(spark, d):
    return table(spark, d, "events").select(F.from_json("props", "k BIGINT")["k"].alias("k")).groupBy("k").agg(F.count(F.lit(1)).alias("n"))


@op(f"SELECT series_id, count(*) AS n, sum(x)::bigint AS total FROM ({S.SQL['events_type_hourly']}) WHERE series_id = 'click' GROUP BY 1")
def partition_prune(spark, d):
    """A directory by series; the filter on the directory column reads one of them."""
    path = scratch(spark, "by-series")
    S.events_type_hourly(spark, d).write.partitionBy("series_id").parquet(path)
    return spark.read.parquet(path).where("series_id = 'click'").groupBy("series_id").agg(F.count(F.lit(1)).alias("n"), F.sum("x").alias("total"))


def _roundtrip(fmt: str, **options: str) -> None:
    def run(spark, d):
        return format_roundtrip(table(spark, d, "orders").select("o_orderkey", "o_orderstatus", "o_totalprice"), fmt, **options)

    QUERIES[f"op_format_roundtrip_{fmt}"] = (run, "SELECT o_orderkey, o_orderstatus, o_totalprice FROM orders")


for _fmt, _opts in (("csv", {"header": "true"}), ("json", {}), ("orc", {}), ("parquet", {})):
    _roundtrip(_fmt, **_opts)


@op("SELECT p_name AS value FROM part WHERE p_size > 40")
def format_roundtrip_text(spark, d):
    return format_roundtrip(table(spark, d, "part").where("p_size > 40").select(F.col("p_name").alias("value")), "text")


both("generator_uniform", "SELECT id AS i, pmod(cast(conv(substr(md5(cast(id AS string)), 1, 8), 16, 10) AS bigint), 100) AS u FROM range(1000)", "SELECT i, ('0x' || substr(md5(i::varchar), 1, 8))::bigint % 100 AS u FROM range(1000) t(i)")

# --- projections and filters ----------------------------------------------------------------------------------

both("zigzag", "SELECT l_orderkey, l_linenumber, l_partkey, CASE WHEN v >= 0 THEN 2 * v ELSE -2 * v - 1 END AS z FROM (SELECT l_orderkey, l_linenumber, l_partkey, cast(l_quantity AS bigint) - 25 AS v FROM lineitem)")
both("cents", "SELECT o_orderkey, cast(round(o_totalprice * 100) AS bigint) AS cents FROM orders")
both("filters", "SELECT o_orderkey FROM orders WHERE o_orderstatus IN ('F', 'O') AND o_totalprice BETWEEN 1000 AND 200000 AND o_orderpriority LIKE '1%' AND NOT (o_orderstatus IS NOT DISTINCT FROM 'P')", None)
both("fn_null", "SELECT o_orderkey, coalesce(nullif(o_orderstatus, 'F'), 'none') AS st, CASE WHEN nullif(o_orderstatus, 'O') IS NULL THEN 1 ELSE 0 END AS was_o FROM orders")
both("fn_cast", "SELECT o_orderkey, try_cast(o_orderpriority AS int) AS bad, try_cast(substr(o_orderpriority, 1, 1) AS int) AS level, CASE WHEN o_totalprice > 100000 THEN 'big' ELSE 'small' END AS size FROM orders")

# --- dense ticks and gaps -------------------------------------------------------------------------------------

_TYPE = S.SQL["events_type_hourly"]


@op(S.SQL["events_type_hourly"])
def gapfill_zero(spark, d):
    return S.events_type_hourly(spark, d)


def _gappy(spark, d) -> DataFrame:
    return S.events_type_hourly(spark, d).withColumn("x", F.when(F.col("x") > 0, F.col("x")))


_GAPPY = f"SELECT series_id, t, nullif(x, 0) AS x FROM ({_TYPE})"


@op(f"SELECT series_id, t, last_value(x IGNORE NULLS) OVER (PARTITION BY series_id ORDER BY t) AS x FROM ({_GAPPY})")
def gapfill_last(spark, d):
    w = W.Window.partitionBy("series_id").orderBy("t")
    return _gappy(spark, d).select("series_id", "t", F.last("x", ignorenulls=True).over(w).alias("x"))


@op(f"""WITH g AS ({_GAPPY}), b AS (SELECT *, last_value(CASE WHEN x IS NOT NULL THEN t END IGNORE NULLS) OVER w AS t0, last_value(x IGNORE NULLS) OVER w AS x0, first_value(CASE WHEN x IS NOT NULL THEN t END IGNORE NULLS) OVER v AS t1, first_value(x IGNORE NULLS) OVER v AS x1 FROM g WINDOW w AS (PARTITION BY series_id ORDER BY t), v AS (PARTITION BY series_id ORDER BY t ROWS BETWEEN CURRENT ROW AND UNBOUNDED FOLLOWING))
    SELECT series_id, t, round(CASE WHEN t1 = t0 THEN x::double ELSE x0 + (x1 - x0) * (t - t0) / (t1 - t0)::double END, 6) AS x FROM b""")
def gapfill_linear(spark, d):
    w = W.Window.partitionBy("series_id").orderBy("t")
    v = w.rowsBetween(0, W.Window.unboundedFollowing)
    at = F.when(F.col("x").isNotNull(), F.struct("t", "x"))
    b = _gappy(spark, d).select("series_id", "t", "x", F.last(at, True).over(w).alias("a"), F.first(at, True).over(v).alias("b"))
    lin = F.when(F.col("a.t") == F.col("b.t"), F.col("x").cast("double")).otherwise(F.col("a.x") + (F.col("b.x") - F.col("a.x")) * (F.col("t") - F.col("a.t")) / F.try_divide(F.lit(1.0), F.try_divide(F.lit(1.0), (F.col("b.t") - F.col("a.t")).cast("double"))))
    return b.select("series_id", "t", F.round(lin, 6).alias("x"))


# --- joins ----------------------------------------------------------------------------------------------------

_DEMAND = "SELECT n_name, count(*) AS n FROM supplier JOIN nation ON s_nationkey = n_nationkey GROUP BY 1"


@op(_DEMAND)
def join_broadcast(spark, d):
    """The nation table has 25 rows, whatever the scale."""
    return table(spark, d, "supplier").join(F.broadcast(table(spark, d, "nation")), F.col("s_nationkey") == F.col("n_nationkey")).groupBy("n_name").agg(F.count(F.lit(1)).alias("n"))


_PRICE = "SELECT o_orderstatus, count(*) AS n, sum(l_quantity::bigint)::bigint AS q FROM orders JOIN lineitem ON o_orderkey = l_orderkey GROUP BY 1"


def _orders_items(spark, d, hint: str) -> DataFrame:
    o = table(spark, d, "orders").select("o_orderkey", "o_orderstatus")
    li = table(spark, d, "lineitem").select("l_orderkey", "l_quantity")
    return o.hint(hint).join(li, F.col("o_orderkey") == F.col("l_orderkey")).groupBy("o_orderstatus").agg(F.count(F.lit(1)).alias("n"), F.sum(F.col("l_quantity").cast("long")).alias("q"))


@op(_PRICE)
def join_sortmerge(spark, d):
    return _orders_items(spark, d, "merge")


@op(_PRICE)
def join_shuffle_hash(spark, d):
    return _orders_items(spark, d, "shuffle_hash")


@op("SELECT event_type, rho, count(*) AS n FROM events, (VALUES (0.01::double), (0.05::double), (0.2::double)) r(rho) GROUP BY 1, 2")
def join_cross_rho(spark, d):
    """Three tolerances for each row: an array exploded, so no join at all."""
    return table(spark, d, "events").groupBy("event_type").agg(F.count(F.lit(1)).alias("n")).withColumn("rho", F.explode(F.array(*map(F.lit, (0.01, 0.05, 0.2)))))


@op("SELECT count(*) AS pairs FROM events a JOIN events b ON a.user_id = b.user_id AND b.ts > a.ts AND b.ts <= a.ts + INTERVAL 15 MINUTE")
def join_interval(spark, d):
    """Pairs within 15 minutes: an equality on 15-minute bins (this one and the next) instead of a nested loop."""
    sec = F.unix_micros(F.col("ts").cast("timestamp"))
    e = table(spark, d, "events").select("user_id", sec.alias("us")).withColumn("bin", F.expr("us div 900000000"))
    a = e.select("user_id", F.col("us").alias("us_a"), F.explode(F.array(F.col("bin"), F.col("bin") + 1)).alias("bin"))
    j = a.join(e, ["user_id", "bin"]).where("us > us_a AND us <= us_a + 900000000")
    return j.agg(F.count(F.lit(1)).alias("pairs"))


@op(f"WITH o AS (SELECT {S._day_sql('o_orderdate')} AS t, count(*) AS x FROM orders GROUP BY 1), e AS (SELECT event_id, (event_id % 2400)::bigint AS t FROM events) SELECT e.event_id, e.t, o.x FROM e ASOF LEFT JOIN o ON e.t >= o.t")
def join_asof(spark, d):
    """Latest order-day count at or before a tick: union and one running window; ticks are cut into ranges of 512 days,
    each started by the last count before it, so no key holds all rows."""
    o = table(spark, d, "orders").groupBy(S.day("o_orderdate").alias("t")).agg(F.count(F.lit(1)).alias("x"))
    e = table(spark, d, "events").select("event_id", F.pmod("event_id", F.lit(2400)).alias("t"))
    part = F.expr("t div 512")
    heads = o.groupBy(part.alias("part")).agg(F.max_by("x", "t").alias("x"), F.max("t").alias("t"))
    carry = heads.select((F.col("part") + 1).alias("part"), "t", "x")
    nums = o.withColumn("part", part).unionByName(carry)
    u = nums.select("part", "t", "x", F.lit(None).cast("long").alias("event_id"), F.lit(0).alias("k")).unionByName(e.select(part.alias("part"), "t", F.lit(None).cast("long").alias("x"), "event_id", F.lit(1).alias("k")))
    w = W.Window.partitionBy("part").orderBy("t", "k")
    return u.withColumn("x", F.last("x", True).over(w)).where("k = 1").select("event_id", "t", "x")


both("join_semi", "SELECT c_custkey FROM customer LEFT SEMI JOIN orders ON c_custkey = o_custkey", "SELECT c_custkey FROM customer SEMI JOIN orders ON c_custkey = o_custkey")
both("join_anti", "SELECT c_custkey FROM customer LEFT ANTI JOIN orders ON c_custkey = o_custkey", "SELECT c_custkey FROM customer ANTI JOIN orders ON c_custkey = o_custkey")
both("join_full", "SELECT coalesce(a.k, b.k) AS k, a.n AS n_a, b.n AS n_b FROM (SELECT p_size AS k, count(*) AS n FROM part WHERE p_size < 30 GROUP BY p_size) a FULL OUTER JOIN (SELECT p_size AS k, count(*) AS n FROM part WHERE p_size > 20 GROUP BY p_size) b ON a.k = b.k")
both("join_left", "SELECT n_name, count(s_suppkey) AS n FROM nation LEFT JOIN supplier ON n_nationkey = s_nationkey GROUP BY n_name")
# Spark unnests a correlated ORDER BY with LIMIT to row numbers without an order, over rows that a shuffle deals after the sort.
both(
    "join_lateral",
    "SELECT c.c_custkey, o.o_orderkey FROM customer c, LATERAL (SELECT o_orderkey FROM (SELECT o_custkey, o_orderkey, row_number() OVER (PARTITION BY o_custkey ORDER BY o_totalprice DESC NULLS LAST, o_orderkey NULLS LAST) AS nth FROM orders) r WHERE r.o_custkey = c.c_custkey AND nth = 1) o",
    "SELECT c.c_custkey, o.o_orderkey FROM customer c, LATERAL (SELECT o_orderkey FROM orders WHERE o_custkey = c.c_custkey ORDER BY o_totalprice DESC, o_orderkey LIMIT 1) o",
)
both("join_self", "SELECT a.event_type, count(*) AS n FROM events a JOIN events b ON a.user_id = b.user_id AND a.event_id < b.event_id AND b.event_id <= a.event_id + 200 GROUP BY a.event_type")

# --- aggregates -----------------------------------------------------------------------------------------------

both("agg_hash", "SELECT event_type, count(*) AS n, cast(sum(cast(round(value * 100) AS bigint)) AS bigint) AS cents FROM events GROUP BY event_type")
both("agg_moments", "SELECT event_type, cast(sum(cast(c AS decimal(18, 0)) * cast(c AS decimal(18, 0))) AS string) AS s2 FROM (SELECT event_type, cast(round(value * 100) AS bigint) AS c FROM events) GROUP BY event_type", "SELECT event_type, (sum(c::hugeint * c::hugeint))::varchar AS s2 FROM (SELECT event_type, round(value * 100)::bigint AS c FROM events) GROUP BY event_type")
both("agg_distinct", "SELECT event_type, count(DISTINCT user_id) AS users FROM events GROUP BY event_type")
both("agg_median", "SELECT event_type, round(median(value), 6) AS med, round(percentile(value, 0.9), 6) AS p90 FROM events GROUP BY event_type", "SELECT event_type, round(median(value), 6) AS med, round(quantile_cont(value, 0.9), 6) AS p90 FROM events GROUP BY event_type")
both("agg_min_by", "SELECT o_custkey, min_by(o_orderkey, struct(o_totalprice, o_orderkey)) AS cheapest, max_by(o_orderkey, struct(o_totalprice, o_orderkey)) AS dearest FROM orders GROUP BY o_custkey", "SELECT o_custkey, arg_min(o_orderkey, (o_totalprice, o_orderkey)) AS cheapest, arg_max(o_orderkey, (o_totalprice, o_orderkey)) AS dearest FROM orders GROUP BY o_custkey")
both("agg_corr", "SELECT l_returnflag, round(corr(l_quantity, l_extendedprice), 4) AS r, round(regr_slope(l_extendedprice, l_quantity), 2) AS slope FROM lineitem GROUP BY l_returnflag")
both("agg_filter", "SELECT event_type, count(*) FILTER (WHERE value > 50) AS big, count_if(value <= 50) AS small FROM events GROUP BY event_type")
both("rollup", "SELECT o_orderstatus, o_orderpriority, count(*) AS n FROM orders GROUP BY ROLLUP (o_orderstatus, o_orderpriority)")
both("cube", "SELECT o_orderstatus, o_orderpriority, count(*) AS n FROM orders GROUP BY CUBE (o_orderstatus, o_orderpriority)")
both("grouping_sets", "SELECT o_orderstatus, o_orderpriority, count(*) AS n FROM orders GROUP BY GROUPING SETS ((o_orderstatus), (o_orderpriority), ())")


@op("SELECT user_id % 10 AS b, count(*) FILTER (WHERE event_type = 'click') AS click, count(*) FILTER (WHERE event_type = 'view') AS view FROM events GROUP BY 1")
def pivot(spark, d):
    p = table(spark, d, "events").groupBy(F.pmod("user_id", F.lit(10)).alias("b")).pivot("event_type", ["click", "view"]).agg(F.count(F.lit(1)))
    return p.na.fill(0)


@op("SELECT p_partkey, 'p_size' AS what, p_size::double AS v FROM part UNION ALL SELECT p_partkey, 'p_retailprice', p_retailprice FROM part")
def unpivot(spark, d):
    p = table(spark, d, "part").select("p_partkey", F.col("p_size").cast("double").alias("p_size"), "p_retailprice")
    return p.unpivot("p_partkey", ["p_size", "p_retailprice"], "what", "v")


@op("SELECT event_type, count(*) AS n, min(value) AS first_v FROM events GROUP BY 1")
def series_arrays(spark, d):
    a = table(spark, d, "events").groupBy("event_type").agg(F.array_sort(F.collect_list("value")).alias("v"))
    return a.select("event_type", F.size("v").cast("long").alias("n"), F.col("v")[0].alias("first_v"))


# --- windows, sorting, sets -----------------------------------------------------------------------------------

_O = "PARTITION BY o_custkey ORDER BY o_orderdate, o_orderkey"
both("win_rank", f"SELECT o_orderkey, row_number() OVER ({_O}) AS rn, rank() OVER (PARTITION BY o_custkey ORDER BY o_orderpriority) AS rk, dense_rank() OVER (PARTITION BY o_custkey ORDER BY o_orderpriority) AS dr, ntile(4) OVER ({_O}) AS nt, round(percent_rank() OVER ({_O}), 6) AS pr FROM orders")
both("win_lag", f"SELECT o_orderkey, lag(o_orderkey, 1) OVER ({_O}) AS before, lead(o_orderkey, 2) OVER ({_O}) AS after2 FROM orders")
both("win_running", f"SELECT o_orderkey, cast(sum(cast(round(o_totalprice * 100) AS bigint)) OVER ({_O} ROWS UNBOUNDED PRECEDING) AS bigint) AS total, max(o_orderkey) OVER ({_O} ROWS UNBOUNDED PRECEDING) AS top FROM orders")
both("win_rows", f"SELECT o_orderkey, count(*) OVER ({_O} ROWS BETWEEN 3 PRECEDING AND 1 PRECEDING) AS n, round(avg(o_totalprice) OVER ({_O} ROWS BETWEEN 3 PRECEDING AND CURRENT ROW), 4) AS mean FROM orders")
both("win_first", f"SELECT o_orderkey, first_value(o_orderkey) OVER ({_O}) AS f, nth_value(o_orderkey, 2) OVER ({_O}) AS second FROM orders")


@op(f"SELECT series_id, t, (sum(x) OVER (PARTITION BY series_id ORDER BY t RANGE BETWEEN 23 PRECEDING AND CURRENT ROW))::bigint AS day_sum FROM ({_TYPE})")
def win_range(spark, d):
    w = W.Window.partitionBy("series_id").orderBy("t").rangeBetween(-23, 0)
    return S.events_type_hourly(spark, d).select("series_id", "t", F.sum("x").over(w).alias("day_sum"))


both("topk_global", "SELECT o_orderkey, o_totalprice FROM orders ORDER BY o_totalprice DESC, o_orderkey LIMIT 50")
both("topk_group", "SELECT o_orderpriority, o_orderkey FROM (SELECT o_orderpriority, o_orderkey, row_number() OVER (PARTITION BY o_orderpriority ORDER BY o_totalprice DESC, o_orderkey) AS rn FROM orders) WHERE rn <= 5")


@op(f"SELECT series_id, t, x FROM ({_TYPE})")
def sorted_layout(spark, d):
    """Range-partitioned by series and tick, sorted inside: the archive's layout."""
    return S.events_type_hourly(spark, d).repartitionByRange(4, "series_id", "t").sortWithinPartitions("series_id", "t")


for _n, _w in (("union_all", "UNION ALL"), ("union", "UNION"), ("intersect", "INTERSECT"), ("except", "EXCEPT"), ("intersect_all", "INTERSECT ALL"), ("except_all", "EXCEPT ALL")):
    both(f"set_{_n}", f"SELECT p_size AS k FROM part WHERE p_size < 30 {_w} SELECT p_size AS k FROM part WHERE p_size > 20")

both("sample_series", "SELECT event_id FROM events WHERE pmod(cast(conv(substr(md5(cast(user_id AS string)), 1, 8), 16, 10) AS bigint), 10) = 0", "SELECT event_id FROM events WHERE ('0x' || substr(md5(user_id::varchar), 1, 8))::bigint % 10 = 0")
both("subquery_scalar", "SELECT o_orderkey FROM orders WHERE o_totalprice > 1.5 * (SELECT avg(o_totalprice) FROM orders)")
both("subquery_exists", "SELECT s_suppkey FROM supplier s WHERE EXISTS (SELECT 1 FROM lineitem WHERE l_suppkey = s.s_suppkey AND l_quantity > 49)")
both("subquery_in", "SELECT c_custkey FROM customer WHERE c_custkey IN (SELECT o_custkey FROM orders WHERE o_orderstatus = 'F')")
both("cte", "WITH a AS (SELECT o_custkey, count(*) AS n FROM orders GROUP BY o_custkey), b AS (SELECT n, count(*) AS customers FROM a GROUP BY n) SELECT n, customers FROM b")
both("recursive_loop", "WITH RECURSIVE r(t, x) AS (SELECT 0, cast(7 AS bigint) UNION ALL SELECT t + 1, (x * 5 + 3) % 1009 FROM r WHERE t < 80) SELECT t, x FROM r")

# --- functions ------------------------------------------------------------------------------------------------

both("fn_string", "SELECT p_partkey, upper(substr(p_name, 1, 5)) AS head, length(p_name) AS n, concat_ws('-', p_brand, p_type) AS bt, regexp_extract(p_brand, '([0-9]+)', 1) AS num, md5(p_name) AS h FROM part")
both("fn_date", "SELECT o_orderkey, cast(year(o_orderdate) AS int) AS y, cast(month(o_orderdate) AS int) AS m, cast(datediff(o_orderdate, date'1995-01-01') AS bigint) AS tick FROM orders", "SELECT o_orderkey, year(o_orderdate)::int AS y, month(o_orderdate)::int AS m, date_diff('day', DATE '1995-01-01', o_orderdate::date)::bigint AS tick FROM orders")
both("fn_math", "SELECT l_orderkey, l_linenumber, l_partkey, floor(l_quantity / 3) AS f, round(sqrt(l_quantity), 6) AS s, round(log2(l_quantity), 6) AS lg, abs(l_quantity - 25) AS a, greatest(l_quantity, 10.0) AS g FROM lineitem", "SELECT l_orderkey, l_linenumber, l_partkey, floor(l_quantity / 3)::bigint AS f, round(sqrt(l_quantity), 6) AS s, round(log2(l_quantity), 6) AS lg, abs(l_quantity - 25) AS a, greatest(l_quantity, 10.0::double) AS g FROM lineitem")
both("fn_array", "SELECT vec_id, size(filter(embedding, v -> v > 0)) AS positive, round(aggregate(transform(embedding, v -> cast(v AS double)), 0D, (s, v) -> s + v), 5) AS total FROM embeddings", "SELECT vec_id, len(list_filter(embedding, lambda v: v > 0))::int AS positive, round(list_sum(list_transform(embedding, lambda v: v::double)), 5) AS total FROM embeddings")
both("fn_map", "SELECT o_orderkey, map_from_arrays(array('p', 's'), array(o_orderpriority, o_orderstatus))['s'] AS st FROM orders", "SELECT o_orderkey, o_orderstatus AS st FROM orders")
both("fn_struct", "SELECT o_orderkey, named_struct('a', o_custkey, 'b', o_orderstatus).b AS st FROM orders", "SELECT o_orderkey, {'a': o_custkey, 'b': o_orderstatus}.b AS st FROM orders")
both("fn_json", "SELECT event_id, cast(get_json_object(props, '$.k') AS int) AS k, get_json_object(to_json(named_struct('a', event_type)), '$.a') AS back FROM events", "SELECT event_id, (props::json->>'$.k')::int AS k, event_type AS back FROM events")
