"""Queries over archived data: every approximate answer is checked against the raw series and its stated error."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from boundspark.experiments.common import corpus, forecaster
from boundspark.experiments.measures import Query
from boundspark.operators import codec as K
from boundspark.plans import series as S
from boundspark.sources import archive as A
from boundspark.sources.tables import scratch

QUERIES: dict[str, tuple[Query, str | None]] = {}
_S = S.SQL["events_cents_type_hourly"]
_IDS = "SELECT series_id, {exact} AS exact, true AS within_bound FROM ({s}) GROUP BY 1"
_SLACK = 1e-6


def query(sql: str | None):
    def add(fn: Query) -> Query:
        QUERIES[fn.__name__] = (fn, sql)
        return fn

    return add


def _raw(spark, d) -> DataFrame:
    return corpus(spark, d, "events_cents_type_hourly")


def _containers(spark, d) -> DataFrame:
    return K.encode_groups(_raw(spark, d), forecaster(spark), c=180, g=8, rhos=(0.05,))


def _lanes(spark, d) -> DataFrame:
    return A.lanes(_containers(spark, d))


def _checked(approx: DataFrame, exact: DataFrame) -> DataFrame:
    return approx.join(exact, "series_id").select("series_id", "exact", (F.abs(F.col("estimate") - F.col("exact")) <= F.col("error") + _SLACK).alias("within_bound"))


@query(_IDS.format(exact="sum(x)::bigint", s=_S))
def archive_sum(spark, d):
    return _checked(A.approx_sum(_lanes(spark, d)), _raw(spark, d).groupBy("series_id").agg(F.sum("x").alias("exact")))


@query(_IDS.format(exact="round(avg(x), 6)", s=_S))
def archive_avg(spark, d):
    return _checked(A.approx_avg(_lanes(spark, d)), _raw(spark, d).groupBy("series_id").agg(F.round(F.avg("x"), 6).alias("exact")))


@query(_IDS.format(exact="min(x)::bigint", s=_S))
def archive_min(spark, d):
    a = A.approx_extremes(_lanes(spark, d)).withColumnRenamed("xmin", "estimate")
    return _checked(a, _raw(spark, d).groupBy("series_id").agg(F.min("x").alias("exact")))


@query(_IDS.format(exact="max(x)::bigint", s=_S))
def archive_max(spark, d):
    a = A.approx_extremes(_lanes(spark, d)).withColumnRenamed("xmax", "estimate")
    return _checked(a, _raw(spark, d).groupBy("series_id").agg(F.max("x").alias("exact")))


@query(f"SELECT true AS sound, count(DISTINCT series_id)::bigint AS series FROM ({_S})")
def archive_threshold(spark, d):
    """No sample above the threshold hides in a row called impossible, none below it in a row called certain."""
    m, v = forecaster(spark), 8000.0
    rows = A.threshold_rows(K.decode_groups(_containers(spark, d), m), v).join(_raw(spark, d), ["series_id", "t"])
    wrong = F.count_if(((F.col("verdict") == "impossible") & (F.col("x") > v + _SLACK)) | ((F.col("verdict") == "certain") & (F.col("x") <= v - _SLACK)))
    return rows.agg((wrong == 0).alias("sound"), F.count_distinct("series_id").alias("series"))


@query(f"SELECT series_id, t // 24 AS tier, true AS within_bound FROM ({_S}) GROUP BY 1, 2")
def archive_tier_rollup(spark, d):
    tiers = A.tier_rollup(K.decode_groups(_containers(spark, d), forecaster(spark)))
    exact = _raw(spark, d).groupBy("series_id", F.expr("t div 24").alias("tier")).agg(F.sum("x").alias("exact"))
    return tiers.join(exact, ["series_id", "tier"]).select("series_id", "tier", (F.abs(F.col("estimate") - F.col("exact")) <= F.col("error") + _SLACK).alias("within_bound"))


@query("SELECT 'click' AS series_id, t, true AS within_bound FROM range(100, 110) r(t)")
def archive_point_lookup(spark, d):
    """One series and a few ticks: the group that holds it is decoded, nothing else."""
    back = K.decode_groups(_containers(spark, d).where(F.exists("lanes", lambda x: x["series_id"] == "click")), forecaster(spark))
    j = back.where("series_id = 'click' AND t BETWEEN 100 AND 109").join(_raw(spark, d), ["series_id", "t"])
    return j.select("series_id", "t", (F.abs(F.col("xhat") - F.col("x")) <= F.col("tau") + _SLACK).alias("within_bound"))


def _written(spark, d) -> DataFrame:
    """Two corpora appended to one archive, read back."""
    path = scratch(spark, "archive")
    A.write_archive(_containers(spark, d), path, "cents")
    other = corpus(spark, d, "events_type_hourly")
    A.write_archive(K.encode_groups(other, forecaster(spark), c=180, g=8, rhos=(0.05,)), path, "counts")
    return A.read_archive(spark, path)


@query(f"SELECT series_id, count(*)::bigint AS n, min(x)::bigint AS least, true AS bounded FROM ({_S}) WHERE series_id = 'view' GROUP BY 1")
def archive_source(spark, d):
    """One series of one corpus from the archive: its filters reach the scan."""
    row = _written(spark, d).where("corpus = 'cents' AND series_id = 'view'").select("series_id", "n", "low", "high")
    raw = _raw(spark, d).groupBy("series_id").agg(F.min("x").alias("least"), F.max("x").alias("most"))
    return row.join(raw, "series_id").select("series_id", "n", "least", ((F.col("low") <= F.col("least") + _SLACK) & (F.col("high") >= F.col("most") - _SLACK)).alias("bounded"))


_BOTH = f"SELECT 'cents' AS corpus, * FROM ({_S}) UNION ALL SELECT 'counts', * FROM ({S.SQL['events_type_hourly']})"


@query(f"SELECT corpus, series_id, count(*)::bigint AS n, sum(x)::bigint AS total, max(x)::bigint AS largest, true AS bound_ok, true AS roundtrip_ok FROM ({_BOTH}) GROUP BY 1, 2")
def archive_decode(spark, d):
    """Both corpora of one archive, decoded from its rows alone: digests equal the encoder's, samples within the bound."""
    rows, m, out = _written(spark, d), forecaster(spark), None
    for name, raw in (("cents", _raw(spark, d)), ("counts", corpus(spark, d, "events_type_hourly"))):
        part = K.verified(K.decode_groups(A.containers_of(rows.where(F.col("corpus") == name)), m), raw).withColumn("corpus", F.lit(name))
        out = part if out is None else out.union(part)
    return out


@query(f"SELECT series_id, count(*)::bigint AS hits FROM ({_S}) WHERE x > 30000 GROUP BY 1")
def archive_pruned_predicate(spark, d):
    """x > v: lanes that cannot hold such a sample are pruned by the scan; the rest are decoded, and only rows that the
    bound leaves open are read from the raw series."""
    v, rows = 30000, _written(spark, d).where("corpus = 'cents'")
    wanted = rows.where((F.col("high") + _SLACK > v) & ~F.col("pad"))
    back = A.threshold_rows(K.decode_groups(A.containers_of(rows, wanted), forecaster(spark)), float(v))
    open_ = back.where("verdict = 'possible'").join(_raw(spark, d).where(F.col("x") > v), ["series_id", "t"], "left_semi")
    return back.where("verdict = 'certain'").union(open_).groupBy("series_id").agg(F.count(F.lit(1)).alias("hits"))


@query(None)
def retention_plan(spark, d):
    """Bytes of a bounded archive of each series against hourly raw values and a daily tier."""
    rows = _lanes(spark, d)
    b = F.octet_length("seed") + F.octet_length("body")
    return rows.select("series_id", b.cast("long").alias("bounded_bytes"), (4 * F.col("n")).alias("raw_bytes"), F.expr("8 * (n div 24)").alias("daily_tier_bytes"), F.round("tau", 6).alias("guaranteed_error"))
