"""What experiments share: the pooled forecaster and the table of real bytes of a corpus."""

from __future__ import annotations

from functools import lru_cache

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from boundspark.operators.codec import CLASSICAL, arrays, study
from boundspark.operators.forecast import Pooled, fit_pooled
from boundspark.plans import series as S
from boundspark.sources.tables import scratch

#: Generated corpora that only the fit reads; evaluation corpora have other seeds, so no tick is shared.
TRAIN_SEEDS = ("train-a", "train-b")
SMALL = {"n_series": 12, "n_ticks": 1600}


@lru_cache(maxsize=4)
def _fitted(app_id: str, spark: SparkSession) -> Pooled:
    train = None
    for seed, noise in zip(TRAIN_SEEDS, (300, 3000), strict=True):
        rows = arrays(S.gen_demand(spark, 12, 2400, seed, noise))
        train = rows if train is None else train.union(rows)
    return fit_pooled(train)


def forecaster(spark: SparkSession) -> Pooled:
    """Fitted once for a session."""
    return _fitted(spark.sparkContext.applicationId, spark)


def corpus(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    if name == "gen_demand":
        return S.gen_demand(spark, **SMALL)
    if name == "gen_smooth":
        return S.gen_smooth(spark)
    if name == "gen_iid":
        return S.gen_iid(spark, 6000)
    if name == "uniform_k_bucket":
        return S.uniform_k_bucket(spark, sf_dir)
    return S.CATALOG[name](spark, sf_dir)


_TABLES: dict[tuple, str] = {}


def bytes_table(spark: SparkSession, sf_dir: str, name: str, c: int = 256) -> DataFrame:
    """The study of a corpus, written once for a session and read from there by the experiments."""
    key = (spark.sparkContext.applicationId, sf_dir, name, c)
    if key not in _TABLES:
        path = scratch(spark, f"study-{name}")
        study(corpus(spark, sf_dir, name), name, forecaster(spark), c).write.parquet(path)
        _TABLES[key] = path
    return spark.read.parquet(_TABLES[key])


def gains(table: DataFrame, size: str = "bytes") -> DataFrame:
    """(corpus, series_id, rho, n, classic, codec, gain, best): real bytes of the best of six against the codec."""
    classic = table.where(F.col("coder").isin(*CLASSICAL)).groupBy("corpus", "series_id", "rho").agg(F.min(size).alias("classic"), F.min_by("coder", F.struct(size, "coder")).alias("best"), F.first("rel_err_pct").alias("rel_err_pct"))
    codec = table.where("coder = 'codec'").select("corpus", "series_id", "rho", "n", F.col(size).alias("codec"))
    out = classic.join(codec, ["corpus", "series_id", "rho"])
    return out.withColumn("gain", 100 * (1 - F.col("codec") / F.col("classic")))
