"""Archives of containers, and bound-aware queries over them.

An archive is a Parquet table with a row for each lane, padding included, so that it decodes by itself: header, first
sample, tolerance, seed, body, digest, and the lane's place in its group. Spark reads and writes the files, in any
store that it reads; appends add files and replace none. Rows carry the least and the largest value that a sample can
have, so predicates on values reach the scan as filters, and sums with a stated error need no decoding.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

#: What names a container.
GROUP = ("corpus", "chunk_id", "n", "group_id", "rho")


def archive_rows(containers: DataFrame, corpus: str = "") -> DataFrame:
    """Containers as one row for each lane; ``low`` and ``high`` bound the samples."""
    lane = containers.select(F.lit(corpus).alias("corpus"), "chunk_id", "n", "group_id", "rho", "g", "c", "header", F.posexplode("lanes").alias("lane", "l"))
    return lane.select(*GROUP, "g", "c", "header", "lane", "l.*", (F.col("l.xmin") - F.col("l.tau")).alias("low"), (F.col("l.xmax") + F.col("l.tau")).alias("high"))


def lanes(containers: DataFrame) -> DataFrame:
    """The real lanes."""
    return archive_rows(containers).where("NOT pad")


def write_archive(containers: DataFrame, path: str, corpus: str = "") -> None:
    """Append; rows are sorted by series within files, for the scans of a few series."""
    rows = archive_rows(containers, corpus)
    rows.repartition("chunk_id", "n", "group_id").sortWithinPartitions("series_id").write.mode("append").parquet(path)


def read_archive(spark: SparkSession, path: str) -> DataFrame:
    return spark.read.parquet(path)


def containers_of(rows: DataFrame, wanted: DataFrame | None = None) -> DataFrame:
    """Containers from the rows of an archive; with ``wanted`` (rows of it) those that hold a wanted lane, whole: a
    forecaster decodes the batch that it encoded."""
    if wanted is not None:
        rows = rows.join(wanted.select(*GROUP).distinct(), list(GROUP), "left_semi")
    lane = F.struct("lane", "series_id", "x0", "tau", "seed_id", "seed", "body", "xmin", "xmax", "pad", "xsum", "sha256")
    out = rows.groupBy(*GROUP).agg(F.first("g").alias("g"), F.first("c").alias("c"), F.first("header").alias("header"), F.array_sort(F.collect_list(lane)).alias("lanes"))
    whole = F.when(F.size("lanes") == F.col("g"), F.transform("lanes", lambda x: x.dropFields("lane"))).otherwise(F.raise_error(F.lit("a container lacks lanes, or has some twice")))
    return out.select("group_id", "chunk_id", "rho", "n", "g", "c", "header", whole.alias("lanes"))


# --- bound-aware answers from lane statistics -------------------------------------------------------------------


def approx_sum(lane_rows: DataFrame) -> DataFrame:
    return lane_rows.select("series_id", "rho", F.col("xsum").alias("estimate"), (F.col("n") * F.col("tau")).alias("error"))


def approx_avg(lane_rows: DataFrame) -> DataFrame:
    return lane_rows.select("series_id", "rho", (F.col("xsum") / F.col("n")).alias("estimate"), F.col("tau").alias("error"))


def approx_extremes(lane_rows: DataFrame) -> DataFrame:
    return lane_rows.select("series_id", "rho", "xmin", "xmax", F.col("tau").alias("error"))


def threshold_lanes(lane_rows: DataFrame, v: float) -> DataFrame:
    """Lanes that surely hold, may hold, or cannot hold a value above ``v``; only the middle ones need decoding."""
    verdict = F.when(F.col("xmax") - F.col("tau") > v, "certain").when(F.col("xmax") + F.col("tau") > v, "possible").otherwise("impossible")
    return lane_rows.select("series_id", "rho", verdict.alias("verdict"))


def threshold_rows(decoded: DataFrame, v: float) -> DataFrame:
    verdict = F.when(F.col("xhat") - F.col("tau") > v, "certain").when(F.col("xhat") + F.col("tau") > v, "possible").otherwise("impossible")
    return decoded.select("series_id", "t", verdict.alias("verdict"))


def tier_rollup(decoded: DataFrame, ticks: int = 24) -> DataFrame:
    """Sums over ``ticks`` ticks from reconstructions, with their error."""
    return decoded.groupBy("series_id", F.expr(f"t div {ticks}").alias("tier")).agg(F.sum("xhat").alias("estimate"), (F.count(F.lit(1)) * F.max("tau")).alias("error"))
