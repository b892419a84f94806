"""Structured Streaming over event files: windows, late rows, joins, and stateful encoders of the lattice and of groups.

Queries here run to the end of the available files and return what the sink holds; production code would give the
same transformations a long-lived trigger. The tolerance of a stream is fixed beforehand, from a calibration batch.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

from boundspark.operators import entropy as E
from boundspark.sources.tables import scratch, table

Query = Callable[[SparkSession, str], DataFrame]
QUERIES: dict[str, tuple[Query, str | None]] = {}
STEP = 500.0  # calibrated: cents


def query(sql: str | None):
    def add(fn: Query) -> Query:
        QUERIES["st_" + fn.__name__] = (fn, sql)
        return fn

    return add


def events_stream(spark: SparkSession, d: str) -> DataFrame:
    schema = table(spark, d, "events").schema
    # The pattern takes the table as one file and as a folder of files; each file is a batch.
    raw = spark.readStream.schema(schema).option("maxFilesPerTrigger", 1).parquet(f"{d}/events.parquet*")
    return raw.withColumn("ts", F.col("ts").cast("timestamp"))


def drain(stream: DataFrame, mode: str = "append") -> DataFrame:
    """Run until the input is used up; rows land in a table in the shared folder, batch by batch, each written once.
    In complete mode each batch replaces the one before."""
    spark = stream.sparkSession
    path = scratch(spark, "stream")
    spark.createDataFrame([], stream.schema).write.parquet(f"{path}/batch=-1")  # a stream without rows has a result too

    def put(batch: DataFrame, batch_id: int) -> None:
        batch.write.mode("overwrite").parquet(f"{path}/batch={0 if mode == 'complete' else batch_id}")

    stream.writeStream.outputMode(mode).foreachBatch(put).option("checkpointLocation", f"{path}-log").trigger(availableNow=True).start().awaitTermination()
    return spark.read.schema(stream.schema).parquet(f"{path}/batch=*")


@query("SELECT event_id, user_id, event_type FROM events")
def scan(spark, d):
    return drain(events_stream(spark, d).select("event_id", "user_id", "event_type"))




@query(f"SELECT date_diff('hour', TIMESTAMP '2024-01-01', time_bucket(INTERVAL 1 HOUR, ts)) AS hour, count(*) AS n FROM events GROUP BY 1")
def tumbling(spark, d):
    """Hourly counts under a watermark."""
    w = events_stream(spark, d).withWatermark("ts", "1 hour").groupBy(F.window("ts", "1 hour")).agg(F.count(F.lit(1)).alias("n"))
    out = drain(w.select(F.col("window.start").alias("s"), "n"), "update")
    last = out.groupBy("s").agg(F.max("n").alias("n"))
    return last.select(F.expr("timestampdiff(HOUR, timestamp'2024-01-01', s)").cast("long").alias("hour"), "n")


@query("SELECT date_diff('minute', TIMESTAMP '2024-01-01', s) AS minute, count(*) AS n FROM (SELECT unnest([time_bucket(INTERVAL 30 MINUTE, ts) - INTERVAL 30 MINUTE * i FOR i IN range(4)]) AS s FROM events) GROUP BY 1")
def sliding(spark, d):
    w = events_stream(spark, d).withWatermark("ts", "1 hour").groupBy(F.window("ts", "2 hours", "30 minutes")).agg(F.count(F.lit(1)).alias("n"))
    last = drain(w.select(F.col("window.start").alias("s"), "n"), "update").groupBy("s").agg(F.max("n").alias("n"))
    return last.select(F.expr("timestampdiff(MINUTE, timestamp'2024-01-01', s)").cast("long").alias("minute"), "n")


@query("WITH g AS (SELECT user_id, CASE WHEN ts < lag(ts) OVER w + INTERVAL 30 MINUTE THEN 0 ELSE 1 END AS opens FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts)) SELECT user_id, sum(opens)::bigint AS sessions, count(*) AS events FROM g GROUP BY 1")
def session(spark, d):
    """Sessions of a user, closed by 30 quiet minutes."""
    w = events_stream(spark, d).groupBy("user_id", F.session_window("ts", "30 minutes")).agg(F.count(F.lit(1)).alias("n"))
    out = drain(w.select("user_id", "n"), "complete")
    return out.groupBy("user_id").agg(F.count(F.lit(1)).alias("sessions"), F.sum("n").alias("events"))


@query("WITH h AS (SELECT *, event_id % 97 = 0 AS late FROM events) SELECT count(*) FILTER (WHERE NOT late) AS on_time, count(*) FILTER (WHERE late) AS patched FROM h")
def late(spark, d):
    """Rows marked late go to a patch table, applied after decoding, and none is lost. The mark is a stand-in here: a drain
    to the end of one file closes no window before its rows are in."""
    s = events_stream(spark, d).withColumn("late", F.col("event_id") % 97 == 0).select("event_id", "late")
    out = drain(s)
    return out.agg(F.count_if(~F.col("late")).alias("on_time"), F.count_if("late").alias("patched"))


@query("SELECT DISTINCT event_id FROM events")
def dedup(spark, d):
    """Each event once, though the stream carries it twice."""
    s = events_stream(spark, d).select("event_id", "ts", F.explode(F.array(F.lit(1), F.lit(2))).alias("copy")).withWatermark("ts", "1 hour")
    return drain(s.dropDuplicatesWithinWatermark(["event_id"]).select("event_id"))


@query("SELECT event_id, event_type, 500.0::double AS step FROM events WHERE event_type IN ('click', 'view')")
def tolerance_join(spark, d):
    """Stream against the static table of tolerances."""
    tol = spark.createDataFrame([("click", STEP), ("view", STEP)], "event_type string, step double")
    return drain(events_stream(spark, d).join(tol, "event_type").select("event_id", "event_type", "step"))


@query("SELECT c.event_id AS click_id, p.event_id AS purchase_id FROM events c JOIN events p ON c.user_id = p.user_id AND c.event_type = 'click' AND p.event_type = 'purchase' AND p.ts >= c.ts AND p.ts <= c.ts + INTERVAL 1 HOUR")
def join(spark, d):
    """Purchases within an hour of a click of the same user: two watermarks and an interval bound the state."""
    e = events_stream(spark, d)
    c = e.where("event_type = 'click'").select(F.col("user_id").alias("cu"), F.col("event_id").alias("click_id"), F.col("ts").alias("cts")).withWatermark("cts", "1 hour")
    p = events_stream(spark, d).where("event_type = 'purchase'").select(F.col("user_id").alias("pu"), F.col("event_id").alias("purchase_id"), F.col("ts").alias("pts")).withWatermark("pts", "1 hour")
    j = c.join(p, F.expr("cu = pu AND pts >= cts AND pts <= cts + INTERVAL 1 HOUR"))
    return drain(j.select("click_id", "purchase_id"))


def _lattice(key: tuple, parts: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
    """State of a series: base and last lattice point. Order inside a batch is by event id."""
    rows = pd.concat(list(parts)).sort_values("event_id")
    x = np.round(rows["value"].to_numpy() * 100).astype(np.int64)
    base, last = state.get if state.exists else (int(x[0]), 0)
    q = np.floor((x - base) / STEP + 0.5).astype(np.int64)
    state.update((base, int(q[-1])))
    yield pd.DataFrame({"series_id": key[0], "event_id": rows["event_id"].to_numpy(), "k": np.diff(q, prepend=last)})


@query("WITH s AS (SELECT event_type AS series_id, event_id, round(value * 100)::bigint AS x FROM events), q AS (SELECT series_id, event_id, floor((x - first_value(x) OVER w) / 500.0::double + 0.5)::bigint AS q FROM s WINDOW w AS (PARTITION BY series_id ORDER BY event_id)) SELECT series_id, event_id, q - coalesce(lag(q) OVER (PARTITION BY series_id ORDER BY event_id), 0) AS k FROM q")
def lattice(spark, d):
    """The lattice encoder with state: indices equal those of the batch form."""
    s = events_stream(spark, d).select("event_type", "event_id", "value").groupBy("event_type")
    return drain(s.applyInPandasWithState(_lattice, "series_id string, event_id long, k long", "base long, last long", "append", GroupStateTimeout.NoTimeout))


def _coded(key: tuple, parts: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
    """State: base, last point. Each batch flushes one container body, range coded, that decodes on its own."""
    rows = pd.concat(list(parts)).sort_values("event_id")
    x = np.round(rows["value"].to_numpy() * 100).astype(np.int64)
    base, last = state.get if state.exists else (int(x[0]), 0)
    q = np.floor((x - base) / STEP + 0.5).astype(np.int64)
    k = np.diff(q, prepend=last)
    state.update((base, int(q[-1])))
    body = E.encode_lanes([k])[0]
    back = base + np.cumsum(np.r_[last, E.decode_lane(body, len(k))])[1:] * STEP
    yield pd.DataFrame({"series_id": [key[0]], "n": [len(k)], "bytes": [len(body)], "bound_ok": [bool(np.abs(back - x).max() <= STEP / 2 + 1e-9)]})


@query("SELECT event_type AS series_id, count(*) AS n, true AS bound_ok FROM events GROUP BY 1")
def group_encode(spark, d):
    """Containers flushed from the stream: decoded values stay within the bound."""
    s = events_stream(spark, d).select("event_type", "event_id", "value").groupBy("event_type")
    out = drain(s.applyInPandasWithState(_coded, "series_id string, n long, bytes long, bound_ok boolean", "base long, last long", "append", GroupStateTimeout.NoTimeout))
    return out.groupBy("series_id").agg(F.sum("n").alias("n"), F.min("bound_ok").alias("bound_ok"))


__all__ = ["QUERIES", "drain", "events_stream"]
