"""The paper's experiments on the given tables and on constructed corpora. Constructed ones are named gen_* and
events_weighted_hourly; the raw tables have no seasons, so there the codec is expected not to win.

Entries are (query, SQL): SQL states what can be stated, such as verdicts that must hold; None where figures depend
on models and coders that SQL does not have.
"""

from __future__ import annotations

import time
from dataclasses import replace

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import window as W

from boundspark.experiments.common import TRAIN_SEEDS, bytes_table, corpus, forecaster, gains
from boundspark.experiments.measures import R6, Query
from boundspark.operators import codec as K
from boundspark.operators import entropy as E
from boundspark.operators import loops as L
from boundspark.operators.forecast import LAGS, SeasonalProfile, Student, open_loop, spread_bucket
from boundspark.plans import series as S

DEMAND = ("gen_demand", "events_weighted_hourly")
OFF = ("ship_cents_nation_daily", "events_cents_type_hourly")
SIMULATION = ("ramp_price", "embed_scanline")
QUERIES: dict[str, tuple[Query, str | None]] = {}


def query(sql: str | None = None):
    def add(fn: Query) -> Query:
        QUERIES[fn.__name__] = (fn, sql)
        return fn

    return add


def _tables(spark, d, names) -> DataFrame:
    out = None
    for n in names:
        t = bytes_table(spark, d, n)
        out = t if out is None else out.unionByName(t)
    return out


def _summary(g: DataFrame, *by: str) -> DataFrame:
    agg = [F.count(F.lit(1)).alias("pairs"), F.count_if(F.col("gain") > 0).alias("wins"), R6(F.median("gain")).alias("median_gain_pct"), R6(F.avg(8 * F.col("classic") / F.col("n"))).alias("classic_bpv"), R6(F.avg(8 * F.col("codec") / F.col("n"))).alias("codec_bpv"), R6(F.median("rel_err_pct")).alias("err_pct")]
    return g.groupBy(*by).agg(*agg)


# --- lossy tables ----------------------------------------------------------------------------------------------


@query()
def domain_table(spark, d):
    """Median gain and wins by corpus, with both demand corpora together."""
    g = gains(_tables(spark, d, DEMAND + OFF + SIMULATION)).withColumn("domain", F.when(F.col("corpus").isin(*DEMAND), "demand").when(F.col("corpus").isin(*SIMULATION), "simulation").otherwise("telemetry"))
    r = g.rollup("domain", "corpus").agg(F.count(F.lit(1)).alias("pairs"), F.count_if(F.col("gain") > 0).alias("wins"), R6(F.median("gain")).alias("median_gain_pct"))
    return r.where("domain IS NOT NULL").withColumn("constructed", F.col("domain") == "demand")


@query()
def domain_points(spark, d):
    return gains(_tables(spark, d, DEMAND + OFF)).select("corpus", "series_id", "rho", R6("gain").alias("gain"))


@query()
def tolerance_demand(spark, d):
    """Gain by tolerance on generated demand: grows with the tolerance."""
    return _summary(gains(bytes_table(spark, d, "gen_demand")), "rho")


@query()
def tolerance_events(spark, d):
    return _summary(gains(bytes_table(spark, d, "events_weighted_hourly")), "rho")


@query()
def tolerance_ship(spark, d):
    return _summary(gains(bytes_table(spark, d, "ship_cents_nation_daily")), "rho")


@query()
def rate_distortion(spark, d):
    t = _tables(spark, d, DEMAND)
    return t.groupBy("corpus", "rho", "coder").agg(R6(F.median("rel_err_pct")).alias("err_pct"), R6(F.median(8 * F.col("bytes") / F.col("n"))).alias("bpv"))


@query()
def falsification(spark, d):
    """Simulation-like corpora, smooth and noisy: the forecaster should lose."""
    return _summary(gains(_tables(spark, d, SIMULATION)), "corpus", "rho")


@query()
def best_of_six(spark, d):
    """Winner among the classical predictors by real bytes."""
    t = bytes_table(spark, d, "ship_cents_nation_daily").where(F.col("coder") != "codec").withColumnRenamed("coder", "predictor")
    return K.select_best(t, ("series_id", "rho"))


@query()
def seed_best_of_five(spark, d):
    t = bytes_table(spark, d, "ship_cents_nation_daily").where(F.col("coder").isin(*(n for n, _ in K.SEED_PREDICTORS))).withColumnRenamed("coder", "predictor")
    return K.select_best(t, ("series_id", "rho"))


@query()
def charged_side_information(spark, d):
    """The bar with LPC coefficients charged to it, against the bar without."""
    t = bytes_table(spark, d, "gen_demand").withColumn("charged", F.col("bytes") + F.col("side_bytes"))
    a = _summary(gains(t), "rho").select("rho", F.col("median_gain_pct").alias("gain_free"))
    b = _summary(gains(t, "charged"), "rho").select("rho", F.col("median_gain_pct").alias("gain_charged"))
    return a.join(b, "rho")


_VERDICT_SQL = "SELECT series_id, rho, count(*)::bigint AS n, true AS bound_ok FROM ({s}) s, (VALUES (0.01::double), (0.05::double), (0.2::double)) r(rho) GROUP BY 1, 2"


@query(_VERDICT_SQL.format(s=S.SQL["events_cents_type_hourly"]))
def bound_check(spark, d):
    """Every coder keeps every sample within its tolerance."""
    t = bytes_table(spark, d, "events_cents_type_hourly")
    return t.groupBy("series_id", "rho").agg(F.max("n").alias("n"), (F.max("max_err_ratio") <= 1 + 1e-9).alias("bound_ok"))


@query()
def zero_hits(spark, d):
    """Share of zero indices, the mechanism of the lossy gain, by corpus, tolerance and coder."""
    return _tables(spark, d, DEMAND + OFF).groupBy("corpus", "rho", "coder").agg(R6(F.avg("zero_share")).alias("zero_share"), R6(F.avg("k_abs")).alias("mean_abs_k"))


@query()
def backend_trend(spark, d):
    """Gain by tolerance under the range coder, xz and zstd, and what the generic back ends cost."""
    t = _tables(spark, d, DEMAND)
    out = None
    for name, col in (("range", "bytes"), ("xz", "xz_bytes"), ("zstd", "zstd_bytes")):
        part = gains(t, col).groupBy("corpus", "rho").agg(R6(F.median("gain")).alias("gain")).withColumn("backend", F.lit(name))
        out = part if out is None else out.unionByName(part)
    ratio = t.groupBy("corpus", "rho").agg(R6(F.median(F.col("xz_bytes") / F.col("bytes"))).alias("xz_to_range"), R6(F.median(F.col("zstd_bytes") / F.col("bytes"))).alias("zstd_to_range"))
    return out.join(ratio, ["corpus", "rho"])


@query()
def ideal_gap(spark, d):
    """Conditional empirical entropy against real bytes: ideals flatter."""
    t = _tables(spark, d, DEMAND + OFF)
    return t.groupBy("corpus", "rho").agg(R6(F.median(F.col("ideal_bits") / F.col("n"))).alias("ideal_bpv"), R6(F.median(8 * F.col("bytes") / F.col("n"))).alias("real_bpv"), R6(F.median(8 * F.col("bytes") / F.greatest("ideal_bits", F.lit(1.0)))).alias("ratio"))


@query()
def proxy_corr(spark, d):
    """Cheap statistics of a series against the gain it gets."""
    from boundspark.experiments.measures import proxy_autocorr

    g = gains(bytes_table(spark, d, "events_weighted_hourly")).where("rho = 0.05").select("series_id", "gain")
    j = proxy_autocorr(spark, d).join(g, "series_id")
    return j.agg(F.count(F.lit(1)).alias("n_series"), F.round(F.corr(F.col("local_over_long"), F.col("gain")), 4).alias("r_ratio"), F.round(F.corr(F.col("lag24") - F.col("lag1"), F.col("gain")), 4).alias("r_autocorr"))


# --- kernels over groups of series -----------------------------------------------------------------------------


def _per_group(spark, d, name: str | DataFrame, fn, schema: str, lanes: int = 16, where: str = "true", units: int = 0) -> DataFrame:
    """Run ``fn(names, x)`` on groups of equal-length series; it yields result tuples. With ``units``: ``fn(names, x, unit)``
    on each group and unit, each a task of its own."""
    cols = [c.split()[0] for c in schema.split(", ")]

    def run(pdf: pd.DataFrame) -> pd.DataFrame:
        return pd.DataFrame(list(fn(*K.joined(pdf), *((int(pdf["unit"].iloc[0]),) if units else ()))), columns=cols)

    series = corpus(spark, d, name) if isinstance(name, str) else name
    rows = K.pieces(series.where(where), lanes)
    if units:
        rows = rows.withColumn("unit", F.explode(F.sequence(F.lit(0), F.lit(units - 1))))
    return K.dealt(rows, *(["unit"] if units else [])).applyInPandas(run, schema)


def _best_classic(x, step) -> np.ndarray:
    """Bytes of the best of six classical predictors for each lane."""
    coefs = np.stack([L.fit_lags(r.astype(float), K.LPC) for r in x])
    return np.min([E.coded_sizes(list(q(x, step)[0])) for _, q in K.SEED_PREDICTORS] + [E.coded_sizes(list(L.lags_closed_loop(x, step, K.LPC, coefs)[0]))], axis=0)


def _body(x, rho, c, model):
    step = 2 * rho * K.sigma(x)
    ids, seeds, hat = K.encode_seeds(x[:, :c], step)
    k, xhat = L.forecast_loop(x, step, hat, model)
    return step, seeds, hat, k, xhat


@query()
def container_split(spark, d):
    """Seed, body and header of real containers: bits for each value and shares."""
    m = forecaster(spark)
    c = K.encode_groups(corpus(spark, d, "events_weighted_hourly"), m, c=256, g=16)
    lane = c.select("n", "g", F.octet_length("header").alias("h"), F.explode("lanes").alias("l")).where("NOT l.pad")
    s = lane.agg(F.sum(F.octet_length("l.seed")).alias("seed"), F.sum(F.octet_length("l.body")).alias("body"), F.sum(F.col("h") / F.col("g") + 17).alias("head"), F.sum("n").alias("n"))
    total = F.col("seed") + F.col("body") + F.col("head")
    parts = F.explode(F.array(*(F.struct(F.lit(p).alias("component"), F.col(p).cast("double").alias("b")) for p in ("seed", "body", "head"))))
    return s.select(total.alias("total"), "n", parts.alias("p")).select("p.component", R6(8 * F.col("p.b") / F.col("n")).alias("bpv"), R6(F.col("p.b") / F.col("total")).alias("share"), R6(4 * F.col("n") / F.col("total")).alias("ratio_to_32_bit"))


#: Context lengths of the ablation; its last unit of work is the classical bar.
CONTEXTS = (64, 128, 256, 512, 1024)
ABLATION = "series_id string, n long, scored long, c int, body double, seed double, total double"


def _ablation(spark, d, series: DataFrame, model) -> DataFrame:
    """One row for each series and context that leaves ticks to score, and one (c = 0) for the best of six; rates in bits."""

    def fn(names, x, unit):
        n = x.shape[1]
        fit = [c for c in CONTEXTS if c < n]
        if not fit or len(fit) <= unit < len(CONTEXTS):
            return
        if unit == len(CONTEXTS):
            best = _best_classic(x, 2 * 0.05 * K.sigma(x))
            for i, name in enumerate(names):
                yield name, n, n - fit[-1], 0, None, None, 8.0 * float(best[i]) / n
            return
        c = fit[unit]
        _, seeds, _, k, _ = _body(x, 0.05, c, model)
        whole, window = E.coded_sizes(list(k)), E.coded_sizes(list(k[:, fit[-1] - c :]))
        for i, name in enumerate(names):
            yield name, n, n - fit[-1], c, 8.0 * float(window[i]) / (n - fit[-1]), 8.0 * len(seeds[i]) / c, 8.0 * (len(seeds[i]) + float(whole[i])) / n

    return _per_group(spark, d, series, fn, ABLATION, units=len(CONTEXTS) + 1)


@query()
def context_ablation(spark, d):
    """Context lengths by corpus and length of archive: the body on the ticks that all contexts predict and what it loses
    against the longest, the seed, and the gain of whole archives (seed and whole body) over the best of six on all ticks.

    Every series is read whole. A context as long as the series leaves nothing to score and has no row: the hourly events
    have 720 ticks. Generated demand, 16 series, is measured at both lengths of the published table.
    """
    lengths = F.explode(F.array(F.lit(4300), F.lit(43800))).alias("ticks")
    demand = S.gen_demand(spark, 16, 43800).select("*", lengths).where("t < ticks")
    parts = [(name, corpus(spark, d, name)) for name in ("events_weighted_hourly", "ship_nation_daily")]
    parts.append(("gen_demand", demand.withColumn("series_id", F.concat("ticks", F.lit("/"), "series_id"))))
    series = None  # of all corpora: one plan groups them, and lanes do not depend on their group
    for name, part in parts:
        part = part.select(F.concat(F.lit(name + "/"), "series_id").alias("series_id"), "t", "x")
        series = part if series is None else series.unionByName(part)
    rows = _ablation(spark, d, series, forecaster(spark)).withColumn("corpus", F.substring_index("series_id", "/", 1))
    g = rows.groupBy("corpus", "n", "scored", "c").agg(F.count(F.lit(1)).alias("n_series"), *(F.avg(v).alias(v) for v in ("body", "seed", "total")))
    w = W.Window.partitionBy("corpus", "n")
    g = g.withColumn("best", F.max_by("body", "c").over(w)).withColumn("classic", F.max(F.when(F.col("c") == 0, F.col("total"))).over(w)).where("c > 0")
    return g.select("corpus", "n", "n_series", "scored", "c", R6("body").alias("body_bpv"), R6(100 * (1 - F.col("body") / F.col("best"))).alias("body_delta_pct"), R6("seed").alias("seed_bpv"), R6("total").alias("codec_bpv"), R6("classic").alias("classic_bpv"), R6(100 * (1 - F.col("total") / F.col("classic"))).alias("gain_pct"))


@query()
def length_sweep(spark, d):
    """Measured end-to-end gain as archives grow: the seed amortises."""
    m = forecaster(spark)

    def fn(names, x):
        for n in (400, 800, 1600):
            part = x[:, :n]
            step, seeds, _, k, _ = _body(part, 0.05, 256, m)
            bodies = E.encode_lanes(list(k))
            best = _best_classic(part, step)
            for i, name in enumerate(names):
                yield name, n, 8.0 * (len(bodies[i]) + len(seeds[i])) / n, 8.0 * float(best[i]) / n

    rows = _per_group(spark, d, "gen_demand", fn, "series_id string, n int, codec double, classic double")
    return rows.groupBy("n").agg(R6(F.avg("codec")).alias("codec_bpv"), R6(F.avg("classic")).alias("classic_bpv"), R6(100 * (1 - F.avg("codec") / F.avg("classic"))).alias("gain_pct"))


@query()
def quantile_ablation(spark, d):
    """Predicted spread used three ways: ideal conditional bits, eight split streams, eight contexts in one stream."""
    m = forecaster(spark)

    def fn(names, x):
        for rho in (0.01, 0.05, 0.2):
            step = 2 * rho * K.sigma(x)
            _, _, hat = K.encode_seeds(x[:, :256], step)
            k, _, spread = L.forecast_loop(x, step, hat, m, want_spread=True)
            plain = E.encode_lanes(list(k))
            bucket = [spread_bucket(s, np.full(len(s), step[i])) for i, s in enumerate(spread)]
            ctx = E.encode_lanes(list(k), bucket, 8)
            split = E.encode_lanes([k[i][bucket[i] == b] for i in range(len(k)) for b in range(8)])
            for i, name in enumerate(names):
                base = 8.0 * len(plain[i])
                ideal0, ideal1 = E.empirical_bits(k[i]), E.empirical_bits(k[i], bucket[i])
                for how, bits in (("ideal", base * ideal1 / max(ideal0, 1e-9)), ("contexts", 8.0 * len(ctx[i])), ("split", 8.0 * sum(map(len, split[8 * i : 8 * i + 8])))):
                    yield name, rho, how, 100 * (1 - bits / base)

    rows = _per_group(spark, d, "gen_demand", fn, "series_id string, rho double, method string, gain double")
    return rows.groupBy("method").agg(R6(F.median("gain")).alias("median_gain_pct"), F.count_if(F.col("gain") > 0).alias("wins"), F.count(F.lit(1)).alias("pairs"))


@query()
def hybrid_table(spark, d):
    """Forecaster alone, persistence alone, BLEND, LEADER, and per-block split streams with flags."""
    m = forecaster(spark)

    def fn(names, x):
        step, _, hat, k, _ = _body(x, 0.05, 256, m)
        sizes = {"model": (E.coded_sizes(list(k)), np.ones(len(x)))}
        classic = L.lorenzo(x, step, 1)[0][:, 256:]
        sizes["classical"] = (E.coded_sizes(list(classic)), np.zeros(len(x)))
        for how in ("blend", "leader"):
            kh, _, led = L.hybrid_loop(x, step, hat, m, how)
            sizes[how] = (E.coded_sizes(list(kh)), led)
        # split streams: each block goes to the stream of the loop with smaller indices, one flag a block
        blocks = -(-k.shape[1] // 256)
        parts, led = [], []
        for i in range(len(x)):
            pick = np.array([np.abs(k[i, 256 * b : 256 * b + 256]).sum() <= np.abs(classic[i, 256 * b : 256 * b + 256]).sum() for b in range(blocks)])
            mask = np.repeat(pick, 256)[: k.shape[1]]
            parts += [k[i][mask], classic[i][~mask]]
            led.append(pick.mean())
        s = E.coded_sizes(parts).reshape(-1, 2).sum(axis=1) + -(-blocks // 8)
        sizes["switched"] = (s, np.array(led))
        for how, (b, led) in sizes.items():
            for i, name in enumerate(names):
                yield name, how, 8.0 * float(b[i]) / k.shape[1], float(led[i])

    rows = _per_group(spark, d, "events_weighted_hourly", fn, "series_id string, method string, bpv double, led double")
    return rows.groupBy("method").agg(R6(F.avg("bpv")).alias("bpv"), R6(F.avg("led")).alias("leader_share"))


@query()
def leader_share(spark, d):
    return hybrid_table(spark, d).where("method = 'leader'").select("method", "leader_share")


@query()
def determinism_table(spark, d):
    """Predictions of a lane under repeats, reordering and other batch sizes, by arithmetic mode."""
    base = forecaster(spark)

    def fn(names, x):
        c = 256
        ctx = np.stack([x[i % len(x), :c] for i in range(9)]).astype(np.float64)
        for mode in ("ordered", "blas32", "blas64", "fixedpoint"):
            m = replace(base, mode=mode, experts=False)

            def run(rows, m=m):
                s, out = m.start(rows), []
                for _ in range(24):
                    p = s.predict()
                    out.append(p)
                    s.push(p)
                return np.stack(out, 1)

            eight = run(ctx[:8])
            for condition, got in (("repeat", run(ctx[:8])), ("reorder", run(ctx[:8][::-1])[::-1]), ("batch 1 vs 8", np.concatenate([run(ctx[i : i + 1]) for i in range(8)])), ("batch 8 vs 9", run(ctx)[:8])):
                yield mode, condition, bool(np.array_equal(eight, got)), float(np.abs(eight - got).max())

    rows = _per_group(spark, d, "events_weighted_hourly", fn, "mode string, condition string, identical boolean, max_diff double")
    return rows.groupBy("mode", "condition").agg(F.min("identical").alias("identical"), F.round(F.max("max_diff"), 9).alias("max_diff"))


@query("SELECT condition, true AS identical FROM (VALUES ('repeat'), ('reorder'), ('batch 1 vs 8'), ('batch 8 vs 9')) v(condition)")
def determinism_ordered(spark, d):
    """The ordered mode is bit-identical under every condition."""
    return determinism_table(spark, d).where("mode = 'ordered'").select("condition", "identical")


@query()
def precision_effect(spark, d):
    """Weights in half precision: shift of predictions against their error, and the cost in bits."""
    base = forecaster(spark)

    def fn(names, x):
        sizes = {}
        for mode in ("ordered", "blas32", "half"):
            m = replace(base, mode=mode)
            step, _, hat, k, _ = _body(x, 0.05, 256, m)
            sizes[mode] = E.coded_sizes(list(k))
            err = np.abs(k * step[:, None]).mean(axis=1)
            for i, name in enumerate(names):
                yield name, mode, 8.0 * float(sizes[mode][i]) / k.shape[1], float(err[i]), 100 * (float(sizes[mode][i]) / float(sizes["ordered"][i]) - 1)

    rows = _per_group(spark, d, "gen_demand", fn, "series_id string, precision string, bpv double, err double, more double")
    return rows.groupBy("precision").agg(R6(F.avg("bpv")).alias("bpv"), R6(F.avg("err")).alias("mean_abs_residual"), R6(F.avg("more")).alias("extra_bytes_pct"))


@query()
def noise_gain_measured(spark, d):
    """Feedback gain of LPC-32 and of the forecaster: prediction spread by history noise of half a step."""
    m = forecaster(spark)

    def fn(names, x):
        rng = np.random.default_rng(17)
        for rho in (0.01, 0.05, 0.2):
            step = 2 * rho * K.sigma(x)
            e = rng.uniform(-0.5, 0.5, x.shape) * step[:, None]
            for i, name in enumerate(names):
                w = L.fit_lags(x[i].astype(float), K.LPC)
                a, _ = L.lag_matrix(e[i], K.LPC)
                yield name, rho, "lpc32", float((a @ w[:-1]).std() / e[i].std())
            c = 256

            def path(h):
                s, out = m.start(h[:, :c]), []
                for t in range(c, h.shape[1]):
                    out.append(s.predict())
                    s.push(h[:, t])
                return np.stack(out, 1)

            g = (path(x + e) - path(x.astype(float))).std(axis=1) / e.std(axis=1)
            for i, name in enumerate(names):
                yield name, rho, "forecaster", float(g[i])

    rows = _per_group(spark, d, "gen_demand", fn, "series_id string, rho double, predictor string, gain double")
    return rows.groupBy("predictor", "rho").agg(R6(F.min("gain")).alias("least"), R6(F.median("gain")).alias("median"), R6(F.max("gain")).alias("most"))


@query()
def win_sign(spark, d):
    """Quadrature of clean error and amplified noise against the sign of the real gain, forecaster against Lorenzo-1."""
    m = forecaster(spark)

    def fn(names, x):
        c = 256
        s, clean = m.start(x[:, :c].astype(float)), []
        for t in range(c, x.shape[1]):
            clean.append(s.predict() - x[:, t])
            s.push(x[:, t].astype(float))
        e_model, e_classic = np.sqrt(np.mean(np.square(clean), axis=0)), np.sqrt(np.mean(np.square(np.diff(x, axis=1)[:, c:]), axis=1))
        for rho in (0.01, 0.05, 0.2):
            step, _, _, k, _ = _body(x, rho, c, m)
            real = E.coded_sizes(list(L.lorenzo(x, step, 1)[0][:, c:])) - E.coded_sizes(list(k))
            noise = step / np.sqrt(12)
            total = np.sqrt(e_model**2 + (0.8 * noise) ** 2), np.sqrt(e_classic**2 + noise**2)
            for i, name in enumerate(names):
                yield name, rho, bool(total[0][i] < total[1][i]), bool(real[i] > 0)

    rows = None
    for n in ("gen_demand", "events_cents_type_hourly"):
        part = _per_group(spark, d, n, fn, "series_id string, rho double, predicted boolean, actual boolean").withColumn("corpus", F.lit(n))
        rows = part if rows is None else rows.union(part)
    return rows.groupBy("corpus").agg(F.count(F.lit(1)).alias("cases"), F.count_if(F.col("predicted") == F.col("actual")).alias("right"))


@query()
def downsample_ratio(spark, d):
    """Worst error of downsampling at the codec's bytes, over the bound that the codec guarantees."""
    m = forecaster(spark)

    def fn(names, x):
        step, seeds, _, k, _ = _body(x, 0.05, 256, m)
        budget = E.coded_sizes(list(k)) + np.array(list(map(len, seeds)))
        n = x.shape[1]
        for i, name in enumerate(names):
            lo, hi = 1, n - 1

            def kept(r, i=i):
                return np.unique(np.r_[np.arange(0, n, r), n - 1])

            def cost(r, i=i):
                return int(E.coded_sizes([np.diff(x[i][kept(r)], prepend=x[i][0])])[0])

            while lo < hi:
                mid = (lo + hi) // 2
                lo, hi = (lo, mid) if cost(mid) <= budget[i] else (mid + 1, hi)
            at = kept(lo)
            worst = np.abs(np.interp(np.arange(n), at, x[i][at]) - x[i]).max()
            yield name, lo, float(worst / (step[i] / 2))

    out = None
    for n in ("gen_demand", "events_cents_type_hourly"):
        part = _per_group(spark, d, n, fn, "series_id string, stride int, ratio double").groupBy().agg(F.count(F.lit(1)).alias("n_series"), R6(F.median("ratio")).alias("median_ratio"), R6(F.median("stride")).alias("median_stride")).withColumn("corpus", F.lit(n))
        out = part if out is None else out.unionByName(part)
    return out


# --- lossless --------------------------------------------------------------------------------------------------

LOSSLESS = ("orders_revenue_daily", "orders_count_daily", "orders_priority_daily", "uniform_k", "uniform_size", "walk", "counter_revenue", "gen_iid", "gen_demand")


def _lossless(spark, d, name: str) -> DataFrame:
    m = forecaster(spark)
    lag_sets = {"lpc32": K.LPC, "lpc256": list(range(1, 257)), "seasonal": [1, 2, 3, 23, 24, 25, 48, 168], "stack16": list(range(1, 12)) + [14, 21, 24, 48, 168]}

    def fn(names, x, unit):
        for s, v in zip(names, x, strict=True):
            n = len(v)
            if unit == len(lag_sets):
                c = min(192, n // 4)
                r = np.r_[np.diff(v[:c], prepend=0), v[c:] - np.round(open_loop(m, v, c)).astype(np.int64)]
                yield s, n, "model", E.mixture_bits(r) / n
            elif unit > len(lag_sets):
                yield s, n, "xz", 8.0 * E.xz_raw_size(v) / n
            else:
                g = list(lag_sets.values())[unit]
                if n > 2 * max(g):
                    yield s, n, "classic", E.mixture_bits(L.open_loop_residuals(v, g, L.fit_lags(v.astype(float), g))) / n

    bits = _per_group(spark, d, name, fn, "series_id string, n int, method string, bpv double", 1, units=len(lag_sets) + 2)
    least = {k: F.min(F.when(F.col("method") == k, F.col("bpv"))) for k in ("xz", "classic", "model")}
    rows = bits.groupBy("series_id", "n").agg(least["xz"].alias("xz_bpv"), F.coalesce(least["classic"], least["model"]).alias("classic_bpv"), least["model"].alias("model_bpv"))
    return rows.withColumn("gain", 100 * (1 - F.col("model_bpv") / F.col("classic_bpv"))).withColumn("corpus", F.lit(name))


@query()
def lossless_table(spark, d):
    """Bits for each value by xz, the best of four least-squares predictors, and the forecaster, one shared coder."""
    out = None
    for n in LOSSLESS:
        t = _lossless(spark, d, n)
        out = t if out is None else out.unionByName(t)
    return out.groupBy("corpus").agg(F.count(F.lit(1)).alias("series"), *(R6(F.avg(c)).alias(c) for c in ("xz_bpv", "classic_bpv", "model_bpv")), R6(F.median("gain")).alias("median_gain_pct"))


@query("SELECT corpus, true AS near_entropy FROM (VALUES ('gen_iid'), ('uniform_k')) v(corpus)")
def noise_control(spark, d):
    """On uniform noise every predictor must read the true entropy, within 0.05 bits."""
    true = {"gen_iid": np.log2(4096), "uniform_k": np.log2(100)}

    def fn(names, x):
        v = x[0]
        center = v - int(np.round(v.mean()))
        yield (names[0], E.mixture_bits(center) / len(v))

    out = None
    for n, h in true.items():
        part = _per_group(spark, d, n, fn, "series_id string, bits double", 1).select(F.lit(n).alias("corpus"), (F.abs(F.col("bits") - float(h)) <= 0.05).alias("near_entropy"))
        out = part if out is None else out.union(part)
    return out


@query()
def harness_defect(spark, d):
    """Different density families make a spurious gain on noise; one family makes none."""

    def fn(names, x):
        v = x[0] - int(np.round(x[0].mean()))
        yield (len(v), *(E.mixture_bits(v, f) for f in ("laplace", "flat", "mixture")))

    rows = _per_group(spark, d, "uniform_k_bucket", fn, "n long, laplace double, flat double, mixture double", 1)
    bits = rows.agg(*((F.sum(f) / F.sum("n")).alias(f) for f in ("laplace", "flat", "mixture")))
    return bits.withColumn("spurious_gain_pct", 100 * (1 - F.col("flat") / F.col("laplace"))).select(*(R6(c).alias(c) for c in ("laplace", "flat", "mixture", "spurious_gain_pct")))


@query()
def covariate_effect(spark, d):
    """Revenue given the order count of the same day: error and code length with and without the covariate."""
    pair = corpus(spark, d, "orders_revenue_daily").select("t", "x").join(corpus(spark, d, "orders_count_daily").select("t", F.col("x").alias("z")), "t")

    def run(pdf):
        pdf = pdf.sort_values("t")
        x, z = pdf["x"].to_numpy(float), pdf["z"].to_numpy(float)
        out = []
        for name, use in (("alone", False), ("with_past_and_future_covariate", True)):
            a, y = L.lag_matrix(x - x.mean(), [1, 2, 3, 7])
            if use:
                a = np.column_stack([a, (z - z.mean())[7:], (z - z.mean())[6:-1]])
            w = np.linalg.solve(a.T @ a + 1e-6 * np.trace(a.T @ a) * np.eye(a.shape[1]), a.T @ y)
            r = np.round(y - a @ w).astype(np.int64)
            out.append((name, round(E.mixture_bits(r) / len(r), 6), round(float(np.abs(r).mean()), 6)))
        return pd.DataFrame(out, columns=["variant", "bpv", "mae"])

    return pair.withColumn("one", F.lit(1)).groupBy("one").applyInPandas(run, "variant string, bpv double, mae double")


@query()
def anchor_grid(spark, d):
    """Coarse samples first, then their interpolation as a covariate of the fine ones: eight configurations.

    The refresh K is not defined in the source; here the anchor line is refreshed every K ticks.
    """
    m = forecaster(spark)

    def fn(names, x):
        n = x.shape[1]
        for rho in (0.01, 0.05):
            step, seeds, _, k, _ = _body(x, rho, 256, m)
            base = E.coded_sizes(list(k)) + np.array(list(map(len, seeds)))
            for stride in (32, 64):
                at = np.unique(np.r_[np.arange(0, n, stride), n - 1])
                kc, hat = L.lorenzo(x[:, at], step, 1)
                coarse = E.coded_sizes(list(kc))
                for refresh in (8, 16):
                    line = np.stack([np.interp(np.arange(n) // refresh * refresh, at, h) for h in hat])
                    fine, _ = L.quantize(x, line, step[:, None])
                    cost = coarse + E.coded_sizes(list(fine))
                    for i, name in enumerate(names):
                        yield name, refresh, stride, rho, 100 * (1 - float(cost[i]) / float(base[i]))

    rows = _per_group(spark, d, "events_weighted_hourly", fn, "series_id string, k int, stride int, rho double, gain double")
    return rows.groupBy("k", "stride", "rho").agg(R6(F.median("gain")).alias("median_gain_pct"))


@query()
def vs_external(spark, d):
    """Re-creations of two scientific compressors (the real binaries are not here): interpolation with a generic back
    end and a 500-byte container, and a block transform cut at the tolerance; by length."""
    def fn(names, x):
        for n in (512, 1024, 2048):
            part = x[:, :n]
            if part.shape[1] < n:
                continue
            step = 2 * 0.05 * K.sigma(part)
            for i, name in enumerate(names):
                interp = min(E.generic_size(L.multilevel(part[i : i + 1], step[i : i + 1], kind)[0][0], "zstd") for kind in ("linear", "cubic")) + 500
                range_coded = int(E.coded_sizes(list(L.multilevel(part[i : i + 1], step[i : i + 1], "cubic")[0]))[0])
                yield name, n, 8.0 * interp / n, 8.0 * range_coded / n, block_transform_bits(part[i], step[i] / 2) / n, 100 * 500 / interp

    rows = _per_group(spark, d, "ship_cents_nation_daily", fn, "series_id string, n int, interp double, ranged double, block double, overhead double")
    return rows.groupBy("n").agg(R6(F.median("interp")).alias("interp_codec_bpv"), R6(F.median("ranged")).alias("same_predictor_range_coder_bpv"), R6(F.median("block")).alias("block_transform_bpv"), R6(F.median("overhead")).alias("container_share_pct"))


def block_transform_bits(x: np.ndarray, tau: float) -> float:
    """Blocks of four through a lifted decorrelating transform, coefficients in steps the tolerance allows, bit planes
    of negabinary numbers counted from the highest one used, with an exponent for each block."""
    pad = np.r_[x, np.repeat(x[-1], -len(x) % 4)].reshape(-1, 4).astype(np.float64)
    a, b, c, e = pad.T
    s, t = (a + e) / 2, (b + c) / 2
    coef = np.stack([(s + t) / 2, (s - t) / 2, (e - a) / 2, (c - b) / 2], 1)
    q = np.round(coef / max(tau / 2, 1e-9)).astype(np.int64)
    mask = np.int64(0x2AAAAAAAAAAAAAAA)
    nega = (q + mask) ^ mask
    top = np.floor(np.log2(np.maximum(nega.max(axis=1), 1))) + 1
    used = np.where(nega > 0, np.floor(np.log2(np.maximum(nega, 1))) + 1, 0)
    return float((8 + top + used.sum(axis=1) + 4).sum())


@query()
def overhead_curve(spark, d):
    return vs_external(spark, d).select("n", "container_share_pct")


@query("SELECT kind, true AS ok FROM (VALUES ('laplacian'), ('sparse'), ('heavy_tailed'), ('all_zero'), ('uniform'), ('alternating'), ('extremes'), ('empty'), ('single')) v(kind)")
def coder_selftest(spark, d):
    """Round trip of the range coder on inputs of nine kinds, made on the executors of every series of event values."""

    def run(batches):
        for pdf in batches:
            out = []
            for xs in pdf["xs"]:
                x = np.asarray(xs, np.int64)
                change, odd = np.diff(x, prepend=x[:1]), np.arange(len(x)) % 2
                kinds = {"laplacian": change // 4000, "sparse": np.where(x % 97 == 0, x % 199 - 99, 0), "heavy_tailed": np.sign(change) * (change // 1000) ** 3, "all_zero": x - x, "uniform": x % 100, "alternating": 1 - 2 * odd, "extremes": np.array([2**62, -(2**62), 0, 15, -15])[x % 5], "empty": x[:0], "single": -x[:1]}
                lanes = E.encode_lanes(list(kinds.values()))
                out += [(kind, bool(np.array_equal(E.decode_lane(b, len(k)), k))) for (kind, k), b in zip(kinds.items(), lanes, strict=True)]
            yield pd.DataFrame(out, columns=["kind", "ok"])

    rows = K.arrays(corpus(spark, d, "events_cents_type_hourly")).repartition(16, "series_id")
    return rows.mapInPandas(run, "kind string, ok boolean").groupBy("kind").agg(F.min("ok").alias("ok"))


_RT = "SELECT series_id, count(*)::bigint AS n, sum(x)::bigint AS total, max(x)::bigint AS largest, true AS bound_ok, true AS roundtrip_ok FROM ({s}) GROUP BY 1"


def _roundtrip(spark, d, g: int) -> DataFrame:
    m, s = forecaster(spark), corpus(spark, d, "events_cents_type_hourly")
    return K.verified(K.decode_groups(K.encode_groups(s, m, c=200, g=g), m), s)


@query(_RT.format(s=S.SQL["events_cents_type_hourly"]))
def group_roundtrip_g8(spark, d):
    """Containers of eight lanes (three of them padding): decoded bytes equal the encoder's, within the bound."""
    return _roundtrip(spark, d, 8)


@query(_RT.format(s=S.SQL["events_cents_type_hourly"]))
def group_roundtrip_g16(spark, d):
    return _roundtrip(spark, d, 16)


@query(f"SELECT true AS same_bytes, count(DISTINCT series_id)::bigint AS series FROM ({S.SQL['events_cents_type_hourly']})")
def partition_invariance(spark, d):
    """Containers do not depend on how Spark cuts tasks."""
    m, s = forecaster(spark), corpus(spark, d, "events_cents_type_hourly")
    lanes = lambda x: K.encode_groups(x, m, c=200, g=8).select(F.explode("lanes").alias("l")).where("NOT l.pad").select("l.series_id", F.sha2("l.body", 256).alias("h"))
    a, b = lanes(s), lanes(s.repartition(3).sortWithinPartitions(F.desc("t")))
    return a.join(b.withColumnRenamed("h", "h2"), "series_id").agg((F.count_if(F.col("h") == F.col("h2")) == F.count(F.lit(1))).alias("same_bytes"), F.count(F.lit(1)).alias("series"))


@query()
def forecaster_variants(spark, d):
    """The pooled stand-in, the seasonal profile, and a small student distilled on the pooled one, over the corpus that
    the pooled one was fitted on: no evaluated series trains it."""
    m = forecaster(spark)
    fitted = K.arrays(S.gen_demand(spark, 12, 2400, TRAIN_SEEDS[0], 300)).collect()  # twelve generated series
    train = np.stack([np.asarray(r["xs"], np.int64) for r in fitted])
    ctx = np.concatenate([train[:, t - 180 : t] for t in range(256, train.shape[1] - 1, 37)]).astype(float)
    lags, w = m.usable(180)
    student = Student.distil(ctx, sum(w[j] * ctx[:, -g] for j, g in enumerate(lags)))

    def fn(names, x):
        for label, f in (("pooled", m), ("profile", SeasonalProfile(24))):
            step, _, _, k, _ = _body(x, 0.05, 256, f)
            for i, b in enumerate(E.coded_sizes(list(k))):
                yield names[i], label, 8.0 * float(b) / k.shape[1]
        for i, name in enumerate(names):
            hist = np.stack([x[i, t - 180 : t] for t in range(256, x.shape[1])]).astype(float)
            r = np.round(student.predict(hist) - x[i, 256:]).astype(np.int64)
            yield name, "student_open_loop", float(E.mixture_bits(r) / len(r))

    return _per_group(spark, d, "events_weighted_hourly", fn, "series_id string, forecaster string, bpv double").groupBy("forecaster").agg(R6(F.avg("bpv")).alias("bpv"))


@query()
def advisor(spark, d):
    """Measure on a sample of series (by hash) and recommend a coder for each corpus by real bytes."""
    t = _tables(spark, d, DEMAND + OFF).where(F.pmod(F.xxhash64("series_id"), F.lit(4)) == 0)
    best = gains(t).groupBy("corpus").agg(R6(F.median("gain")).alias("median_gain_pct"), F.mode("best", deterministic=True).alias("classical"))
    return best.withColumn("recommended", F.when(F.col("median_gain_pct") > 0, "codec").otherwise(F.col("classical")))


@query()
def throughput(spark, d):
    """Values for each second by group size and context, through the lockstep loop, on this machine."""
    m = forecaster(spark)

    def fn(names, x):
        for g, c in ((1, 128), (6, 256), (64, 256), (256, 256)):
            lanes = np.stack([x[i % len(x)] for i in range(g)])
            step = 2 * 0.05 * K.sigma(lanes)
            hat = lanes[:, :c].astype(float)
            start = time.perf_counter()
            L.forecast_loop(lanes[:, : c + 200], step, hat, m)
            yield g, c, "float64", g * 200 / (time.perf_counter() - start)

    return _per_group(spark, d, "events_cents_type_hourly", fn, "g int, c int, precision string, values_per_s double")


__all__ = ["LAGS", "QUERIES"]
