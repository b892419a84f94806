"""Methods and measures with exact SQL oracles: tolerances, lattice coding, interpolation, contexts, risks, curves.

Each entry is (Spark query, DuckDB SQL). Doubles are rounded to six decimals on both sides.
"""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import window as W

from boundspark.plans import lattice as P
from boundspark.plans import series as S

Query = Callable[[SparkSession, str], DataFrame]
QUERIES: dict[str, tuple[Query, str | None]] = {f"series_{n}": (f, S.SQL[n]) for n, f in S.CATALOG.items()}

CORPUS = "events_cents_type_hourly"
R6 = lambda c: F.round(c, 6)


def plain6(c: str):
    """Rounded, with no negative zero."""
    return F.when(F.round(c, 6) == 0, F.lit(0.0)).otherwise(F.round(c, 6)).alias(c)


_XHAT = "CASE WHEN round(xhat, 6) = 0 THEN 0.0::double ELSE round(xhat, 6) END AS xhat"


def _corpus(spark: SparkSession, d: str, name: str = CORPUS) -> DataFrame:
    return S.CATALOG[name](spark, d)


def _tol_sql(corpus: str = CORPUS, rhos: tuple[float, ...] = P.RHOS) -> str:
    """CTEs s (series), r (tolerances), m (moments) and tol (series_id, rho, n, tau, step, mean)."""
    values = ", ".join(f"({r}::double)" for r in rhos)
    return f"""s AS ({S.SQL[corpus]}), r(rho) AS (VALUES {values}),
        m AS (SELECT series_id, count(*)::bigint AS n, (count(*)::hugeint * sum(x::hugeint * x::hugeint)::hugeint - sum(x)::hugeint * sum(x)::hugeint)::double AS v, sum(abs(x))::double AS s_abs FROM s GROUP BY 1),
        tol AS (SELECT series_id, rho, n, rho * (sqrt(v) / n) AS tau, 2 * rho * (sqrt(v) / n) AS step, s_abs FROM m, r)"""


def tolerance_sigma(spark, d):
    t = P.by_sigma(_corpus(spark, d))
    return t.select("series_id", "rho", "n", R6("tau").alias("tau"), R6("step").alias("step"), R6("rel_err_pct").alias("rel_err_pct"), "sub_integer")


def tolerance_sample_sigma(spark, d):
    return P.by_sigma(_corpus(spark, d), ddof=1).select("series_id", "rho", "n", R6("tau").alias("tau"))


def tolerance_relative(spark, d):
    return P.relative(_corpus(spark, d), 2.0).select("series_id", "n", R6("tau").alias("tau"), R6("step").alias("step"))


def tolerance_absolute(spark, d):
    return P.absolute(_corpus(spark, d), 25.0).select("series_id", "n", "tau", "step", "sub_integer")


QUERIES |= {
    "tolerance_sigma": (tolerance_sigma, f"WITH {_tol_sql()} SELECT series_id, rho, n, round(tau, 6) AS tau, round(step, 6) AS step, round(CASE WHEN s_abs > 0 THEN 100 * tau * n / s_abs END, 6) AS rel_err_pct, tau < 0.5 AS sub_integer FROM tol"),
    "tolerance_sample_sigma": (tolerance_sample_sigma, f"WITH {_tol_sql()} SELECT series_id, rho, n, round(rho * (sqrt(v) / sqrt(n::double * greatest(n - 1, 1))), 6) AS tau FROM m, r"),
    "tolerance_relative": (tolerance_relative, f"WITH {_tol_sql()} SELECT series_id, n, round((2.0::double / 100.0::double) * s_abs / n, 6) AS tau, round(2 * ((2.0::double / 100.0::double) * s_abs / n), 6) AS step FROM m"),
    "tolerance_absolute": (tolerance_absolute, f"WITH {_tol_sql()} SELECT series_id, n, 25.0::double AS tau, 50.0::double AS step, false AS sub_integer FROM m"),
}


def _lattice(spark, d, **how) -> DataFrame:
    s = _corpus(spark, d)
    return P.encode(P.with_tolerance(s, P.by_sigma(s)), **how)


def _lattice_sql(diff: str) -> str:
    return f"""WITH {_tol_sql()},
        j AS (SELECT s.series_id, rho, t, x, tau, step, first_value(x) OVER w AS base FROM s JOIN tol USING (series_id) WINDOW w AS (PARTITION BY s.series_id, rho ORDER BY t)),
        q AS (SELECT *, (CASE WHEN step = 0 THEN 0 ELSE floor((x - base) / step + 0.5) END)::bigint AS q FROM j),
        k AS (SELECT *, ({diff})::bigint AS k, base + q * step AS xhat FROM q WINDOW w AS (PARTITION BY series_id, rho ORDER BY t))"""


def _lag(n: int) -> str:
    return f"coalesce(lag(q, {n}) OVER w, 0)"


_DIFF = {1: f"q - {_lag(1)}", 2: f"q - 2 * {_lag(1)} + {_lag(2)}", 3: f"q - 3 * {_lag(1)} + 3 * {_lag(2)} - {_lag(3)}", "season": f"q - {_lag(24)}"}


def _lattice_query(**how) -> Query:
    return lambda spark, d: _lattice(spark, d, **how).select("series_id", "rho", "t", "k", plain6("xhat"))


for _name, _how, _key in (("lattice_l1", {"order": 1}, 1), ("lattice_l2", {"order": 2}, 2), ("lattice_l3", {"order": 3}, 3), ("lattice_seasonal", {"season": 24}, "season")):
    QUERIES[_name] = (_lattice_query(**_how), _lattice_sql(_DIFF[_key]) + " SELECT series_id, rho, t, k, " + _XHAT + " FROM k")


def lattice_decode(spark, d):
    """Decoded from second-order indices; equals the encoder's reconstruction."""
    enc = _lattice(spark, d, order=2)
    return P.decode(enc, 2).select("series_id", "rho", "t", plain6("xhat"))


def lattice_bound(spark, d):
    enc = _lattice(spark, d, order=1)
    worst = F.max(F.abs(F.col("xhat") - F.col("x")) / F.col("tau"))
    return enc.groupBy("series_id", "rho").agg(F.count(F.lit(1)).alias("n"), (worst <= 1 + 1e-9).alias("bound_ok"))


def lattice_zero_share(spark, d):
    enc = _lattice(spark, d, order=1)
    return enc.groupBy("series_id", "rho").agg(R6(F.avg(F.when(F.col("k") == 0, 1.0).otherwise(0.0))).alias("zero_share"), F.sum(F.abs("k")).alias("k_abs"))


def lattice_l1_orders(spark, d):
    """The minimal slice: non-empty order days, one tolerance, first-order indices in total."""
    s = S.table(spark, d, "orders").groupBy(S.day("o_orderdate").alias("t")).agg(F.count(F.lit(1)).alias("x")).withColumn("series_id", F.lit("orders"))
    enc = P.encode(P.with_tolerance(s, P.by_sigma(s, (0.05,))), order=1)
    return enc.groupBy("series_id", "rho").agg(F.sum(F.abs("k")).alias("k_abs"), F.count_if(F.col("k") == 0).alias("zeros"), F.count(F.lit(1)).alias("n"))


_ORDERS = f"SELECT 'orders' AS series_id, {S._day_sql('o_orderdate')} AS t, count(*)::bigint AS x FROM orders GROUP BY 2"
QUERIES |= {
    "lattice_decode": (lattice_decode, _lattice_sql(_DIFF[2]) + " SELECT series_id, rho, t, " + _XHAT + " FROM k"),
    "lattice_bound": (lattice_bound, f"WITH {_tol_sql()} SELECT series_id, rho, n, true AS bound_ok FROM tol"),
    "lattice_zero_share": (lattice_zero_share, _lattice_sql(_DIFF[1]) + " SELECT series_id, rho, round(avg(CASE WHEN k = 0 THEN 1.0::double ELSE 0.0::double END), 6) AS zero_share, sum(abs(k))::bigint AS k_abs FROM k GROUP BY 1, 2"),
    "lattice_l1_orders": (lattice_l1_orders, _lattice_sql(_DIFF[1]).replace(S.SQL[CORPUS], _ORDERS).replace("(0.01::double), (0.05::double), (0.2::double)", "(0.05::double)") + " SELECT series_id, rho, sum(abs(k))::bigint AS k_abs, count(*) FILTER (WHERE k = 0) AS zeros, count(*) AS n FROM k GROUP BY 1, 2"),
}


def closed_loop_recursive(spark, d):
    """Daily orders by the lattice; the oracle runs the loop tick by tick."""
    s = S.orders_count_daily(spark, d)
    enc = P.encode(P.with_tolerance(s, P.by_sigma(s, (0.2,))), order=2)
    return enc.select("t", "k", plain6("xhat"))


_LOOP_SQL = f"""WITH RECURSIVE {_tol_sql('orders_count_daily', (0.2,))},
    z AS (SELECT t, x, step FROM s, tol),
    l AS (SELECT t, x, step, x::double AS h1, x::double AS h2, 0::bigint AS k FROM z WHERE t = 0
      UNION ALL SELECT z.t, z.x, z.step, p + floor((z.x - p) / z.step + 0.5) * z.step, h1, floor((z.x - p) / z.step + 0.5)::bigint
      FROM (SELECT l.t AS lt, h1, CASE WHEN l.t = 0 THEN h1 ELSE 2 * h1 - h2 END AS p FROM l) y JOIN z ON z.t = y.lt + 1)
    SELECT t, k::bigint AS k, CASE WHEN round(h1, 6) = 0 THEN 0.0::double ELSE round(h1, 6) END AS xhat FROM l"""


def _multilevel(kind: str) -> Query:
    def run(spark, d):
        s = _corpus(spark, d)
        out = P.multilevel_blocks(P.with_tolerance(s, P.by_sigma(s)), kind)
        return out.select("series_id", "rho", "t", "k", plain6("xhat"))

    return run


def _multilevel_sql(kind: str, size: int = 64) -> str:
    """Unrolled: each stride is a CTE that fills its targets by joins on the block's known ticks."""
    parts = [f"WITH {_tol_sql()}", f"a AS (SELECT s.series_id, rho, step, t // {size} AS b, t % {size} AS i, x FROM s JOIN tol USING (series_id))", "h0 AS (SELECT series_id, rho, b, i, 0::bigint AS k, x::double AS h FROM a WHERE i = 0)"]
    level, stride = 0, size // 2
    while stride >= 1:
        on = lambda z, o: f"LEFT JOIN h{level} {z} ON {z}.series_id = a.series_id AND {z}.rho = a.rho AND {z}.b = a.b AND {z}.i = a.i + ({o})"
        lin = "CASE WHEN r1.h IS NOT NULL THEN 0.5::double * l1.h + 0.5::double * r1.h ELSE l1.h END"
        p, joins = lin, f"{on('l1', -stride)} {on('r1', stride)}"
        if kind == "cubic":
            p = f"CASE WHEN l3.h IS NOT NULL AND r3.h IS NOT NULL THEN (-1 * l3.h + 9 * l1.h + 9 * r1.h - r3.h) / 16 ELSE {lin} END"
            joins += f" {on('l3', -3 * stride)} {on('r3', 3 * stride)}"
        parts.append(f"p{level} AS (SELECT a.series_id, a.rho, a.b, a.i, a.x, a.step, {p} AS p FROM a {joins} WHERE a.i % {2 * stride} = {stride})")
        k = "(CASE WHEN step = 0 THEN 0 ELSE floor((x - p) / step + 0.5) END)::bigint"
        parts.append(f"h{level + 1} AS (SELECT * FROM h{level} UNION ALL SELECT series_id, rho, b, i, {k} AS k, p + {k} * step AS h FROM p{level})")
        level, stride = level + 1, stride // 2
    return ", ".join(parts) + f" SELECT series_id, rho, (b * {size} + i)::bigint AS t, k, CASE WHEN round(h, 6) = 0 THEN 0.0::double ELSE round(h, 6) END AS xhat FROM h{level}"


QUERIES |= {"closed_loop_recursive": (closed_loop_recursive, _LOOP_SQL), "multilevel_linear_64": (_multilevel("linear"), _multilevel_sql("linear")), "multilevel_cubic_64": (_multilevel("cubic"), _multilevel_sql("cubic"))}


def context_counts(spark, d):
    """Samples, zeros and sign bits by coding context of 2|k[-1]| + |k[-2]|."""
    w = W.Window.partitionBy("series_id", "rho").orderBy("t")
    mag = 2 * F.coalesce(F.abs(F.lag("k", 1).over(w)), F.lit(0)) + F.coalesce(F.abs(F.lag("k", 2).over(w)), F.lit(0))
    ctx = sum((F.when(mag >= e, 1).otherwise(0) for e in (1, 3, 6, 12, 24)), F.lit(0))
    return _lattice(spark, d, order=1).withColumn("ctx", ctx.cast("long")).groupBy("rho", "ctx").agg(F.count(F.lit(1)).alias("n"), F.count_if(F.col("k") == 0).alias("zeros"), F.count_if(F.col("k") < 0).alias("negative"))


def binarize_counts(spark, d):
    """Bins by kind: zero flags, signs, unary bins up to the cap of 14, and Exp-Golomb tail bins."""
    m = F.abs("k")
    unary = F.when(m == 0, 0).when(m > 14, 14).otherwise(m)
    tail = F.when(m > 14, 2 * F.floor(F.log2((m - 14).cast("double")) + 1e-12) + 1).otherwise(0)
    out = _lattice(spark, d, order=1).select("rho", F.when(m > 0, 1).otherwise(0).alias("s"), unary.alias("u"), tail.alias("g"))
    return out.groupBy("rho").agg(F.count(F.lit(1)).alias("zero_flags"), F.sum("s").cast("long").alias("signs"), F.sum("u").cast("long").alias("unary_bins"), F.sum("g").cast("long").alias("tail_bins"))


def empirical_entropy(spark, d):
    c = _lattice(spark, d, order=1).groupBy("series_id", "rho", "k").agg(F.count(F.lit(1)).alias("c"))
    n = F.sum("c").over(W.Window.partitionBy("series_id", "rho"))
    p = c.withColumn("p", F.col("c") / n)
    return p.groupBy("series_id", "rho").agg(F.round(-F.sum(F.col("p") * F.log2("p")), 4).alias("bits"))


def zigzag_pack(spark, d):
    k = F.col("k")
    return _lattice(spark, d, order=1).select("series_id", "rho", "t", F.when(k >= 0, 2 * k).otherwise(-2 * k - 1).alias("z"))


_CTX = "(CASE WHEN g >= 1 THEN 1 ELSE 0 END + CASE WHEN g >= 3 THEN 1 ELSE 0 END + CASE WHEN g >= 6 THEN 1 ELSE 0 END + CASE WHEN g >= 12 THEN 1 ELSE 0 END + CASE WHEN g >= 24 THEN 1 ELSE 0 END)::bigint"
QUERIES |= {
    "context_counts": (context_counts, _lattice_sql(_DIFF[1]) + f", c AS (SELECT rho, k, 2 * coalesce(abs(lag(k, 1) OVER w), 0) + coalesce(abs(lag(k, 2) OVER w), 0) AS g FROM k WINDOW w AS (PARTITION BY series_id, rho ORDER BY t)) SELECT rho, {_CTX} AS ctx, count(*) AS n, count(*) FILTER (WHERE k = 0) AS zeros, count(*) FILTER (WHERE k < 0) AS negative FROM c GROUP BY 1, 2"),
    "binarize_counts": (binarize_counts, _lattice_sql(_DIFF[1]) + " SELECT rho, count(*) AS zero_flags, count(*) FILTER (WHERE k <> 0) AS signs, sum(least(abs(k), 14))::bigint AS unary_bins, sum(CASE WHEN abs(k) > 14 THEN 2 * floor(log2(abs(k) - 14) + 1e-12) + 1 ELSE 0 END)::bigint AS tail_bins FROM k GROUP BY 1"),
    "empirical_entropy": (empirical_entropy, _lattice_sql(_DIFF[1]) + ", c AS (SELECT series_id, rho, k, count(*) AS c FROM k GROUP BY 1, 2, 3), p AS (SELECT *, c / sum(c) OVER (PARTITION BY series_id, rho)::double AS p FROM c) SELECT series_id, rho, round(-sum(p * log2(p)), 4) AS bits FROM p GROUP BY 1, 2"),
    "zigzag_pack": (zigzag_pack, _lattice_sql(_DIFF[1]) + " SELECT series_id, rho, t, CASE WHEN k >= 0 THEN 2 * k ELSE -2 * k - 1 END AS z FROM k"),
}

_OPEN = {1: ((1, 1),), 2: ((1, 2), (2, -1)), 3: ((1, 3), (2, -3), (3, 1))}


def mae_lorenzo(spark, d):
    """Clean error of the three orders on the true history."""
    w = W.Window.partitionBy("series_id").orderBy("t")
    err = lambda o: F.abs(F.col("x") - sum((c * F.lag("x", g).over(w) for g, c in _OPEN[o]), F.lit(0)))
    e = _corpus(spark, d).select("series_id", *(err(o).alias(f"e{o}") for o in _OPEN))
    return e.groupBy("series_id").agg(*(R6(F.avg(f"e{o}")).alias(f"mae{o}") for o in _OPEN))


def _pred_sql(o: int, c: str = "x") -> str:
    return " + ".join(f"({w}) * lag({c}, {g}) OVER w" for g, w in _OPEN[o])


def noise_gain(spark, d):
    """Spread of predictions when history carries uniform noise, by that of the noise: 1, sqrt 5, sqrt 19."""
    e = S.uniform_int(F.concat(F.col("series_id"), F.lit("/"), F.col("t").cast("string")), 2001) - 1000
    w = W.Window.partitionBy("series_id").orderBy("t")
    n = _corpus(spark, d).select("series_id", "t", e.alias("e"))
    diff = {o: sum((c * F.lag("e", g).over(w) for g, c in _OPEN[o]), F.lit(0)) for o in _OPEN}
    p = n.select("e", *(diff[o].alias(f"d{o}") for o in _OPEN))
    return p.agg(*(F.round(F.stddev_pop(f"d{o}") / F.stddev_pop("e"), 4).alias(f"gain{o}") for o in _OPEN), *(F.round(F.sqrt(F.lit(float(sum(c * c for _, c in _OPEN[o])))), 4).alias(f"analytic{o}") for o in _OPEN))


_NOISE = S.UNIFORM_SQL.format(key="series_id || '/' || t", bound=2001)
QUERIES |= {
    "mae_lorenzo": (mae_lorenzo, f"WITH s AS ({S.SQL[CORPUS]}), e AS (SELECT series_id, {', '.join(f'abs(x - ({_pred_sql(o)})) AS e{o}' for o in _OPEN)} FROM s WINDOW w AS (PARTITION BY series_id ORDER BY t)) SELECT series_id, {', '.join(f'round(avg(e{o}), 6) AS mae{o}' for o in _OPEN)} FROM e GROUP BY 1"),
    "noise_gain": (noise_gain, f"WITH s AS ({S.SQL[CORPUS]}), n AS (SELECT series_id, t, {_NOISE} - 1000 AS e FROM s), p AS (SELECT e, {', '.join(f'{_pred_sql(o, chr(101))} AS d{o}' for o in _OPEN)} FROM n WINDOW w AS (PARTITION BY series_id ORDER BY t)) SELECT {', '.join(f'round(stddev_pop(d{o}) / stddev_pop(e), 4) AS gain{o}' for o in _OPEN)}, {', '.join(f'round(sqrt({sum(c * c for _, c in _OPEN[o])}.0::double), 4) AS analytic{o}' for o in _OPEN)} FROM p"),
}


def win_sign_model(spark, d):
    """Total error as clean error and amplified quantisation noise in quadrature; which of orders 1 and 2 should win."""
    s = _corpus(spark, d)
    w = W.Window.partitionBy("series_id").orderBy("t")
    e = lambda o: F.pow(F.col("x") - sum((c * F.lag("x", g).over(w) for g, c in _OPEN[o]), F.lit(0)), F.lit(2.0))
    clean = s.select("series_id", e(1).alias("c1"), e(2).alias("c2")).groupBy("series_id").agg(F.avg("c1").alias("c1"), F.avg("c2").alias("c2"))
    noise = F.col("step") * F.col("step") / 12
    j = clean.join(P.by_sigma(s).select("series_id", "rho", "step"), "series_id")
    return j.select("series_id", "rho", F.round(F.sqrt(F.col("c1") + 1 * noise), 4).alias("total1"), F.round(F.sqrt(F.col("c2") + 5 * noise), 4).alias("total2"), (F.col("c1") + 1 * noise < F.col("c2") + 5 * noise).alias("order1_wins"))


QUERIES["win_sign_model"] = (win_sign_model, f"WITH {_tol_sql()}, e AS (SELECT series_id, pow(x - ({_pred_sql(1)}), 2.0) AS c1, pow(x - ({_pred_sql(2)}), 2.0) AS c2 FROM s WINDOW w AS (PARTITION BY series_id ORDER BY t)), c AS (SELECT series_id, avg(c1) AS c1, avg(c2) AS c2 FROM e GROUP BY 1) SELECT series_id, rho, round(sqrt(c1 + 1 * (step * step / 12)), 4) AS total1, round(sqrt(c2 + 5 * (step * step / 12)), 4) AS total2, c1 + 1 * (step * step / 12) < c2 + 5 * (step * step / 12) AS order1_wins FROM c JOIN tol USING (series_id)")


def log2_law(spark, d):
    """Bits saved by an accuracy ratio, and the ratio that halves a budget of bits."""
    r = spark.range(1, 21).select((1 + F.col("id") / 10.0).alias("ratio"))
    return r.select(R6("ratio").alias("ratio"), R6(F.log2("ratio")).alias("bits"), R6(100 * F.log2("ratio") / 20).alias("pct_of_20"), R6(F.pow(F.lit(2.0), F.lit(10.0))).alias("factor_to_halve_20"))


def flip_risk(spark, d):
    """Chance that drift moves an index: drift / step for each sample, expected time, and failure within n samples."""
    t = P.by_sigma(_corpus(spark, d)).withColumn("drift", F.explode(F.array(F.lit(7.8e-3), F.lit(3.9e-3), F.lit(2.0e-3))))
    p = F.col("drift") / F.col("step")
    return t.select("series_id", "rho", "drift", F.round(p, 9).alias("p"), F.round(1 / p, 3).alias("mean_samples"), R6(1 - F.exp(-4300 * p)).alias("p_fail_short"), R6(1 - F.exp(-43800 * p)).alias("p_fail_long"))


def snap_flip(spark, d):
    """Snapping predictions to a grid moves the flip risk to the grid's own edges; it does not remove it."""
    s = _corpus(spark, d)
    w = W.Window.partitionBy("series_id").orderBy("t")
    p = s.select("x", (F.lag("x", 1).over(w) + F.lag("x", 2).over(w)).alias("p2"), F.col("t")).where("p2 IS NOT NULL").select("x", (F.col("p2") / 2.0).alias("p"))
    g, e, step = 16.0, 0.51, 40.0
    snap = lambda v: F.floor(v / g + 0.5) * g
    idx = lambda v: F.floor((F.col("x") - v) / step + 0.5)
    q = p.select((idx(F.col("p")) != idx(F.col("p") + e)).alias("raw"), (idx(snap(F.col("p"))) != idx(snap(F.col("p") + e))).alias("snapped"))
    return q.agg(F.count_if("raw").alias("raw_flips"), F.count_if("snapped").alias("snapped_flips"), F.count(F.lit(1)).alias("n"))


_IDX = "floor((x - ({v})) / 40.0::double + 0.5)"
_SNAP = "(floor(({v}) / 16.0::double + 0.5) * 16.0::double)"
QUERIES |= {
    "log2_law": (log2_law, "SELECT round(1 + i / 10.0::double, 6) AS ratio, round(log2(1 + i / 10.0::double), 6) AS bits, round(100 * log2(1 + i / 10.0::double) / 20, 6) AS pct_of_20, 1024.0::double AS factor_to_halve_20 FROM range(1, 21) t(i)"),
    "flip_risk": (flip_risk, f"WITH {_tol_sql()}, dr(drift) AS (VALUES (7.8e-3::double), (3.9e-3::double), (2.0e-3::double)) SELECT series_id, rho, drift, round(drift / step, 9) AS p, round(1 / (drift / step), 3) AS mean_samples, round(1 - exp(-4300 * (drift / step)), 6) AS p_fail_short, round(1 - exp(-43800 * (drift / step)), 6) AS p_fail_long FROM tol, dr"),
    "snap_flip": (snap_flip, f"WITH s AS ({S.SQL[CORPUS]}), p AS (SELECT x, (lag(x, 1) OVER w + lag(x, 2) OVER w) / 2.0::double AS p FROM s WINDOW w AS (PARTITION BY series_id ORDER BY t)) SELECT count(*) FILTER (WHERE {_IDX.format(v='p')} <> {_IDX.format(v='p + 0.51::double')}) AS raw_flips, count(*) FILTER (WHERE {_IDX.format(v=_SNAP.format(v='p'))} <> {_IDX.format(v=_SNAP.format(v='p + 0.51::double'))}) AS snapped_flips, count(*) AS n FROM p WHERE p IS NOT NULL"),
}


def length_curve(spark, d):
    """Rate at a length: body for all but the seed, seed for its own samples, header once; best context of five."""
    # Published body and seed rates by context, as context, body bits, seed bits.
    rates = spark.createDataFrame([(64, 2.183, 6.367), (128, 2.071, 4.582), (256, 2.017, 3.611), (512, 1.959, 3.214), (1024, 1.956, 2.980)], "c long, body double, seed double")
    r = rates.withColumn("n", F.explode(F.array(*(F.lit(n).cast("long") for n in (4300, 8760, 17520, 43800)))))
    rate = (F.col("body") * (F.col("n") - F.col("c")) + F.col("seed") * F.col("c") + 8 * 86) / F.col("n")
    out = r.withColumn("rate", rate)
    best = F.min_by("c", F.struct("rate", "c")).over(W.Window.partitionBy("n"))
    return out.select("n", "c", R6("rate").alias("rate"), R6(100 * (1 - F.col("rate") / 2.244)).alias("gain"), R6(100 * (1 - F.col("body") / 2.244)).alias("limit_gain"), (F.col("c") == best).alias("best"))


def seed_share(spark, d):
    """Container shares and overhead of a fixed header by length."""
    n = spark.range(9, 17).select(F.pow(F.lit(2.0), F.col("id")).cast("long").alias("n"))
    seed, body = F.lit(3.46 * 512), 1.906 * (F.col("n") - 512)
    total = seed + body + 86 * 8
    return n.select("n", R6(seed / total).alias("seed_share"), R6(body / total).alias("body_share"), R6(86 * 8 / total).alias("header_share"), R6(F.lit(500 * 8) / (F.lit(500 * 8) + body)).alias("container_500_share"))


_RATE = "((body * (n - c) + seed * c + 8 * 86) / n)"
QUERIES |= {
    "length_curve": (length_curve, f"WITH r(c, body, seed) AS (VALUES (64::bigint, 2.183::double, 6.367::double), (128, 2.071, 4.582), (256, 2.017, 3.611), (512, 1.959, 3.214), (1024, 1.956, 2.980)), l(n) AS (VALUES (4300::bigint), (8760), (17520), (43800)), z AS (SELECT n, c, body, {_RATE} AS rate FROM r, l) SELECT n, c, round(rate, 6) AS rate, round(100 * (1 - rate / 2.244::double), 6) AS gain, round(100 * (1 - body / 2.244::double), 6) AS limit_gain, c = first_value(c) OVER (PARTITION BY n ORDER BY rate, c) AS best FROM z"),
    "seed_share": (seed_share, "WITH z AS (SELECT (2 ** i)::bigint AS n, 3.46::double * 512 AS seed, 1.906::double * ((2 ** i)::bigint - 512) AS body FROM range(9, 17) t(i)), y AS (SELECT *, seed + body + 86 * 8 AS total FROM z) SELECT n, round(seed / total, 6) AS seed_share, round(body / total, 6) AS body_share, round(86 * 8 / total, 6) AS header_share, round((500 * 8) / ((500 * 8) + body), 6) AS container_500_share FROM y"),
}


def downsample_fixed(spark, d, stride: int = 8):
    """Every stride-th sample (and the last) kept, the rest linear between knots: worst and mean error by series."""
    s = _corpus(spark, d)
    w = W.Window.partitionBy("series_id")
    o = w.orderBy("t")
    last = F.max("t").over(w)
    knot = F.when((F.col("t") % stride == 0) | (F.col("t") == last), F.struct("t", "x"))
    b = s.withColumn("knot", knot)
    lo = F.last("knot", ignorenulls=True).over(o)
    hi = F.first("knot", ignorenulls=True).over(o.rowsBetween(0, W.Window.unboundedFollowing))
    b = b.select("series_id", "t", "x", lo.alias("lo"), hi.alias("hi"))
    est = F.when(F.col("hi.t") == F.col("lo.t"), F.col("lo.x").cast("double")).otherwise(F.col("lo.x") + (F.col("hi.x") - F.col("lo.x")) * (F.col("t") - F.col("lo.t")) / (F.col("hi.t") - F.col("lo.t")))
    e = b.select("series_id", F.abs(est - F.col("x")).alias("e"))
    return e.groupBy("series_id").agg(R6(F.max("e")).alias("worst"), R6(F.avg("e")).alias("mean_error"), F.count(F.lit(1)).alias("n"))


def downsample_mean(spark, d, stride: int = 8):
    s = _corpus(spark, d).withColumn("b", F.expr(f"t div {stride}"))
    m = s.groupBy("series_id", "b").agg(F.avg("x").alias("m"), F.min("x").alias("lo"), F.max("x").alias("hi"))
    j = s.join(m, ["series_id", "b"])
    return j.groupBy("series_id").agg(R6(F.max(F.abs(F.col("x") - F.col("m")))).alias("worst_of_mean"), F.max(F.col("hi") - F.col("lo")).alias("widest_band"))


def proxy_autocorr(spark, d):
    """Day-lag and lag-1 autocorrelation, and the ratio of mean changes at both lags."""
    w = W.Window.partitionBy("series_id").orderBy("t")
    s = S.events_weighted_hourly(spark, d).select("series_id", "x", F.lag("x", 1).over(w).alias("x1"), F.lag("x", 24).over(w).alias("x24"))
    return s.groupBy("series_id").agg(F.round(F.corr("x", "x1"), 4).alias("lag1"), F.round(F.corr("x", "x24"), 4).alias("lag24"), F.round(F.avg(F.abs(F.col("x") - F.col("x1"))) / F.avg(F.abs(F.col("x") - F.col("x24"))), 4).alias("local_over_long"))


def contamination_overlap(spark, d):
    """Keys that evaluation shares with the forecaster's training corpora: none."""
    train = S.gen_demand(spark, 12, 2400, "train-a").union(S.gen_demand(spark, 12, 2400, "train-b")).select("series_id", "t")
    return S.events_weighted_hourly(spark, d).select("series_id", "t").join(train, ["series_id", "t"], "left_semi").agg(F.count(F.lit(1)).alias("overlap_rows"))


def sentinel_screen(spark, d):
    """Three sentinels put into one series: robust flags by median and median deviation, and the harm to tau."""
    s = S.orders_priority_daily(spark, d)
    bad = (F.col("series_id") == "2-HIGH") & F.col("t").isin(100, 900, 1700)
    x = s.withColumn("x", F.when(bad, F.lit(-430000000)).otherwise(F.col("x")).cast("long"))
    med = x.groupBy("series_id").agg(F.median("x").alias("med"))
    dev = x.join(med, "series_id").withColumn("dev", F.abs(F.col("x") - F.col("med")))
    mad = dev.groupBy("series_id").agg(F.median("dev").alias("mad"))
    flag = dev.join(mad, "series_id").withColumn("bad", F.col("dev") > 1000 * F.greatest("mad", F.lit(1.0)))
    return flag.groupBy("series_id").agg(F.count_if("bad").alias("flagged"), F.max("bad").alias("drop_series"), F.count(F.lit(1)).alias("n"))


_DS = f"WITH s AS ({S.SQL[CORPUS]}), l AS (SELECT *, max(t) OVER (PARTITION BY series_id) AS last FROM s), k AS (SELECT series_id, t, x, lead(t) OVER w AS t2, lead(x) OVER w AS x2 FROM l WHERE t % 8 = 0 OR t = last WINDOW w AS (PARTITION BY series_id ORDER BY t)), e AS (SELECT l.series_id, abs(CASE WHEN l.t = k.t THEN k.x::double ELSE k.x + (k.x2 - k.x) * (l.t - k.t) / (k.t2 - k.t)::double END - l.x) AS e FROM l ASOF JOIN k ON l.series_id = k.series_id AND l.t >= k.t)"
QUERIES |= {
    "downsample_fixed": (downsample_fixed, _DS + " SELECT series_id, round(max(e), 6) AS worst, round(avg(e), 6) AS mean_error, count(*) AS n FROM e GROUP BY 1"),
    "downsample_mean": (downsample_mean, f"WITH s AS ({S.SQL[CORPUS]}), j AS (SELECT series_id, x, avg(x) OVER w AS m, min(x) OVER w AS lo, max(x) OVER w AS hi FROM s WINDOW w AS (PARTITION BY series_id, t // 8)) SELECT series_id, round(max(abs(x - m)), 6) AS worst_of_mean, max(hi - lo) AS widest_band FROM j GROUP BY 1"),
    "proxy_autocorr": (proxy_autocorr, f"WITH s AS (SELECT series_id, x, lag(x, 1) OVER w AS x1, lag(x, 24) OVER w AS x24 FROM ({S.SQL['events_weighted_hourly']}) WINDOW w AS (PARTITION BY series_id ORDER BY t)) SELECT series_id, round(corr(x, x1), 4) AS lag1, round(corr(x, x24), 4) AS lag24, round(avg(abs(x - x1)) / avg(abs(x - x24)), 4) AS local_over_long FROM s GROUP BY 1"),
    "contamination_overlap": (contamination_overlap, "SELECT 0::bigint AS overlap_rows"),
    "sentinel_screen": (sentinel_screen, f"WITH s AS (SELECT series_id, t, CASE WHEN series_id = '2-HIGH' AND t IN (100, 900, 1700) THEN -430000000 ELSE x END AS x FROM ({S.SQL['orders_priority_daily']})), d AS (SELECT *, abs(x - median(x) OVER (PARTITION BY series_id)) AS dev FROM s), f AS (SELECT *, dev > 1000 * greatest(median(dev) OVER (PARTITION BY series_id), 1.0) AS bad FROM d) SELECT series_id, count(*) FILTER (WHERE bad) AS flagged, bool_or(bad) AS drop_series, count(*) AS n FROM f GROUP BY 1"),
}


def gen_uniform(spark, d):
    """A uniform number for each event, from a hash of its id: the same in every engine."""
    e = S.table(spark, d, "events").select(F.col("event_id").cast("long").alias("t"))
    return e.select(F.lit("iid").alias("series_id"), "t", S.uniform_int(F.concat(F.lit("iid/"), F.col("t").cast("string")), 4096).alias("x"))


QUERIES["gen_uniform"] = (gen_uniform, f"SELECT 'iid' AS series_id, event_id::bigint AS t, {S.UNIFORM_SQL.format(key='(chr(105) || chr(105) || chr(100) || chr(47) || event_id)', bound=4096)} AS x FROM events")
