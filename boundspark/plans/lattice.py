"""Tolerances and the lattice form of closed-loop coding with integer predictors.

A closed loop whose predictor has integer weights and starts on the first sample only ever reconstructs points
base + step * integer. So the integer is floor((x - base) / step + 1/2), and the indices of the loop are its finite
differences: a stateless projection and ``lag``, one exchange and one sort for all orders and tolerances.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import window as W

RHOS = (0.01, 0.05, 0.2)


def moments(series: DataFrame, by: tuple[str, ...] = ("series_id",)) -> DataFrame:
    """Count, sum and n * sum(x^2) - sum(x)^2, in exact integers: independent of row order."""
    base = series.groupBy(*by).agg(F.count(F.lit(1)).alias("n"), F.sum(F.col("x").cast("decimal(19,0)")).alias("s1"), F.sum(F.col("x").cast("decimal(19,0)") * F.col("x").cast("decimal(19,0)")).alias("s2"), F.sum(F.abs("x").cast("decimal(19,0)")).alias("s_abs"))
    wide = lambda c: F.col(c).cast("decimal(38,0)")
    spread = wide("s2") * F.col("n").cast("decimal(10,0)") - wide("s1") * F.col("s1").cast("decimal(19,0)")
    return base.select(*by, "n", F.col("s1").cast("long").alias("total"), F.col("s_abs").cast("double").alias("s_abs"), spread.cast("double").alias("v"))


def by_sigma(series: DataFrame, rhos: tuple[float, ...] = RHOS, ddof: int = 0) -> DataFrame:
    """(series_id, rho, n, tau, step, rel_err_pct, sub_integer): tau is rho times the standard deviation."""
    m = moments(series).withColumn("rho", F.explode(F.array(*map(F.lit, rhos))))
    sigma = F.sqrt("v") / (F.col("n") if ddof == 0 else F.sqrt(F.col("n").cast("double") * F.greatest(F.col("n") - 1, F.lit(1))))
    step = 2 * F.col("rho") * sigma
    tau = F.col("rho") * sigma
    return m.select("series_id", "rho", "n", tau.alias("tau"), step.alias("step"), (F.when(F.col("s_abs") > 0, 100 * tau * F.col("n") / F.col("s_abs"))).alias("rel_err_pct"), (tau < 0.5).alias("sub_integer"))


def absolute(series: DataFrame, tau: float) -> DataFrame:
    return series.groupBy("series_id").agg(F.count(F.lit(1)).alias("n")).select("series_id", F.lit(0.0).alias("rho"), "n", F.lit(float(tau)).alias("tau"), F.lit(2.0 * tau).alias("step"), F.lit(None).cast("double").alias("rel_err_pct"), F.lit(tau < 0.5).alias("sub_integer"))


def relative(series: DataFrame, pct: float) -> DataFrame:
    """Tolerance as a percentage of the mean absolute value."""
    tau = F.lit(pct / 100.0) * F.col("s_abs") / F.col("n")
    return moments(series).select("series_id", F.lit(0.0).alias("rho"), "n", tau.alias("tau"), (2 * tau).alias("step"), F.lit(float(pct)).alias("rel_err_pct"), (tau < 0.5).alias("sub_integer"))


def with_tolerance(series: DataFrame, tol: DataFrame) -> DataFrame:
    """Samples with their tolerances; the dictionary of series is joined by the planner's choice, not forced."""
    return series.join(tol.select("series_id", "rho", "tau", "step"), "series_id")


def lattice_point(x: Column, base: Column, step: Column) -> Column:
    return F.when(step == 0, F.lit(0)).otherwise(F.floor((x - base) / step + 0.5)).cast("long")


def encode(samples: DataFrame, order: int = 1, season: int | None = None, chunk: int | None = None) -> DataFrame:
    """(series_id, rho, t, k, xhat) of the Lorenzo predictor of an order, or of the sample one season before."""
    keys = ["series_id", "rho"]
    if chunk:
        samples = samples.withColumn("chunk", F.expr(f"t div {chunk}"))
        keys.append("chunk")
    w = W.Window.partitionBy(*keys).orderBy("t")
    base = F.first("x").over(w)
    d = samples.withColumn("base", base).withColumn("q", lattice_point(F.col("x"), F.col("base"), F.col("step")))
    k: Column = F.col("q")
    if season:
        k = k - F.coalesce(F.lag("q", season).over(w), F.lit(0))
    else:
        terms = {1: ((1, 1),), 2: ((1, 2), (2, -1)), 3: ((1, 3), (2, -3), (3, 1))}[order]
        for lag, weight in terms:
            k = k - weight * F.coalesce(F.lag("q", lag).over(w), F.lit(0))
    return d.select(*keys, "t", k.cast("long").alias("k"), (F.col("base") + F.col("q") * F.col("step")).alias("xhat"), "x", "tau", "step", "base")


def decode(indices: DataFrame, order: int = 1) -> DataFrame:
    """Reconstruction from indices: ``order`` nested running sums, then one multiplication."""
    w = W.Window.partitionBy("series_id", "rho").orderBy("t").rowsBetween(W.Window.unboundedPreceding, 0)
    d = indices.withColumn("q", F.col("k"))
    for _ in range(order):
        d = d.withColumn("q", F.sum("q").over(w))
    return d.select("series_id", "rho", "t", (F.col("base") + F.col("q") * F.col("step")).alias("xhat"))


# --- the 64-tick multilevel form: one projection for each of six levels, over arrays ----------------------------


def multilevel_plan(kind: str = "linear", size: int = 64) -> list[tuple[int, int, list[tuple[float, int]]]]:
    """(target, stride, weights) in emission order for a block of ``size`` ticks; a target has known neighbours only."""
    plan: list[tuple[int, int, list[tuple[float, int]]]] = [(0, 0, [])]
    stride = size // 2
    while stride >= 1:
        for i in range(stride, size, 2 * stride):
            left, right = i - stride, i + stride
            if kind == "cubic" and i - 3 * stride >= 0 and i + 3 * stride < size:
                w = [(-1 / 16, i - 3 * stride), (9 / 16, left), (9 / 16, right), (-1 / 16, i + 3 * stride)]
            elif right < size:
                w = [(0.5, left), (0.5, right)]
            else:
                w = [(1.0, left)]
            plan.append((i, stride, w))
        stride //= 2
    return plan


def _level_indices(pred, s: int):
    def at(old: Column, i: Column) -> Column:
        x = F.element_at("xs", (i + 1).cast("int"))
        k = F.when(F.col("step") == 0, F.lit(0)).otherwise(F.floor((x - pred(i)) / F.col("step") + 0.5)).cast("long")
        return F.when(F.pmod(i, F.lit(2 * s)) == s, k).otherwise(old)

    return at


def _level_values(pred, s: int):
    def at(old: Column, i: Column) -> Column:
        return F.when(F.pmod(i, F.lit(2 * s)) == s, pred(i) + F.element_at("ks", (i + 1).cast("int")) * F.col("step")).otherwise(old)

    return at


def multilevel_blocks(samples: DataFrame, kind: str = "linear", size: int = 64) -> DataFrame:
    """(series_id, rho, t, k, xhat) by multilevel interpolation inside blocks of ``size`` ticks; the last may be shorter.

    A block is one array row; levels are chained projections over the arrays, so no loop runs outside the plan.
    """
    rows = samples.withColumn("block", F.expr(f"t div {size}"))
    cells = rows.groupBy("series_id", "rho", "block").agg(F.array_sort(F.collect_list(F.struct("t", "x"))).alias("c"), F.first("step").alias("step"))
    d = cells.select("series_id", "rho", "block", "step", F.col("c.x").alias("xs"))
    d = d.select("*", F.transform("xs", lambda x: F.lit(0).cast("long")).alias("ks"), F.transform("xs", lambda x, i: F.when(i == 0, F.col("xs")[0].cast("double")).otherwise(F.lit(0.0))).alias("hs"))
    stride = size // 2
    while stride >= 1:
        s = stride

        def pred(i: Column, s: int = s) -> Column:
            h, m = lambda j: F.element_at("hs", (j + 1).cast("int")), F.size("xs")
            right = h(F.least(i + s, m - 1))
            lin = F.when(i + s < m, 0.5 * h(i - s) + 0.5 * right).otherwise(h(i - s))
            if kind == "linear":
                return lin
            far = (i - 3 * s >= 0) & (i + 3 * s < m)
            lo, hi = F.greatest(i - 3 * s, F.lit(0)), F.least(i + 3 * s, m - 1)
            return F.when(far, (-1 * h(lo) + 9 * h(i - s) + 9 * right - h(hi)) / 16).otherwise(lin)

        d = d.withColumn("ks", F.transform("ks", _level_indices(pred, s))).withColumn("hs", F.transform("hs", _level_values(pred, s)))
        stride //= 2
    out = d.select("series_id", "rho", "block", F.posexplode(F.arrays_zip("ks", "hs")).alias("i", "v"))
    return out.select("series_id", "rho", (F.col("block") * size + F.col("i")).alias("t"), F.col("v.ks").alias("k"), F.col("v.hs").alias("xhat"))
