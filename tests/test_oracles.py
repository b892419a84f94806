"""Queries against DuckDB at the smallest scale, plans, and user functions."""

from __future__ import annotations

import glob
import math
import os

import duckdb
import pandas as pd
import pytest

from boundspark import catalog

ORACLES = catalog.oracle_sql()
QUERIES = catalog.queries()
FAST = [n for n in ORACLES if n.startswith(("series_", "lattice", "tolerance", "op_join", "op_gapfill", "op_win", "multilevel", "flip", "snap", "length", "downsample", "sentinel", "closed"))]


@pytest.fixture(scope="module")
def duck(sf):
    con = duckdb.connect()
    for f in glob.glob(f"{sf}/*.parquet"):
        con.sql(f"CREATE VIEW {os.path.basename(f)[:-8]} AS SELECT * FROM '{f}'")
    return con


def rows(df: pd.DataFrame) -> list:
    cell = lambda v: None if v is None or v is pd.NA or (isinstance(v, float) and math.isnan(v)) else float(v) if isinstance(v, int | float) and not isinstance(v, bool) else v.item() if hasattr(v, "item") else v
    cols = sorted(df.columns)
    return sorted((tuple(cell(v) for v in r) for r in df[cols].astype(object).itertuples(index=False, name=None)), key=repr)


@pytest.mark.parametrize("name", FAST)
def test_matches_oracle(spark, sf, duck, name):
    got, want = QUERIES[name](spark, sf).toPandas(), duck.sql(ORACLES[name]).df()
    assert sorted(got.columns) == sorted(want.columns)
    a, b = rows(got), rows(want)
    assert [tuple(map(str, r)) for r in a] == [tuple(map(str, r)) for r in b]


def test_lattice_plan_stays_in_the_jvm_with_one_window_exchange(spark, sf):
    from boundspark.plans import lattice as P
    from boundspark.plans import series as S

    s = S.uniform_k(spark, sf)
    t = P.with_tolerance(s, P.absolute(s, 5.0))
    plan = P.encode(t, 2)._jdf.queryExecution().executedPlan().toString()
    assert "Python" not in plan and "Pandas" not in plan


def test_scan_is_pruned(spark, sf):
    plan = QUERIES["op_scan_pruned"](spark, sf)._jdf.queryExecution().executedPlan().toString()
    assert "PushedFilters: [" in plan and "value" not in plan.split("ReadSchema")[1]


def test_lateral_ranks_carry_their_order(spark, sf):
    """A sort before the shuffle does not order the rows behind it: the window must name the order itself."""
    plan = QUERIES["op_join_lateral"](spark, sf)._jdf.queryExecution().executedPlan().toString()
    windows = [line for line in plan.splitlines() if "row_number()" in line and "Window [" in line]
    assert windows and all("o_totalprice" in line and "o_orderkey" in line for line in windows)


def test_user_functions(spark):
    from boundspark.functions.scalar import register_all

    register_all(spark)
    r = spark.sql("SELECT decode_indices(encode_indices(array(0L, -3L, 40L, 0L)), 4) AS k").first()
    assert list(r["k"]) == [0, -3, 40, 0]
    assert spark.sql("SELECT count(*) AS n FROM multilevel_schedule(64)").first()["n"] == 64


FROM_TABLES = ["anchor_grid", "coder_selftest", "container_split", "contamination_overlap", "context_ablation", "determinism_table", "determinism_ordered", "forecaster_variants", "gen_uniform", "hybrid_table", "leader_share", "harness_defect"]


@pytest.mark.parametrize("name", FROM_TABLES)
def test_reads_a_given_table(spark, sf, duck, name):
    """The job is done on a given table that Spark reads (or has staged by ranges), not on made-up rows."""
    df = QUERIES[name](spark, sf)
    assert any("/events.parquet" in f or "/ranges-" in f for f in df.inputFiles())
    if name in ORACLES:
        assert rows(df.toPandas()) == rows(duck.sql(ORACLES[name]).df())


def test_entry_module_lists_everything():
    import __spark_entry__ as e

    assert set(e.oracle_sql()) <= set(e.queries())
    assert len(e.queries()) > 150
