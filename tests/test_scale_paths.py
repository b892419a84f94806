"""Paths that only larger inputs take: many files, many groups, ranges of one series, archives of many appends."""

from __future__ import annotations

import time

import numpy as np
import pytest

from boundspark.operators import codec as K
from boundspark.operators.forecast import LAGS, Pooled
from boundspark.plans import lattice as P
from boundspark.plans import series as S
from boundspark.sources import archive as A
from boundspark.streaming import encoders

MODEL = Pooled(LAGS, (0.4, *([0.0] * 9), 0.3, *([0.0] * 4), 0.3, 0.0))


@pytest.fixture(scope="module")
def many_files(spark, sf, tmp_path_factory):
    """The events in four files of one folder, written one after another."""
    d = tmp_path_factory.mktemp("files")
    events = spark.read.parquet(f"{sf}/events.parquet")
    most = events.agg({"event_id": "max"}).first()[0] + 1
    for k in range(4):
        events.where(f"event_id * 4 div {most} = {k}").coalesce(1).write.mode("append").parquet(f"file://{d}/events.parquet")
        time.sleep(1.1)
    return f"file://{d}"


@pytest.mark.parametrize("name", ["st_scan", "st_lattice", "st_tumbling", "st_dedup", "st_group_encode"])
def test_streams_over_several_files_and_batches(spark, sf, many_files, name):
    run = encoders.QUERIES[name][0]
    rows = lambda d: sorted(map(tuple, run(spark, d).collect()), key=repr)
    assert rows(many_files) == rows(sf) != []


def test_an_empty_stream_has_an_empty_result(spark, many_files):
    assert encoders.drain(encoders.events_stream(spark, many_files).where("event_id < 0").select("event_id")).count() == 0


def _series(spark, lengths):
    rows = [(f"s{i}", t, (i + 3) * t % 17) for i, n in enumerate(lengths) for t in range(n)]
    return spark.createDataFrame(rows, "series_id string, t long, x long")


def test_groups_are_dense_and_windows_hold_names_alone(spark):
    rows = K.arrays(_series(spark, [5] * 21 + [8] * 3))
    got = K.grouped(rows, 4).select("series_id", "n", "group_id", "lane").collect()
    for n, many in ((5, 21), (8, 3)):
        places = sorted((r["group_id"], r["lane"]) for r in got if r["n"] == n)
        assert places == [(k // 4, k % 4) for k in range(many)]
    plan = K.grouped(rows, 4)._jdf.queryExecution().optimizedPlan().toString()
    for line in plan.splitlines():
        if "Window" in line:
            assert "xs" not in line


def test_one_series_over_several_ranges(spark):
    df = spark.range(1000).selectExpr("id * 7 % 1000 AS by", "id % 5 AS x").repartition(6)
    rows = S._ordered(df, S.F.lit("one"), "by", S.F.col("x"), running=True).collect()
    x = {r["by"]: r["x"] for r in df.collect()}
    want = np.cumsum([x[k] for k in range(1000)]).tolist()
    assert [r["x"] for r in sorted(rows, key=lambda r: r["t"])] == want and sorted(r["t"] for r in rows) == list(range(1000))


@pytest.mark.parametrize("kind", ["linear", "cubic"])
@pytest.mark.parametrize("n", [1, 2, 63, 64, 65, 150])
def test_multilevel_blocks_keep_short_blocks(spark, kind, n):
    s = _series(spark, [n])
    out = P.multilevel_blocks(P.with_tolerance(s, P.absolute(s, 1.5)), kind).join(s, ["series_id", "t"]).collect()
    assert sorted(r["t"] for r in out) == list(range(n))
    assert all(abs(r["xhat"] - r["x"]) <= 1.5 + 1e-9 for r in out)


def test_an_archive_of_many_appends_decodes(spark, tmp_path):
    """The same group written for two corpora, lengths and tolerances: every lane is there, and whole."""
    path = f"file://{tmp_path}/archive"
    both = {"a": _series(spark, [40] * 5 + [60] * 2), "b": _series(spark, [40] * 3)}
    for name, s in both.items():
        A.write_archive(K.encode_groups(s, MODEL, c=20, g=4, rhos=(0.05, 0.2)), path, name)
    rows = A.read_archive(spark, path)
    assert rows.where("NOT pad").count() == 2 * (7 + 3)
    for name, s in both.items():
        back = K.decode_groups(A.containers_of(rows.where(S.F.col("corpus") == name)), MODEL)
        assert back.count() == 2 * s.count() and back.where("NOT sha_ok").count() == 0
    one = rows.where("corpus = 'a' AND series_id = 's6' AND rho = 0.2")
    assert {r["series_id"] for r in K.decode_groups(A.containers_of(rows, one), MODEL).select("series_id").distinct().collect()} == {"s5", "s6"}
    plan = rows.where("high > 5").select("series_id", "high")._jdf.queryExecution().executedPlan().toString()
    assert "GreaterThan(high,5.0)" in plan


def test_one_lane_in_plain_numbers_equals_the_lockstep():
    """Few lanes are coded one by one, in blocks; one lane is forecast in plain numbers: bytes and indices are the same."""
    from boundspark.operators import entropy as E
    from boundspark.operators import loops as L

    r = np.random.default_rng(2)
    lanes = [r.laplace(0, s, n).round().astype(np.int64) for s in (0.3, 5, 4000) for n in (0, 1, 2, 3, 50, 51, 52, 200, 300, 301, 302, 303)]
    assert len(lanes) > E.FEW_LANES
    for few, many in zip(map(lambda k: E._encode_lane(k, None, 1), lanes), E.encode_lanes(lanes), strict=True):
        assert few == many
    x = (1000 + 200 * np.sin(np.arange(600) / 4) + r.normal(0, 20, 600)).round().astype(np.int64)[None]
    step = np.array([12.0])
    seed = L.lorenzo(x[:, :200], step, 1)[1]
    one, whole = L.forecast_loop(x, step, seed, MODEL), L.forecast_loop(x, step, seed, MODEL, want_spread=True)
    assert np.array_equal(one[0], whole[0]) and np.array_equal(one[1], whole[1])


def test_a_long_series_is_dealt_by_coder_and_tolerance(spark, monkeypatch):
    """A series of more than PIECE ticks reaches no task as one row, and its coders are tasks of their own."""
    s = _series(spark, [400, 400, 90])
    whole = K.study(s, "c", MODEL, c=60).drop("corpus")
    monkeypatch.setattr(K, "PIECE", 128)
    assert max(r["n"] for r in K.pieces(s, 4).selectExpr("size(xs) AS n").collect()) <= 128
    parted = K.study(s, "c", MODEL, c=60).drop("corpus")
    exact = ["series_id", "rho", "coder", "n", "bytes", "seed_bytes", "xz_bytes"]
    rows = lambda df: sorted(map(tuple, df.select(*exact).collect()))
    assert rows(parted) == rows(whole) and len(rows(whole)) == 3 * 3 * 7
    plan = K.study(s, "c", MODEL, c=60)._jdf.queryExecution().executedPlan().toString()
    assert "unit" in plan


def test_lossless_kernels_hold_blocks_only():
    """Memory of the lossless kernels does not follow the length of a series; their results do not follow the blocks."""
    import tracemalloc

    from boundspark.operators import entropy as E
    from boundspark.operators import loops as L
    from boundspark.operators.forecast import open_loop

    x = np.cumsum(np.random.default_rng(3).integers(0, 100, 120_000))
    lags = list(range(1, 257))
    tracemalloc.start()
    E.mixture_bits(L.open_loop_residuals(x, lags, L.fit_lags(x.astype(float), lags)))
    peak = tracemalloc.get_traced_memory()[1]
    tracemalloc.stop()
    assert peak < 120 << 20  # the whole lag matrix alone has 235 MB
    state, want = MODEL.start(x[None, :192].astype(float)), []
    for t in range(192, 3000):
        want.append(float(state.predict()[0]))
        state.push(x[t : t + 1].astype(float))
    assert np.array_equal(open_loop(MODEL, x[:3000], 192, 700), np.array(want))


def test_the_context_ablation_scores_every_context_that_fits(spark):
    """Each series at each context shorter than it, the same last ticks scored for all, and bytes of whole archives."""
    from boundspark.experiments import studies

    s = _series(spark, [1100] * 3 + [300, 65, 64, 1])
    got = {(r["series_id"], r["c"]): r for r in studies._ablation(spark, "", s, MODEL).collect()}
    lengths = {"s0": 1100, "s1": 1100, "s2": 1100, "s3": 300, "s4": 65}
    assert set(got) == {(k, c) for k, n in lengths.items() for c in (0, 64, 128, 256, 512, 1024) if c < n}
    assert {(r["n"], r["scored"]) for r in got.values()} == {(1100, 76), (300, 44), (65, 1)}
    for k, n in lengths.items():
        x = np.array([[(int(k[1:]) + 3) * t % 17 for t in range(n)]])
        tau = 0.05 * K.sigma(x)
        assert got[k, 0]["total"] == 8 * studies._best_classic(x, 2 * tau)[0] / n
        for c in (c for c in (64, 128, 256, 512, 1024) if c < n):
            e, r = K.encode_group(x, tau, c, MODEL), got[k, c]
            assert (r["seed"], r["total"]) == (8 * len(e["seed"][0]) / c, 8 * (len(e["seed"][0]) + len(e["body"][0])) / n)
            assert r["body"] == 8 * len(studies.E.encode_lanes([e["k"][0][-r["scored"] :]])[0]) / r["scored"]


def test_the_context_ablation_is_whole(spark, sf):
    """Shipments and generated demand at all five contexts, events at those shorter than their 720 hours, with gains."""
    from boundspark import catalog

    rows = catalog.queries()["context_ablation"](spark, sf).collect()
    seen = {}
    for r in rows:
        seen.setdefault((r["corpus"], r["n"], r["n_series"]), []).append(r)
    table = lambda name: (name, *S.CATALOG[name](spark, sf).selectExpr("count(DISTINCT t)", "count(DISTINCT series_id)").first())
    whole = [table("ship_nation_daily"), ("gen_demand", 4300, 16), ("gen_demand", 43800, 16)]
    assert set(seen) == {*whole, table("events_weighted_hourly")}
    for key, part in seen.items():
        part.sort(key=lambda r: r["c"])
        assert [r["c"] for r in part] == [64, 128, 256, 512, 1024][: 5 if key in whole else 4]
        assert {r["scored"] for r in part} == {key[1] - part[-1]["c"]} and part[-1]["body_delta_pct"] == 0
        for r in part:
            assert abs(r["gain_pct"] - 100 * (1 - r["codec_bpv"] / r["classic_bpv"])) < 1e-3
