"""Coders, closed loops, containers: round trips, bounds, worked vectors."""

from __future__ import annotations

import numpy as np
import pytest
from hypothesis import given, settings
from hypothesis import strategies as st

from boundspark.operators import codec as K
from boundspark.operators import entropy as E
from boundspark.operators import loops as L
from boundspark.operators.forecast import LAGS, Pooled, SeasonalProfile

MODEL = Pooled(LAGS, (0.4, *([0.0] * 9), 0.3, *([0.0] * 4), 0.3, 0.0))


@settings(max_examples=60, deadline=None)
@given(st.lists(st.lists(st.integers(-(2**62), 2**62) | st.integers(-20, 20), max_size=40), min_size=1, max_size=4))
def test_range_coder_round_trip_and_lanes_do_not_mix(lanes):
    arrays = [np.array(x, np.int64) for x in lanes]
    coded = E.encode_lanes(arrays)
    for a, b in zip(arrays, coded, strict=True):
        assert np.array_equal(E.decode_lane(b, len(a)), a)
        assert E.encode_lanes([a])[0] == b


def test_ideal_bits_never_exceed_real_bits():
    k = np.random.default_rng(1).laplace(0, 5, 2000).round().astype(np.int64)
    assert E.adaptive_ideal_bits(k) <= 8 * len(E.encode_lanes([k])[0])


def test_lattice_vectors():
    x, d = np.array([[10, 12, 15, 15, 9, 30]]), np.array([4.0])
    assert L.lorenzo(x, d, 1)[0].tolist() == [[0, 1, 0, 0, -1, 5]]
    assert L.lorenzo(x, d, 2)[0].tolist() == [[0, 1, -1, 0, -1, 6]]
    assert L.lorenzo(x, d, 3)[0].tolist() == [[0, 1, -2, 1, -1, 7]]
    assert L.lorenzo(x, d, 1)[1].tolist() == [[10, 14, 14, 14, 10, 30]]


def test_multilevel_vector():
    k, xhat = L.multilevel(np.array([[10, 12, 15, 15, 9]]), np.array([4.0]), "linear")
    assert k.tolist() == [[0, 0, 1, 0, 1]]
    assert xhat.tolist() == [[10, 12, 14, 16, 10]]


@pytest.mark.parametrize("n", [1, 2, 3, 17, 64, 65, 300])
@pytest.mark.parametrize("rho", [0.01, 0.05, 0.2])
def test_every_coder_keeps_the_bound_and_decodes(n, rho):
    x = np.random.default_rng(n).integers(-500, 5000, (3, n))
    step = 2 * rho * K.sigma(x)
    base = x[:, 0].astype(float)
    for i, (_, fn) in enumerate(K.SEED_PREDICTORS):
        k, xhat = fn(x, step)
        assert (np.abs(xhat - x) <= step[:, None] / 2 * (1 + 1e-9) + 1e-9).all()
        assert np.array_equal(K.SEED_DECODERS[i](k, base, step), xhat)


def test_group_round_trip_and_batch_invariance():
    r = np.random.default_rng(3)
    t = np.arange(500)
    x = np.stack([1000 + 200 * np.sin(2 * np.pi * t / 24) + r.normal(0, 20, 500) for _ in range(5)]).round().astype(np.int64)
    tau = 0.05 * K.sigma(x)
    whole = K.encode_group(x, tau, 200, MODEL)
    lanes = [{"tau": tau[i], "x0": int(x[i, 0]), "seed_id": int(whole["seed_id"][i]), "seed": whole["seed"][i], "body": whole["body"][i]} for i in range(5)]
    assert np.array_equal(K.decode_group(lanes, 500, 200, MODEL), whole["xhat"])
    alone = K.encode_group(x[2:3], tau[2:3], 200, MODEL)
    assert alone["body"][0] == whole["body"][2]


def test_constant_series_costs_a_flush():
    x = np.full((1, 400), 7)
    enc = K.encode_group(x, np.zeros(1), 128, SeasonalProfile(24))
    assert np.array_equal(enc["xhat"], x)


def test_mixture_reads_uniform_noise():
    v = np.random.default_rng(5).integers(0, 4096, 6000) - 2048
    assert abs(E.mixture_bits(v) / len(v) - 12) < 0.05


def test_header():
    assert K.read_header(K.header_bytes(8, 256, 1000, 0.05, "abc")) == {"version": 1, "g": 8, "c": 256, "n": 1000, "rho": 0.05, "fingerprint": "abc"}
