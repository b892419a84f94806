"""Closed-loop kernels in lockstep: arrays are (lanes, ticks); a lane is one series at one tolerance.

Each function returns indices ``k`` and reconstructions ``xhat``; predictors only ever see reconstructions.
"""

from __future__ import annotations

import math

import numpy as np

from boundspark.operators.forecast import Forecaster, Pooled


def quantize(x: np.ndarray, p: np.ndarray, step: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    safe = np.where(step > 0, step, 1.0)
    k = np.where(step > 0, np.floor((x - p) / safe + 0.5), 0.0)
    xhat = np.where(step > 0, p + k * step, p)
    # after rounding the error may pass half a step by an ulp: move to the neighbour if that one is nearer
    over = np.abs(xhat - x) > 0.5 * step
    if over.any():
        move = np.where(over, np.sign(x - xhat), 0.0)
        better = np.abs(p + (k + move) * step - x) < np.abs(xhat - x)
        k = np.where(over & better, k + move, k)
        xhat = np.where(over & better, p + k * step, xhat)
    return k.astype(np.int64), xhat


def lorenzo(x: np.ndarray, step: np.ndarray, order: int) -> tuple[np.ndarray, np.ndarray]:
    """The lattice form: base plus whole steps, differenced ``order`` times."""
    s, base = step[:, None], x[:, :1].astype(np.float64)
    q = np.where(s > 0, np.floor((x - base) / np.where(s > 0, s, 1.0) + 0.5), 0.0).astype(np.int64)
    k = q
    for _ in range(order):
        k = np.diff(k, axis=1, prepend=0)
    return k, base + q * s


def lorenzo_decode(k: np.ndarray, base: np.ndarray, step: np.ndarray, order: int) -> np.ndarray:
    for _ in range(order):
        k = np.cumsum(k, axis=1)
    return base[:, None] + k * step[:, None]


def levels(n: int) -> list[int]:
    out, s = [], 1
    while s < n:
        out.append(s)
        s *= 2
    return out[::-1]


def _neighbours(xhat: np.ndarray, i: np.ndarray, s: int, kind: str) -> np.ndarray:
    n = xhat.shape[1]
    left, right = xhat[:, i - s], xhat[:, np.minimum(i + s, n - 1)]
    p = np.where(i + s < n, 0.5 * left + 0.5 * right, left)
    if kind == "cubic":
        far = (i - 3 * s >= 0) & (i + 3 * s < n)
        c = (-1 * xhat[:, np.maximum(i - 3 * s, 0)] + 9 * left + 9 * right - xhat[:, np.minimum(i + 3 * s, n - 1)]) / 16
        p = np.where(far, c, p)
    return p


def multilevel(x: np.ndarray, step: np.ndarray, kind: str) -> tuple[np.ndarray, np.ndarray]:
    """Interpolation from coarse to fine; indices in emission order (level by level), reconstructions in time order."""
    n = x.shape[1]
    xhat = np.zeros(x.shape)
    xhat[:, 0] = x[:, 0]
    ks = [np.zeros((len(x), 1), np.int64)]
    for s in levels(n):
        i = np.arange(s, n, 2 * s)
        k, xhat[:, i] = quantize(x[:, i], _neighbours(xhat, i, s, kind), step[:, None])
        ks.append(k)
    return np.concatenate(ks, axis=1), xhat


def multilevel_decode(k: np.ndarray, base: np.ndarray, step: np.ndarray, kind: str) -> np.ndarray:
    n, at = k.shape[1], 1
    xhat = np.zeros(k.shape)
    xhat[:, 0] = base
    for s in levels(n):
        i = np.arange(s, n, 2 * s)
        xhat[:, i] = _neighbours(xhat, i, s, kind) + k[:, at : at + len(i)] * step[:, None]
        at += len(i)
    return xhat


def lag_matrix(x: np.ndarray, lags: list[int]) -> tuple[np.ndarray, np.ndarray]:
    """Design (ticks, lags) and target of one series, from the tick where all lags exist."""
    t = np.arange(max(lags), len(x))
    return np.stack([x[t - g] for g in lags], 1), x[t]


def fit_lags(x: np.ndarray, lags: list[int], ridge: float = 1e-6) -> np.ndarray:
    """Least squares of a series on its own lags, about its mean; the last entry is the mean."""
    mean = x.mean()
    if len(x) <= 2 * max(lags) or x.std() == 0:
        w = np.zeros(len(lags))
        w[0] = 1.0
        return np.r_[w, mean]
    g, b = np.zeros((len(lags), len(lags))), np.zeros(len(lags))
    for a, y in _lag_blocks(x, mean, lags):
        g, b = g + a.T @ a, b + a.T @ y
    return np.r_[np.linalg.solve(g + ridge * max(np.trace(g) / len(lags), 1e-12) * np.eye(len(lags)), b), mean]


#: Rows of a lag matrix that are held at a time.
LAG_ROWS = 1 << 14


def _lag_blocks(x: np.ndarray, mean: float, lags: list[int]):
    """The lag matrix and target of ``x - mean``, LAG_ROWS rows at a time."""
    top = max(lags)
    for at in range(top, len(x), LAG_ROWS):
        yield lag_matrix(x[at - top : at + LAG_ROWS].astype(np.float64) - mean, lags)


def lags_closed_loop(x: np.ndarray, step: np.ndarray, lags: list[int], coefs: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Linear prediction with coefficients of each lane; before all lags exist the last value predicts."""
    lanes, n = x.shape
    xhat, k = np.zeros((n, lanes)), np.zeros((n, lanes), np.int64)
    xhat[0] = x[:, 0]
    w, mean, top = coefs[:, :-1].T, coefs[:, -1], max(lags)
    xt = x.T.astype(np.float64)
    dense = lags == list(range(1, top + 1))
    wd = w[::-1]
    for t in range(1, n):
        if t < top:
            p = xhat[t - 1]
        elif dense:
            p = mean + ((xhat[t - top : t] - mean) * wd).sum(axis=0)
        else:
            p = mean + sum(w[j] * (xhat[t - g] - mean) for j, g in enumerate(lags))
        k[t], xhat[t] = quantize(xt[t], p, step)
    return k.T, xhat.T


def open_loop_residuals(x: np.ndarray, lags: list[int], coefs: np.ndarray) -> np.ndarray:
    """Integer residuals of rounded predictions from the true history of one series (lossless path)."""
    top, w, mean = max(lags), coefs[:-1], coefs[-1]
    r = np.diff(x, prepend=0).astype(np.float64)
    if len(x) > top:
        at = top
        for a, y in _lag_blocks(x, mean, lags):
            r[at : at + len(y)] = y - np.round(a @ w + mean) + mean
            at += len(y)
    return np.round(r).astype(np.int64)


def _forecast_one(x: np.ndarray, step: float, seed: np.ndarray, model: Pooled) -> tuple[np.ndarray, np.ndarray] | None:
    """``forecast_loop`` of one lane in plain numbers: the same operations in the same order, at a tenth of the time.
    None where a prediction is not finite."""
    n, c = len(x), seed.shape[1]
    state = model.start(seed)
    (first, *lags), w = state.lags, state.w.tolist()
    pairs, w0, m, window = list(zip(w[1:], lags, strict=True)), w[0], model.memory, state.window
    e0, e1, e2, e3 = state.error[:, 0].tolist()
    total, season, half = float(state.total[0]), 168 if c >= 168 else min(24, c), 0.5 * step
    h, ks, values = seed[0].tolist(), np.zeros(n - c, np.int64), x.tolist()
    for t in range(c, n):
        p = w0 * h[t - first]
        for wk, g in pairs:
            p += wk * h[t - g]
        q1, q2, q3 = total / window, h[t - 1], h[t - season]
        a, b, d, f = e0 * e0 * e0 * e0, e1 * e1 * e1 * e1, e2 * e2 * e2 * e2, e3 * e3 * e3 * e3
        if not (a and b and d and f):
            return None
        a, b, d, f = 1.0 / a, 1.0 / b, 1.0 / d, 1.0 / f
        best = (0.0 + a * p + b * q1 + d * q2 + f * q3) / (0.0 + a + b + d + f)
        if not math.isfinite(best):
            return None
        v = float(values[t])
        k = math.floor((v - best) / step + 0.5)
        r = best + k * step
        if abs(r - v) > half:
            other = k + (1 if v > r else -1)
            if abs(best + other * step - v) < abs(r - v):
                k, r = other, best + other * step
        ks[t - c] = k
        e0, e1, e2, e3 = e0 * m + abs(p - r), e1 * m + abs(q1 - r), e2 * m + abs(q2 - r), e3 * m + abs(q3 - r)
        total = total + r - h[t - window]
        h.append(r)
    return ks[None], np.array(h[c:])[None]


def forecast_loop(x: np.ndarray, step: np.ndarray, seed: np.ndarray, model: Forecaster, want_spread: bool = False):
    """Body of the codec: ticks from seed.shape[1] on, in lockstep, from reconstructed context ``seed``."""
    lanes, n = x.shape
    c = seed.shape[1]
    if lanes == 1 and not want_spread and step[0] > 0 and isinstance(model, Pooled) and model.mode == "ordered" and model.experts and not model.snap:
        one = _forecast_one(x[0], float(step[0]), seed, model)
        if one is not None:
            return one
    state = model.start(seed)
    k, xhat = np.zeros((lanes, n - c), np.int64), np.zeros((lanes, n - c))
    spread = np.zeros((lanes, n - c)) if want_spread else None
    xf = x.astype(np.float64)
    for t in range(c, n):
        p = state.predict()
        if spread is not None:
            spread[:, t - c] = state.spread()
        k[:, t - c], r = quantize(xf[:, t], p, step)
        xhat[:, t - c] = r
        state.push(r)
    return (k, xhat, spread) if want_spread else (k, xhat)


def forecast_decode(k: np.ndarray, step: np.ndarray, seed: np.ndarray, model: Forecaster) -> np.ndarray:
    state = model.start(seed)
    out = np.zeros(k.shape)
    for t in range(k.shape[1]):
        p = state.predict()
        r = np.where(step > 0, p + k[:, t] * step, p)
        out[:, t] = r
        state.push(r)
    return out


def hybrid_loop(x: np.ndarray, step: np.ndarray, seed: np.ndarray, model: Forecaster, how: str, block: int = 256):
    """Closed loop of the forecaster with persistence as the classical partner. ``blend``: weights by trailing
    inverse error; ``leader``: the winner of the block before, the forecaster at first. Neither sends side information.
    Returns k, xhat and the share of blocks that the forecaster led."""
    lanes, n = x.shape
    c = seed.shape[1]
    state, last = model.start(seed), seed[:, -1].copy()
    k, xhat = np.zeros((lanes, n - c), np.int64), np.zeros((lanes, n - c))
    err = np.full((2, lanes), 1e-9)
    block_err = np.zeros((2, lanes))
    leads, led, blocks = np.ones(lanes, bool), np.zeros(lanes), 0
    for t in range(c, n):
        a, b = state.predict(), last
        if (t - c) % block == 0:
            if t > c:
                leads = block_err[0] <= block_err[1]
            led, blocks = led + leads, blocks + 1
            block_err = np.zeros((2, lanes))
        if how == "blend":
            wa, wb = 1 / err[0], 1 / err[1]
            p = (wa * a + wb * b) / (wa + wb)
        else:
            p = np.where(leads, a, b)
        k[:, t - c], r = quantize(x[:, t].astype(np.float64), p, step)
        xhat[:, t - c] = r
        e = np.stack([np.abs(a - r), np.abs(b - r)])
        err, block_err = err * (1 - 1 / block) + e, block_err + e
        state.push(r)
        last = r
    return k, xhat, led / max(blocks, 1)
