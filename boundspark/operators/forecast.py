"""Forecasters for the bounded codec: a protocol, a pooled stand-in for a pre-trained model, and adapters.

No pre-trained weights exist here, so the stand-in is fitted once on generated corpora that no experiment reads and
then applied unchanged (zero-shot) to every series. It holds a pooled autoregression on short and seasonal lags, a
local mean and persistence, and weighs them by their errors in the context. All arithmetic of the ``ordered`` mode is
elementwise over lanes in a fixed order, so a lane's prediction does not depend on the size of its batch.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator
from dataclasses import dataclass, field
from itertools import accumulate
from typing import Protocol

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

#: Lags in ticks: recent ones, a day and a week of hours, a week of days.
LAGS = (1, 2, 3, 4, 5, 6, 7, 14, 21, 23, 24, 25, 48, 72, 167, 168, 169)


class State(Protocol):
    def predict(self) -> np.ndarray: ...
    def push(self, reconstruction: np.ndarray) -> None: ...


class Forecaster(Protocol):
    """``start`` takes contexts (lanes, c); the state predicts one tick and is fed the reconstruction."""

    def start(self, context: np.ndarray) -> State: ...
    def fingerprint(self) -> str: ...


@dataclass(frozen=True)
class Pooled:
    lags: tuple[int, ...]
    weights: tuple[float, ...]
    mode: str = "ordered"
    memory: float = 0.97
    snap: float = 0.0
    experts: bool = True

    def start(self, context: np.ndarray) -> PooledState:
        return PooledState(self, context)

    def fingerprint(self) -> str:
        text = repr((self.lags, [w.hex() for w in self.weights], self.mode, self.memory, self.snap, self.experts))
        return hashlib.sha256(text.encode()).hexdigest()[:16]

    def usable(self, c: int) -> tuple[list[int], np.ndarray]:
        """Lags that fit a context; the weight of the others goes to the last value, so weights still sum to one."""
        lags = [g for g in self.lags if g <= c]
        w = np.array([self.weights[k] for k, g in enumerate(self.lags) if g <= c])
        w[0] += 1 - w.sum()
        return lags, w


@dataclass
class PooledState:
    model: Pooled
    context: np.ndarray
    at: int = 0
    error: np.ndarray = field(init=False)

    def __post_init__(self) -> None:
        g, self.c = self.context.shape
        self.ring = np.ascontiguousarray(self.context.T, np.float64)  # (c, lanes): one row for each tick
        self.lags, self.w = self.model.usable(self.c)
        self.error = np.full((4, g), 1e-9)
        self.window = min(32, self.c)
        self.total = np.zeros(g)
        for k in range(self.window):
            self.total = self.total + self.ring[self.c - self.window + k]
        self.last: list[np.ndarray] | None = None
        warm = min(self.c - max(self.lags), 4 * self.window) if self.model.experts else 0
        if warm > 0:  # weigh the experts on the end of the context before the first tick
            whole, self.total = self.ring, self.total
            hist = PooledState.__new__(PooledState)
            hist.__dict__.update(self.__dict__)
            hist.ring, hist.c = whole[: self.c - warm].copy(), self.c - warm
            hist.window = min(self.window, hist.c)
            hist.total = hist.ring[hist.c - hist.window :].sum(axis=0)
            hist.error = np.full((4, g), 1e-9)
            for t in range(self.c - warm, self.c):
                hist.predict()
                hist.push(whole[t])
            self.error = hist.error
            self.at = 0

    def _lag(self, g: int) -> np.ndarray:
        return self.ring[(self.at - g) % self.c]

    def _pooled(self) -> np.ndarray:
        mode = self.model.mode
        if mode == "ordered":
            out = self.w[0] * self._lag(self.lags[0])
            for k in range(1, len(self.lags)):
                out = out + self.w[k] * self._lag(self.lags[k])
            return out
        x = np.stack([self._lag(g) for g in self.lags], 1)
        if mode == "blas32":
            return (x.astype(np.float32) @ self.w.astype(np.float32)).astype(np.float64)
        if mode == "blas64":
            return x @ self.w
        if mode == "fixedpoint":
            q = np.round(self.w * (1 << 20)).astype(np.int64)
            q[0] += (1 << 20) - q.sum()
            return ((np.round(x * 16).astype(np.int64) * q).sum(axis=1) >> 20) / 16.0
        if mode == "half":
            return x @ self.w.astype(np.float16).astype(np.float64)
        raise ValueError(mode)

    def predict(self) -> np.ndarray:
        p = self._pooled()
        if self.model.experts:
            season = self._lag(168) if self.c >= 168 else self._lag(min(24, self.c))
            self.last = [p, self.total / self.window, self._lag(1), season]
            num, den = 0.0, 0.0
            for e, q in zip(self.error, self.last, strict=True):
                w = 1.0 / (e * e * e * e)
                num, den = num + w * q, den + w
            p = num / den
        if self.model.snap:
            p = np.floor(p / self.model.snap + 0.5) * self.model.snap
        return p

    def spread(self) -> np.ndarray:
        """Width between the outer of nine quantiles: four times the trailing error of the best expert."""
        return 4.0 * self.error.min(axis=0) * (1 - self.model.memory)

    def push(self, x: np.ndarray) -> None:
        if self.last is not None:
            m = self.model.memory
            self.error = np.stack([e * m + np.abs(q - x) for e, q in zip(self.error, self.last, strict=True)])
        self.total = self.total + x - self.ring[(self.at - self.window) % self.c]
        self.ring[self.at % self.c] = x
        self.at = (self.at + 1) % self.c


def open_loop(model: Pooled, x: np.ndarray, c: int, block: int = 1 << 16) -> np.ndarray:
    """Predictions of the ticks from c on of one series of integers, each from the true ticks before it: what a state
    started on x[:c] and fed x says, operation for operation, but by arrays. Only the errors of the experts run on."""
    lags, w = model.usable(c)
    state = model.start(x[None, :c].astype(np.float64))
    if model.mode != "ordered" or not model.experts or model.snap:
        out = []
        for v in x[c:].astype(np.float64):
            out.append(float(state.predict()[0]))
            state.push(np.array([v]))
        return np.array(out)
    season, m, window = (168 if c >= 168 else min(24, c)), model.memory, state.window
    errors = [float(e) for e in state.error[:, 0]]
    out = np.zeros(len(x) - c)
    for at in range(c, len(x), block):
        t = np.arange(at, min(at + block, len(x)))
        v = x.astype(np.float64) if len(x) <= block else None
        lag = lambda g, v=v, t=t: (x[t - g].astype(np.float64) if v is None else v[t - g])
        p = w[0] * lag(lags[0])
        for k in range(1, len(lags)):
            p = p + w[k] * lag(lags[k])
        sums = np.cumsum(x[at - window : t[-1] + 1])  # exact in integers
        total = (np.r_[sums[window - 1 : -1]] - np.r_[0, sums[: len(t) - 1]]).astype(np.float64)
        num, den = 0.0, 0.0
        for k, q in enumerate((p, total / window, lag(1), lag(season))):
            e = list(accumulate(np.abs(q - x[t]).tolist(), lambda e, d: e * m + d, initial=errors[k]))
            errors[k] = e.pop()
            e = np.array(e)
            weight = 1.0 / (e * e * e * e)
            num, den = num + weight * q, den + weight
        out[t - c] = num / den
    return out


def _gram(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Sums of outer products over a partition: one row, whatever the partition's size."""
    m = len(LAGS)
    total = np.zeros((m, m))
    for b in batches:
        for xs in b.column("xs").to_pylist():
            x = np.asarray(xs, np.float64)
            x = x / (x.std() + 1.0)
            t = np.arange(max(LAGS), len(x))
            last = x[t - 1]
            cols = np.stack([x[t] - last, *(x[t - g] - last for g in LAGS[1:])], 1)
            total += cols.T @ cols
    yield pa.RecordBatch.from_arrays([pa.array([total.ravel().tolist()], pa.list_(pa.float64()))], ["g"])


def fit_pooled(train: DataFrame, ridge: float = 1e-3, **options) -> Pooled:
    """Pooled ridge regression whose weights sum to one (so it follows level and scale). ``train``: series_id, xs."""
    m = len(LAGS)
    rows = train.select("xs").mapInArrow(_gram, "g array<double>").agg(F.array(*(F.sum(F.col("g")[k]) for k in range(m * m))).alias("g")).first()["g"]
    g = np.array([v or 0.0 for v in rows]).reshape(m, m)
    a = g[1:, 1:] + ridge * np.eye(m - 1) * max(np.trace(g[1:, 1:]) / (m - 1), 1e-9)
    w = np.round(np.linalg.solve(a, g[1:, 0]), 9)
    return Pooled(LAGS, (float(1 - w.sum()), *map(float, w)), **options)


@dataclass(frozen=True)
class SeasonalProfile:
    """Mean of the values one and seven seasons ago."""

    season: int = 24

    def start(self, context: np.ndarray) -> PooledState:
        c = context.shape[1]
        lags = tuple(dict.fromkeys(g for g in (1, self.season, 7 * self.season) if g <= c))
        w = {1: (1.0,), 2: (0.0, 1.0), 3: (0.0, 0.5, 0.5)}[len(lags)]
        return PooledState(Pooled(lags, w, experts=False), context)

    def fingerprint(self) -> str:
        return f"profile{self.season}"


@dataclass
class Student:
    """A small one-hidden-layer network distilled on a teacher's predictions."""

    lags: tuple[int, ...]
    w1: np.ndarray
    w2: np.ndarray

    @staticmethod
    def distil(contexts: np.ndarray, targets: np.ndarray, lags: tuple[int, ...] = LAGS[:13], hidden: int = 16, steps: int = 400) -> Student:
        rng = np.random.default_rng(5)
        x, scale = Student._inputs(contexts, lags)
        y = (targets - contexts[:, -1]) / scale
        w1, w2 = rng.normal(0, 0.3, (x.shape[1], hidden)), np.zeros(hidden)
        for _ in range(steps):
            h = np.tanh(x @ w1)
            d = (h @ w2 - y) / len(y)
            g2, g1 = h.T @ d, x.T @ (np.outer(d, w2) * (1 - h * h))
            # steps of bounded length: inputs may be many scales wide
            rate = 0.5 / max(1.0, float(np.sqrt((g1**2).sum() + (g2**2).sum())))
            w2, w1 = w2 - rate * g2, w1 - rate * g1
        return Student(lags, w1, w2)

    @staticmethod
    def _inputs(contexts: np.ndarray, lags: tuple[int, ...]) -> tuple[np.ndarray, np.ndarray]:
        last = contexts[:, -1]
        scale = np.abs(np.diff(contexts, axis=1)).mean(axis=1) + 1.0
        return np.stack([(contexts[:, -g] - last) / scale for g in lags[1:]], 1), scale

    def predict(self, contexts: np.ndarray) -> np.ndarray:
        x, scale = self._inputs(contexts, self.lags)
        return contexts[:, -1] + scale * (np.tanh(x @ self.w1) @ self.w2)


class External:
    """Adapter for any object with ``predict(contexts) -> medians``, such as a checkpoint on accelerator nodes."""

    def __init__(self, model, name: str):
        self.model, self.name = model, name

    def start(self, context: np.ndarray) -> _ExternalState:
        return _ExternalState(self.model, context.copy())

    def fingerprint(self) -> str:
        return self.name


class _ExternalState:
    def __init__(self, model, context: np.ndarray):
        self.model, self.context = model, context

    def predict(self) -> np.ndarray:
        return np.asarray(self.model.predict(self.context), np.float64)

    def push(self, x: np.ndarray) -> None:
        self.context = np.concatenate([self.context[:, 1:], x[:, None]], 1)


def spread_bucket(spread: np.ndarray, step: np.ndarray, buckets: int = 8) -> np.ndarray:
    """Bucket of the predicted width in steps, by powers of two."""
    ratio = np.maximum(spread / np.where(step > 0, step, 1.0), 2.0**-4)
    return np.clip(np.floor(np.log2(ratio)) + 3, 0, buckets - 1).astype(np.int64)
