"""The bounded codec over groups of series, its container, and the fused study kernel of all coders.

A series is one row with its ticks as an array (``arrays``); series of one length form groups of exactly G lanes,
assigned from the dictionary of series, never from Spark's partitions, so bytes do not depend on how tasks are cut.
"""

from __future__ import annotations

import hashlib
import struct
from collections.abc import Callable

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import window as W

from boundspark.operators import entropy as E
from boundspark.operators import loops as L
from boundspark.operators.forecast import Forecaster, Pooled, spread_bucket

LPC = list(range(1, 33))
#: Predictors that need nothing but indices to decode; the index is the one-byte seed id.
SEED_PREDICTORS: tuple[tuple[str, Callable], ...] = (
    ("lorenzo1", lambda x, d: L.lorenzo(x, d, 1)),
    ("lorenzo2", lambda x, d: L.lorenzo(x, d, 2)),
    ("lorenzo3", lambda x, d: L.lorenzo(x, d, 3)),
    ("linear", lambda x, d: L.multilevel(x, d, "linear")),
    ("cubic", lambda x, d: L.multilevel(x, d, "cubic")),
)
SEED_DECODERS: tuple[Callable, ...] = (
    *(lambda k, b, d, o=o: L.lorenzo_decode(k, b, d, o) for o in (1, 2, 3)),
    *(lambda k, b, d, kind=kind: L.multilevel_decode(k, b, d, kind) for kind in ("linear", "cubic")),
)
CLASSICAL = (*(n for n, _ in SEED_PREDICTORS), "lpc32")


def arrays(series: DataFrame, chunk: int | None = None) -> DataFrame:
    """(series_id, chunk_id, n, x0, xs): one row for each series and chunk, ticks in order; duplicate ticks raise."""
    chunk_id = F.expr(f"t div {chunk}") if chunk else F.lit(0).cast("long")
    rows = series.where("x IS NOT NULL").groupBy("series_id", chunk_id.alias("chunk_id")).agg(F.array_sort(F.collect_list(F.struct("t", "x"))).alias("c"))
    ok = F.when(F.size("c") == F.size(F.array_distinct("c.t")), F.col("c.x")).otherwise(F.raise_error(F.lit("duplicate ticks in a series")))
    return rows.select("series_id", "chunk_id", F.size("c").cast("long").alias("n"), F.col("c")[0]["x"].alias("x0"), ok.alias("xs"))


#: Hash buckets in which series of one chunk and length are ranked: no window holds more than a bucket's names.
RANK_BUCKETS = 64


def grouped(rows: DataFrame, g: int) -> DataFrame:
    """Adds group_id and lane: ranks of series among those of the same chunk and length, by (hash bucket, name).

    Ranks are made of names alone; arrays join them afterwards. A group is named by (chunk_id, n, group_id).
    """
    names = rows.select("series_id", "chunk_id", "n", F.pmod(F.xxhash64("series_id"), F.lit(RANK_BUCKETS)).alias("bucket"))
    sizes = names.groupBy("chunk_id", "n", "bucket").agg(F.count(F.lit(1)).alias("size"))
    before = sizes.withColumn("before", F.sum("size").over(W.Window.partitionBy("chunk_id", "n").orderBy("bucket")) - F.col("size")).drop("size")
    nth = F.row_number().over(W.Window.partitionBy("chunk_id", "n", "bucket").orderBy("series_id")) - 1
    ranked = names.withColumn("nth", nth).join(before, ["chunk_id", "n", "bucket"]).select("series_id", "chunk_id", (F.col("before") + F.col("nth")).alias("rank"))
    out = rows.join(ranked, ["series_id", "chunk_id"]).withColumn("group_id", F.expr(f"rank div {g}")).withColumn("lane", F.pmod("rank", F.lit(g))).drop("rank")
    # Groups cost far more time than bytes: a stated number of partitions keeps them from being coalesced into one task.
    n = int(rows.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    return out.repartition(n, "chunk_id", "n", "group_id")


#: Ticks of a series that the JVM holds as one row where a kernel reads whole series.
PIECE = 1 << 14


def pieces(series: DataFrame, g: int, least: int = 1) -> DataFrame:
    """Groups of whole series, of ``least`` ticks or more, whose ticks stay in rows of PIECE until ``joined`` puts them
    together: (series_id, part, xs, chunk_id, n, group_id, lane), with the groups and lanes of ``grouped``."""
    rows = arrays(series, PIECE).select("series_id", F.col("chunk_id").alias("part"), "n", "xs")
    names = rows.groupBy("series_id").agg(F.lit(0).cast("long").alias("chunk_id"), F.sum("n").alias("n")).where(F.col("n") >= least)
    return rows.drop("n").join(grouped(names, g), "series_id")


def dealt(rows: DataFrame, *unit: str):
    """``pieces`` by group, and by unit of work within it."""
    keys = ["chunk_id", "n", "group_id", *unit]
    n = int(rows.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    return rows.repartition(4 * n if unit else n, *keys).groupBy(*keys)  # units are few and heavy: more places, fewer meetings


def joined(pdf: pd.DataFrame) -> tuple[np.ndarray, np.ndarray]:
    """Names and ticks (lanes, n) of the series of one group."""
    pdf = pdf.sort_values(["lane", "part"])
    lanes = pdf.groupby("lane", sort=True)
    x = np.empty((lanes.ngroups, int(pdf["n"].iloc[0])), np.int64)
    for row, (_, parts) in zip(x, lanes["xs"], strict=True):
        np.concatenate(list(parts), out=row)
    return lanes["series_id"].first().to_numpy(), x


def sigma(x: np.ndarray) -> np.ndarray:
    """Population deviation of each lane, from exact integers."""
    out = []
    for row in x:
        v = len(row) * sum(a * a for a in row.tolist()) - int(row.sum()) ** 2
        out.append(float(v) ** 0.5 / len(row))
    return np.array(out)


def encode_seeds(x: np.ndarray, step: np.ndarray, first: int = 0) -> tuple[np.ndarray, list[bytes], np.ndarray]:
    """Best of the five side-information-free predictors for each lane: ids, bytes, reconstructions."""
    tried = [fn(x, step) for _, fn in SEED_PREDICTORS[first:]]
    coded = [E.encode_lanes(list(k)) for k, _ in tried]
    best = np.array([min(range(len(tried)), key=lambda j: (len(coded[j][i]), j)) for i in range(len(x))])
    xhat = np.stack([tried[j][1][i] for i, j in enumerate(best)]) if len(x) else np.zeros(x.shape)
    return best + first, [coded[j][i] for i, j in enumerate(best)], xhat


def encode_group(x: np.ndarray, tau: np.ndarray, c: int, model: Forecaster) -> dict:
    """One group: seeds, lockstep body, and the reconstruction for checks."""
    step = 2 * tau
    c = min(c, x.shape[1])
    ids, seeds, seed_hat = encode_seeds(x[:, :c], step)
    k, body_hat = L.forecast_loop(x, step, seed_hat, model) if c < x.shape[1] else (np.zeros((len(x), 0), np.int64), np.zeros((len(x), 0)))
    return {"c": c, "seed_id": ids, "seed": seeds, "body": E.encode_lanes(list(k)), "k": k, "xhat": np.concatenate([seed_hat, body_hat], 1)}


def decode_group(lanes: list[dict], n: int, c: int, model: Forecaster) -> np.ndarray:
    """Reconstruct all lanes of a group (a forecaster's batch must be the encoder's batch)."""
    step = 2 * np.array([a["tau"] for a in lanes])
    base = np.array([a["x0"] for a in lanes], np.float64)
    c = min(c, n)
    seed = np.stack([SEED_DECODERS[a["seed_id"]](E.decode_lane(a["seed"], c)[None], base[i : i + 1], step[i : i + 1])[0] for i, a in enumerate(lanes)])
    if c == n:
        return seed
    k = np.stack([E.decode_lane(a["body"], n - c) for a in lanes])
    return np.concatenate([seed, L.forecast_decode(k, step, seed, model)], 1)


# Fixed value: the container's magic and version.
HEADER = struct.Struct("<4sHHHqd16s")


def header_bytes(g: int, c: int, n: int, rho: float, fingerprint: str) -> bytes:
    return HEADER.pack(b"BSPK", 1, g, c, n, rho, fingerprint.encode()[:16].ljust(16, b"\0"))


def read_header(data: bytes) -> dict:
    magic, version, g, c, n, rho, fp = HEADER.unpack(data[: HEADER.size])
    if magic != b"BSPK" or version != 1:
        raise ValueError("not a container of this version")
    return {"version": version, "g": g, "c": c, "n": n, "rho": rho, "fingerprint": fp.rstrip(b"\0").decode()}


CONTAINER = "group_id long, chunk_id long, rho double, n long, g int, c int, header binary, lanes array<struct<series_id: string, x0: long, tau: double, seed_id: int, seed: binary, body: binary, xmin: double, xmax: double, pad: boolean, xsum: double, sha256: string>>"


def encode_groups(series: DataFrame, model: Forecaster, c: int = 256, g: int = 16, rhos: tuple[float, ...] = (0.05,), chunk: int | None = None) -> DataFrame:
    """Containers: one row for each group, chunk and tolerance; the last group is padded to exactly g lanes."""

    def run(pdf: pd.DataFrame) -> pd.DataFrame:
        pdf = pdf.sort_values("lane")
        real = len(pdf)
        x = np.stack([np.asarray(v, np.int64) for v in pdf["xs"]])
        x = np.concatenate([x, np.repeat(x[:1], g - real, axis=0)]) if real < g else x
        s, out = sigma(x), []
        for rho in rhos:
            enc = encode_group(x, rho * s, c, model)
            lanes = [
                {"series_id": pdf["series_id"].iloc[min(i, real - 1)] if i < real else "", "x0": int(x[i, 0]), "tau": float(rho * s[i]), "seed_id": int(enc["seed_id"][i]), "seed": enc["seed"][i], "body": enc["body"][i], "xmin": float(enc["xhat"][i].min()), "xmax": float(enc["xhat"][i].max()), "pad": i >= real, "xsum": float(enc["xhat"][i].sum()), "sha256": digest(enc["xhat"][i])}
                for i in range(g)
            ]
            out.append((int(pdf["group_id"].iloc[0]), int(pdf["chunk_id"].iloc[0]), rho, x.shape[1], g, enc["c"], header_bytes(g, enc["c"], x.shape[1], rho, model.fingerprint()), lanes))
        return pd.DataFrame(out, columns=["group_id", "chunk_id", "rho", "n", "g", "c", "header", "lanes"])

    return grouped(arrays(series, chunk), g).groupBy("chunk_id", "n", "group_id").applyInPandas(run, CONTAINER)


def digest(xhat: np.ndarray) -> str:
    return hashlib.sha256(np.ascontiguousarray(xhat, "<f8").tobytes()).hexdigest()


def decode_groups(containers: DataFrame, model: Forecaster) -> DataFrame:
    """(series_id, rho, chunk_id, t, xhat): each container row is decoded on its own, no shuffle."""

    def run(batches):
        for pdf in batches:
            out = []
            for row in pdf.to_dict("records"):
                head = read_header(row["header"])
                if head["fingerprint"] != model.fingerprint()[:16]:
                    raise ValueError("the container was written with another forecaster")
                xhat = decode_group(list(row["lanes"]), head["n"], head["c"], model)
                for lane, r in zip(row["lanes"], xhat, strict=True):
                    if not lane["pad"]:
                        out.append(pd.DataFrame({"series_id": lane["series_id"], "rho": row["rho"], "chunk_id": row["chunk_id"], "t": np.arange(len(r)), "xhat": r, "tau": lane["tau"], "sha_ok": digest(r) == lane["sha256"]}))
            yield pd.concat(out) if out else pd.DataFrame(columns=["series_id", "rho", "chunk_id", "t", "xhat", "tau", "sha_ok"])

    return containers.mapInPandas(run, "series_id string, rho double, chunk_id long, t long, xhat double, tau double, sha_ok boolean")


def verified(decoded: DataFrame, series: DataFrame) -> DataFrame:
    """For each series: samples, their sum and largest, whether all lie within the bound, whether all bytes came back."""
    j = decoded.join(series, ["series_id", "t"])
    worst = F.max(F.abs(F.col("xhat") - F.col("x")) - F.col("tau") * (1 + 1e-9))
    return j.groupBy("series_id").agg(F.count(F.lit(1)).alias("n"), F.sum("x").alias("total"), F.max("x").alias("largest"), (worst <= 0).alias("bound_ok"), F.min("sha_ok").alias("roundtrip_ok"))


def select_best(bytes_df: DataFrame, keys: tuple[str, ...]) -> DataFrame:
    """The row of least bytes for each key; equal bytes go to the smaller predictor name."""
    return bytes_df.groupBy(*keys).agg(F.min_by("predictor", F.struct("bytes", "predictor")).alias("predictor"), F.min("bytes").alias("bytes"), F.first("n").alias("n"))


# --- the fused study kernel -----------------------------------------------------------------------------------

STUDY = "corpus string, series_id string, rho double, coder string, n long, bytes long, seed_bytes long, side_bytes long, zero_share double, xz_bytes long, zstd_bytes long, ideal_bits double, max_err_ratio double, rel_err_pct double, step double, k_abs double"


def study(series: DataFrame, corpus: str, model: Forecaster, c: int = 256, rhos: tuple[float, ...] = (0.01, 0.05, 0.2), lanes: int = 4, extra: bool = True) -> DataFrame:
    """Every coder's real bytes for each (series, tolerance): the six classical closed loops, the codec, and others.

    Samples cross into Python once; a few result rows for each series come back. Of series of more than PIECE ticks each
    coder at each tolerance is a task of its own.
    """
    coders = (*CLASSICAL, "codec")

    def run(pdf: pd.DataFrame) -> pd.DataFrame:
        series_ids, x = joined(pdf)
        unit = int(pdf["unit"].iloc[0])
        s, out = sigma(x), []
        used = rhos if unit < 0 else (rhos[unit // len(coders)],)
        wanted = coders if unit < 0 else (coders[unit % len(coders)],)
        many, n = len(used), x.shape[1]
        xs, tau = np.repeat(x, many, axis=0), (s[:, None] * np.array(used)).ravel()
        step = 2 * tau
        names = np.repeat(series_ids, many)
        results = {name: fn(xs, step) for name, fn in SEED_PREDICTORS if name in wanted}
        if "lpc32" in wanted:
            coefs = np.repeat(np.stack([L.fit_lags(r.astype(np.float64), LPC) for r in x]), many, axis=0)
            results["lpc32"] = L.lags_closed_loop(xs, step, LPC, coefs)
        if "codec" in wanted:
            ids, seeds, seed_hat = encode_seeds(xs[:, : min(c, n - 1)], step)
            k, hat = L.forecast_loop(xs, step, seed_hat, model)
            results["codec"] = (k, np.concatenate([seed_hat, hat], 1))
        keys = list(results)
        coded = E.encode_lanes([k for key in keys for k in results[key][0]])
        sizes = dict(zip(keys, np.array(list(map(len, coded))).reshape(len(keys), -1), strict=True))
        mean = np.abs(xs).mean(axis=1)
        for key in keys:
            ks, xhat = results[key]
            for i in range(len(xs)):
                err = float(np.abs(xhat[i] - xs[i]).max())
                seed = len(seeds[i]) if key == "codec" else 0
                row = (corpus, names[i], used[i % many], key, n, int(sizes[key][i]) + seed, seed, 4 * len(LPC) if key == "lpc32" else 9 if key == "codec" else 8, float((ks[i] == 0).mean()) if ks.shape[1] else 1.0)
                more = (E.generic_size(ks[i], "xz"), E.generic_size(ks[i], "zstd"), E.empirical_bits(ks[i], E.contexts(ks[i])) * len(ks[i]) + 8.0 * seed) if extra else (0, 0, 0.0)
                out.append((*row, more[0] + seed, more[1] + seed, more[2], err / tau[i] if tau[i] else err, 100 * float(tau[i]) / mean[i] if mean[i] else 0.0, float(step[i]), float(np.abs(ks[i]).mean()) if ks.shape[1] else 0.0))
        return pd.DataFrame(out, columns=[f.split()[0] for f in STUDY.split(", ")])

    units = F.when(F.col("n") > PIECE, F.sequence(F.lit(0), F.lit(len(rhos) * len(coders) - 1))).otherwise(F.array(F.lit(-1)))
    return dealt(pieces(series, lanes, 2).withColumn("unit", F.explode(units)), "unit").applyInPandas(run, STUDY)


__all__ = ["Pooled", "arrays", "decode_groups", "encode_groups", "select_best", "spread_bucket", "study"]
