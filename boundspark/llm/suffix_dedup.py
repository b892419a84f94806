"""Substring dedup on bytes by suffix arrays built block by block with a difference cover.

A byte goes if a string of ``length`` bytes that covers it also starts in a document with a smaller id. Which
suffixes can match at all is settled by the anchor rounds of ``repeats``; the suffixes that remain are sorted here,
one suffix bucket (one anchor group's suffixes at one alignment) at a time. A bucket is sorted by the few bytes up to
the next sample of the difference cover; ties longer than that are settled by the sample's rank, which was computed
once for the block, so no suffix is ever held or compared at full length while sorting. Neighbours whose common
prefix reaches ``length`` form runs, and the smallest document of a run decides.

Defined cases: a null text has no bytes; texts shorter than ``length`` keep all their bytes; rows with equal doc_id
are no earlier than one another; a null doc_id is earlier than all others; an empty table gives an empty result;
extra columns are ignored; very long texts are worked on in overlapping pieces and joined again.
"""

from __future__ import annotations

import hashlib

import numpy as np
from pyspark.sql import DataFrame, SparkSession

from boundspark.llm.common import shown, table
from boundspark.llm.repeats import Contexts, Layout, remove_repeats

LENGTH = 50
PERIOD = 31
# A perfect difference cover modulo 31.
COVER = (1, 5, 11, 24, 25, 27)


def layout(length: int = LENGTH) -> Layout:
    return Layout(length=length, k=max(4, length * 24 // 50), kind="bytes", rule="earlier")


def sample_ranks(rows: np.ndarray) -> dict[int, np.ndarray]:
    """Ranks of the suffixes at cover positions, comparable across positions: by PERIOD bytes, then by doubling."""
    width = rows.shape[1]
    positions = [p for p in range(width) if p % PERIOD in COVER]
    padded = np.zeros((len(rows), width + PERIOD + 1), np.uint8)
    padded[:, :width] = rows
    heads = np.concatenate([padded[:, p : p + PERIOD + 1] for p in positions])
    heads[:, PERIOD] = 0
    words = np.ascontiguousarray(heads).view(">u8").astype(np.uint64)
    rank = _dense(*(words[:, k] for k in range(words.shape[1]))).reshape(len(positions), len(rows))
    at, step = {p: k for k, p in enumerate(positions)}, PERIOD
    while step < width:
        nxt = np.full_like(rank, -1)
        for p, k in at.items():
            if p + step in at:
                nxt[k] = rank[at[p + step]]
        rank = _dense(rank.ravel(), nxt.ravel()).reshape(rank.shape)
        step *= 2
    return {p: rank[k] for p, k in at.items()}


def _dense(*keys: np.ndarray) -> np.ndarray:
    """Dense rank of rows by several keys."""
    order = np.lexsort(keys[::-1])
    change = np.zeros(len(order), bool)
    for k in keys:
        s = k[order]
        change[1:] |= s[1:] != s[:-1]
    out = np.empty(len(order), np.int64)
    out[order] = np.cumsum(change)
    return out


def suffix_blocks(lay: Layout, ctx: Contexts) -> np.ndarray:
    """For each context the set of its windows (bit: offset) that some other context with a smaller value holds."""
    out = np.zeros(len(ctx.h), np.uint64)
    group = np.cumsum(np.r_[False, ctx.h[1:] != ctx.h[:-1]])
    # Whole groups, about a block's worth of contexts at a time.
    edges = np.searchsorted(group, np.arange(0, int(group[-1]) + 2))
    start = 0
    while start < len(edges) - 1:
        stop = int(np.searchsorted(edges, edges[start] + 20_000, "right"))
        stop = min(max(stop - 1, start + 1), len(edges) - 1)
        a, b = int(edges[start]), int(edges[stop])
        out[a:b] = _one_block(lay, ctx.rows[a:b], group[a:b], ctx.v[a:b], ctx.low[a:b], ctx.high[a:b])
        start = stop
    return out


def _one_block(lay: Layout, rows: np.ndarray, group: np.ndarray, value: np.ndarray, low: np.ndarray, high: np.ndarray) -> np.ndarray:
    ranks, out = sample_ranks(rows), np.zeros(len(rows), np.uint64)
    for offset in range(lay.left + 1):
        mine = np.flatnonzero((low <= offset) & (offset <= high))
        if len(mine) < 2:
            continue
        at = lay.left - offset
        delta = next(d for d in range(PERIOD) if at + d in ranks)
        keys = [ranks[at + delta][mine]]
        for k in range(at + delta, at, -8):  # bytes before the sample, eight to a key, last first
            lead = rows[mine, max(at, k - 8) : k].astype(np.uint64)
            keys.append((lead << (np.arange(lead.shape[1])[::-1] * 8).astype(np.uint64)).sum(axis=1, dtype=np.uint64))
        order = np.lexsort((*keys, group[mine]))
        s = mine[order]
        text = rows[s, at : at + lay.length]
        same = (group[s][1:] == group[s][:-1]) & (text[1:] == text[:-1]).all(axis=1)
        first = np.flatnonzero(np.r_[True, ~same])
        least = np.repeat(np.minimum.reduceat(value[s], first), np.diff(np.r_[first, len(s)]))
        out[s[value[s] > least]] |= np.uint64(1 << offset)
    return out


class Digest:
    """n_bytes, n_removed, n_spans and the digest of what is left of one document."""

    def __init__(self) -> None:
        self.n = self.removed = self.spans = 0
        self.inside, self.kept = False, hashlib.sha256()

    def add(self, text: bytes, gone: np.ndarray) -> None:
        n = int(gone.sum())
        self.n += len(text)
        self.removed += n
        if n:
            self.spans += int(gone[0] and not self.inside) + int((gone[1:] > gone[:-1]).sum())
            text = np.frombuffer(text, np.uint8)[~gone].tobytes()
        if len(gone):
            self.inside = bool(gone[-1])
        self.kept.update(text)

    def row(self) -> tuple:
        return self.n, self.removed, self.spans, self.kept.hexdigest()


class Remainder:
    """Text without removed bytes; a character that is only partly removed stays whole."""

    def __init__(self) -> None:
        self.parts: list[bytes] = []

    def add(self, text: bytes, gone: np.ndarray) -> None:
        if gone.any():
            raw = np.frombuffer(text, np.uint8)
            char = np.cumsum((raw & 0xC0) != 0x80)
            whole = np.ones(int(char[-1]) + 1, bool)
            whole[char[~gone]] = False
            text = raw[~whole[char]].tobytes()
        self.parts.append(text)

    def row(self) -> tuple:
        return (b"".join(self.parts).decode("utf-8", errors="replace"),)


def suffix_dedup(docs: DataFrame, length: int = LENGTH, **cols) -> DataFrame:
    """doc_id, n_bytes, n_removed, n_spans, kept_sha256 for each document."""
    out = remove_repeats(docs, layout(length), suffix_blocks, Digest, "doc_id long, n_bytes long, n_removed long, n_spans long, kept_sha256 string", **cols)
    return out.select(shown("doc_id"), *out.columns[1:])


def suffix_dedup_texts(docs: DataFrame, row_col: str, length: int = LENGTH, **cols) -> DataFrame:
    """The number in ``row_col``, under that name, and the text that is left, as ``text_left``."""
    out = remove_repeats(docs, layout(length), suffix_blocks, Remainder, "row_number long, text_left string", row_col, **cols)
    return out.withColumnRenamed("row_number", row_col)


def op3_difference_cover(spark: SparkSession, sf_dir: str) -> DataFrame:
    return suffix_dedup(table(spark, sf_dir, "documents"))


ORACLE: dict[str, str] = {}
