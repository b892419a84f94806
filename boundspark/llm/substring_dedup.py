"""Substring dedup on words with suffix automata of reference shards.

A word goes if a window of ``length`` words that covers it also starts anywhere else. The anchor rounds of
``repeats`` leave contexts of recurring anchors; they are dealt to shards by anchor, and each shard's automaton is
built from its own contexts (the reference) and ships with them to one task, where the same contexts stream through
it: matching statistics give, at every word, the state of the longest match, and a window is matched when the state
that holds its words has two or more occurrences. Maximal spans of matched windows are removed.

The automata are not broadcast to all tasks: all shards together grow with the corpus, so only routing keeps what a
task holds bounded. A context's words carry their distance from the anchor, so that one place seen from two anchors
is not taken for two places.

Defined cases: a null text has no words; texts of fewer than ``length`` words keep them all; repeated rows are other
places and so lose all their windows; a null doc_id is shown as null; an empty table gives an empty result; extra
columns are ignored; very long texts are worked on in overlapping pieces and joined
again; a word longer than a piece makes the piece longer.
"""

from __future__ import annotations

import hashlib

import numpy as np
from pyspark.sql import DataFrame, SparkSession

from boundspark.llm.common import mix64, shown, table
from boundspark.llm.repeats import Contexts, Layout, linear_hash, remove_repeats

LENGTH = 35


def layout(length: int = LENGTH) -> Layout:
    return Layout(length=length, k=max(3, length * 12 // 35), kind="words", rule="again")


class SuffixAutomaton:
    """Of several sequences, with a weight for each; states know their longest word, suffix link and occurrences."""

    def __init__(self) -> None:
        self.next: list[dict[int, int]] = [{}]
        self.link, self.size, self.weight = [-1], [0], [0]

    def add(self, sequence: list[int], weight: int) -> None:
        last = 0
        nxt, link, size = self.next, self.link, self.size
        for symbol in sequence:
            known = nxt[last].get(symbol)
            if known is not None and size[known] == size[last] + 1:
                last = known
            elif known is not None:
                last = self._clone(last, known, symbol)
            else:
                state = self._state(size[last] + 1)
                p = last
                while p >= 0 and symbol not in nxt[p]:
                    nxt[p][symbol] = state
                    p = link[p]
                if p < 0:
                    link[state] = 0
                else:
                    q = nxt[p][symbol]
                    link[state] = q if size[q] == size[p] + 1 else self._clone(p, q, symbol)
                last = state
            self.weight[last] += weight

    def _state(self, size: int) -> int:
        self.next.append({})
        self.link.append(-1)
        self.size.append(size)
        self.weight.append(0)
        return len(self.size) - 1

    def _clone(self, p: int, q: int, symbol: int) -> int:
        twin = self._state(self.size[p] + 1)
        self.next[twin] = dict(self.next[q])
        self.link[twin] = self.link[q]
        self.link[q] = twin
        while p >= 0 and self.next[p].get(symbol) == q:
            self.next[p][symbol] = twin
            p = self.link[p]
        return twin

    def finish(self) -> None:
        """Add up occurrences over suffix links, longest states first."""
        for state in sorted(range(1, len(self.size)), key=self.size.__getitem__, reverse=True):
            if self.link[state] > 0:
                self.weight[self.link[state]] += self.weight[state]

    def stream(self, sequence: list[int], length: int) -> list[int]:
        """For each position the occurrences of the ``length`` symbols that end there; 0 where there is no match."""
        out, state, held = [], 0, 0
        nxt, link, size = self.next, self.link, self.size
        for symbol in sequence:
            while state and symbol not in nxt[state]:
                state = link[state]
                held = size[state]
            to = nxt[state].get(symbol)
            if to is None:
                state = held = 0
            else:
                state, held = to, held + 1
            while held > length and size[link[state]] >= length:  # the shortest match that is long enough
                state = link[state]
                held = size[state]
            out.append(self.weight[state] if held >= length else 0)
        return out


def _extents(lay: Layout, ctx: Contexts, group: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """Columns [from, to) around the anchor that each context shares with another of its group, and a hash for each side.

    Every window holds the anchor, so a window that another context holds too lies within what is shared to the left
    and to the right of it. Hashes only ever let too much through; the automaton decides.
    """
    n = len(group)
    anchor = linear_hash(ctx.rows[:, lay.left : lay.left + lay.k], 21) ^ mix64(group.astype(np.uint64))
    edges, sides = [np.full(n, lay.left), np.full(n, lay.left + lay.k)], [anchor, anchor.copy()]
    # A context's elements are known from lay.left - high to lay.left + length - low.
    known = [ctx.high.astype(np.int64), lay.length - ctx.low.astype(np.int64) - lay.k]
    for side, (columns, step) in enumerate(((range(lay.left - 1, -1, -1), -1), (range(lay.left + lay.k, lay.span), 1))):
        active = np.arange(n)
        for done, j in enumerate(columns):
            active = active[known[side][active] > done]
            with np.errstate(over="ignore"):
                h = mix64(sides[side][active] * np.uint64(0x9E3779B97F4A7C15) + ctx.rows[active, j])
            order = np.argsort(h)
            same = h[order][1:] == h[order][:-1]
            both = order[np.r_[False, same] | np.r_[same, False]] if len(h) else order
            active = active[both]
            if not len(active):
                break
            sides[side][active] = h[both]
            edges[side][active] += step
    return edges[0], edges[1], sides[0], sides[1]


def shard_automata(lay: Layout, ctx: Contexts) -> np.ndarray:
    """For each context the set of its windows (bit: offset) that other contexts hold too.

    What reaches the automata is the shared part of each context; equal parts are one sequence with their total weight.
    """
    out = np.zeros(len(ctx.h), np.uint64)
    group = np.cumsum(np.r_[False, ctx.h[1:] != ctx.h[:-1]])
    start, stop, left, right = _extents(lay, ctx, group)
    order = np.lexsort((stop, start, right, left, group))
    order = order[(stop - start)[order] >= lay.length]
    if not len(order):
        return out
    keys = [x[order] for x in (group, left, right, start, stop)]
    change = np.zeros(len(order), bool)
    for x in keys:
        change[1:] |= x[1:] != x[:-1]
    first, part = np.flatnonzero(np.r_[True, change[1:]]), np.cumsum(change)
    weight = np.add.reduceat(ctx.v[order], first).tolist()
    one = order[first]
    with np.errstate(over="ignore"):
        column = mix64(np.arange(1, lay.span + 1, dtype=np.uint64) * np.uint64(0x9E3779B97F4A7C15))
    begins, ends, masks = start[one].tolist(), stop[one].tolist(), np.zeros(len(one), np.uint64)
    edges = np.r_[np.flatnonzero(np.r_[True, group[one][1:] != group[one][:-1]]), len(one)].tolist()
    for a, b in zip(edges[:-1], edges[1:], strict=True):
        automaton, texts = SuffixAutomaton(), []
        symbols = ctx.rows[one[a:b]] ^ column
        for k in range(a, b):
            texts.append(symbols[k - a, begins[k] : ends[k]].tolist())
            automaton.add(texts[-1], weight[k])
        automaton.finish()
        for k, text in zip(range(a, b), texts, strict=True):
            seen, mask = automaton.stream(text, lay.length), 0
            for end in range(lay.length - 1, len(text)):
                if seen[end] > 1:
                    mask |= 1 << (lay.left - (begins[k] + end - lay.length + 1))
            masks[k] = mask
    out[order] = masks[part]
    return out


class Digest:
    """n_words, n_removed and the digest of the words that are left of one document."""

    def __init__(self) -> None:
        self.n = self.removed = 0
        self.kept = hashlib.sha256()

    def add(self, text: bytes, gone: np.ndarray) -> None:
        left, n = _left(text, gone), int(gone.sum())
        if left and self.n > self.removed:
            self.kept.update(b" ")
        self.kept.update(b" ".join(left))
        self.n, self.removed = self.n + len(gone), self.removed + n

    def row(self) -> tuple:
        return self.n, self.removed, self.kept.hexdigest()


class Remainder:
    def __init__(self) -> None:
        self.words: list[bytes] = []

    def add(self, text: bytes, gone: np.ndarray) -> None:
        self.words += _left(text, gone)

    def row(self) -> tuple:
        return (b" ".join(self.words).decode("utf-8", errors="replace"),)


def _left(text: bytes, gone: np.ndarray) -> list[bytes]:
    words = text.split()
    return [w for w, x in zip(words, gone.tolist(), strict=True) if not x] if gone.any() else words


def substring_dedup(docs: DataFrame, length: int = LENGTH, **cols) -> DataFrame:
    """doc_id, n_words, n_removed, kept_sha256 for each document."""
    out = remove_repeats(docs, layout(length), shard_automata, Digest, "doc_id long, n_words long, n_removed long, kept_sha256 string", **cols)
    return out.select(shown("doc_id"), *out.columns[1:])


def substring_dedup_texts(docs: DataFrame, length: int = LENGTH, **cols) -> DataFrame:
    """doc_id and the words that are left, joined by single spaces."""
    return remove_repeats(docs, layout(length), shard_automata, Remainder, "doc_id long, text string", **cols)


def op4_suffix_automata(spark: SparkSession, sf_dir: str) -> DataFrame:
    return substring_dedup(table(spark, sf_dir, "documents"))


ORACLE: dict[str, str] = {}
