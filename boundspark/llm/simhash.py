"""SimHash near-dedup with a Gray-order hierarchical index.

Fingerprints of whole texts are linked when few bits differ. Distinct fingerprints are routed by the bits of all but
``radius`` of their blocks (with radius + 2 blocks, two that link agree in at least two blocks, so a route is the
value of one pair of blocks). Inside a route they are sorted by Gray rank and indexed as a hierarchy: bytes that a
whole group shares are factored into the upper node, groups are compared by their shared bytes alone, and a pair of
groups whose accumulated differences exceed the radius is pruned with everything below. The links of a route leave
it as a spanning forest, never as all pairs; components come from rounds of label contraction with staged tables.

Defined cases: a null or wordless text has fingerprint zero and links like any other; texts of fewer words than a
shingle are one shingle; a bit set in exactly half of the shingles is 0; repeated rows and equal fingerprints share
a component; a null doc_id is shown as null and sorts first; an empty table gives an empty result; extra columns are
ignored; very long texts are read whole.
"""

from __future__ import annotations

from collections.abc import Iterator
from itertools import combinations

import numpy as np
import pandas as pd
import pyarrow as pa
import xxhash
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from boundspark.llm.common import NO_ID, as_bytes, shown, source, stage, table

SEED = 42
LOWER = bytes(c + 32 if 65 <= c <= 90 else c for c in range(256))


def fingerprint(text: bytes, width: int = 3) -> int:
    words = text.translate(LOWER).split()
    if not words:
        return 0
    if len(words) <= width:
        shingles = [b" ".join(words)]
    else:
        shingles = [b" ".join(s) for s in zip(*(words[k:] for k in range(width)), strict=False)]
    digest = xxhash.xxh64_intdigest
    h = np.array([digest(s, SEED) for s in shingles], "<u8")
    votes = np.unpackbits(h.view(np.uint8).reshape(-1, 8), axis=1, bitorder="little").sum(axis=0, dtype=np.int64)
    return int(np.packbits(2 * votes > len(h), bitorder="little").view("<u8")[0])


def fingerprints(docs: DataFrame, width: int = 3) -> DataFrame:
    """(doc_id, fp): fp as a signed 64-bit integer."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            fps = np.array([fingerprint(t, width) for t in as_bytes(b.column(1))], np.uint64).view(np.int64)
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array(fps)], ["doc_id", "fp"])

    return source(docs).mapInArrow(run, "doc_id long, fp long")


def gray_rank(x: np.ndarray) -> np.ndarray:
    """Position of each 64-bit pattern in the reflected Gray sequence."""
    for s in (1, 2, 4, 8, 16, 32):
        x = x ^ (x >> np.uint64(s))
    return x


class GrayIndex:
    """Patterns of many routes in one hierarchy: level 0 is a route, level k adds the k-th byte of the pattern.

    Sorting by (route, Gray rank) keeps every shared leading bit pattern contiguous, so a node is a range of rows.
    """

    BYTES = 8

    def __init__(self, route: np.ndarray, patterns: np.ndarray):
        self.order = np.lexsort((gray_rank(patterns), route))
        self.patterns = patterns[self.order]
        self.digits = self.patterns.astype(">u8").view(np.uint8).reshape(-1, self.BYTES)
        route = route[self.order]
        n = len(route)
        new = np.r_[True, route[1:] != route[:-1]] if n else np.zeros(0, bool)
        self.starts = [np.flatnonzero(new)]  # first row of each node, level by level
        for k in range(self.BYTES):
            new = new | np.r_[True, self.digits[1:, k] != self.digits[:-1, k]] if n else new
            self.starts.append(np.flatnonzero(new))
        self.size = n

    def children(self, level: int) -> tuple[np.ndarray, np.ndarray]:
        """For each node of a level: its first child and its number of children."""
        first = np.searchsorted(self.starts[level + 1], self.starts[level])
        return first, np.diff(np.r_[first, len(self.starts[level + 1])])

    def links(self, radius: int) -> Iterator[tuple[np.ndarray, np.ndarray]]:
        """Pairs of rows (in the caller's numbering) of one route that differ in at most ``radius`` bits."""
        todo = [(0, np.arange(len(self.starts[0])), np.arange(len(self.starts[0])), np.zeros(len(self.starts[0]), np.int64))]
        while todo:
            level, a, b, diff = todo.pop()
            if not len(a):
                continue
            if level == self.BYTES:
                apart = a != b
                yield self.order[self.starts[level][a[apart]]], self.order[self.starts[level][b[apart]]]
                continue
            first, many = self.children(level)
            if len(a) > 1 and int((many[a] * many[b]).sum()) > 1 << 20:  # bound the frontier: depth first over halves
                half = len(a) // 2
                todo += [(level, a[:half], b[:half], diff[:half]), (level, a[half:], b[half:], diff[half:])]
                continue
            count = many[a] * many[b]
            pair = np.repeat(np.arange(len(a)), count)
            within = np.arange(len(pair)) - np.repeat(np.cumsum(count) - count, count)
            ca, cb = first[a][pair] + within // many[b][pair], first[b][pair] + within % many[b][pair]
            digit = self.digits[self.starts[level + 1], level]
            far = diff[pair] + np.bitwise_count(digit[ca] ^ digit[cb])
            near = (far <= radius) & (ca <= cb)
            todo.append((level + 1, ca[near], cb[near], far[near]))


class Forest:
    """Union-find over rows; links come in arrays, roots are smallest rows."""

    def __init__(self, n: int):
        self.parent = np.arange(n)

    def roots(self) -> np.ndarray:
        p = self.parent
        while True:
            q = p[p]
            if np.array_equal(p, q):
                self.parent = p
                return p
            p = q

    def union(self, a: np.ndarray, b: np.ndarray) -> None:
        while len(a):
            p = self.roots()
            ra, rb = p[a], p[b]
            open_ = ra != rb
            a, b, ra, rb = a[open_], b[open_], ra[open_], rb[open_]
            np.minimum.at(self.parent, np.maximum(ra, rb), np.minimum(ra, rb))


def block_edges(radius: int) -> list[int]:
    """Bit positions that split 64 bits into radius + 2 blocks."""
    n = radius + 2
    return [64 * k // n for k in range(n + 1)]


def _route_links(radius: int):
    """Spanning links of one group of routes; the rows of a group are distinct fingerprints of a few routes."""

    def run(pdf: pd.DataFrame) -> pd.DataFrame:
        fps = pdf["fp"].to_numpy(np.int64).view(np.uint64)
        route = np.unique(pdf["route"].to_numpy(np.int64), return_inverse=True)[1]
        forest = Forest(len(fps))
        for a, b in GrayIndex(route, fps).links(radius):
            forest.union(a, b)
        root = forest.roots()
        tied = np.flatnonzero(root != np.arange(len(fps)))
        signed = fps.view(np.int64)
        return pd.DataFrame({"a": signed[tied], "b": signed[root[tied]]})

    return run


def routes(radius: int = 2) -> Column:
    """The routes of a row's fp; rows whose fps differ in at most ``radius`` bits share one."""
    edges, out = block_edges(radius), []
    for no, (i, j) in enumerate(combinations(range(radius + 2), 2)):
        mask = sum(((1 << edges[k + 1]) - 1) ^ ((1 << edges[k]) - 1) for k in (i, j))
        mask = mask - (1 << 64) if mask >> 63 else mask
        out.append(F.xxhash64(F.lit(no), F.col("fp").bitwiseAND(F.lit(mask).cast("long"))))
    return F.array(*out)


def links(distinct: DataFrame, radius: int = 2) -> DataFrame:
    """(a, b) fingerprint links whose closure is the closure of all links within ``radius`` bits."""
    routed = distinct.select("fp", F.explode(routes(radius)).alias("route"))
    # A route alone links nothing; counting routes first spares the kernel and most of the exchange.
    busy = routed.groupBy("route").agg(F.count(F.lit(1)).alias("n")).where("n > 1").select("route")
    n = int(distinct.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    grouped = routed.join(busy.hint("merge"), "route", "left_semi").withColumn("part", F.pmod("route", F.lit(16 * n)))
    return grouped.groupBy("part").applyInPandas(_route_links(radius), "a long, b long")


#: Edges among which one task may meet all neighbours of a node; among more, they meet in SALTS places.
ONE_PLACE, SALTS = 1_000_000, 64


def _with_least(edges: DataFrame, itself: bool, spread: bool) -> DataFrame:
    """(a, b, m): each edge with the smallest neighbour of a, or a ``itself`` where that is smaller.

    A node may have very many neighbours: where ``spread`` they meet in SALTS places, which alone meet in one.
    """
    least = lambda e: e.groupBy("a").agg(F.min("m").alias("m")).select("a", (F.least("a", "m") if itself else F.col("m")).alias("m"))
    if not spread:
        return edges.join(least(edges.withColumnRenamed("b", "m")).hint("merge"), "a")
    e = edges.withColumn("salt", F.pmod(F.xxhash64("b"), F.lit(SALTS)))
    part = e.groupBy("a", "salt").agg(F.min("b").alias("m"))
    return e.join(part.select("a", "salt").join(least(part).hint("merge"), "a").hint("merge"), ["a", "salt"]).select("a", "b", "m")


def components(edges: DataFrame) -> DataFrame:
    """(node, root) for every node of ``edges`` (a, b): alternating large-star and small-star rounds."""
    both = lambda e: e.union(e.select("b", "a"))
    e = stage(edges.where("a <> b").distinct())
    while True:
        spread = e.count() > ONE_PLACE
        # large star: every larger neighbour of a node is tied to the node's smallest neighbour
        large = _with_least(both(e), True, spread).where("b > a").select(F.col("b").alias("a"), F.col("m").alias("b")).where("a <> b").distinct()
        # small star: a node and its smaller neighbours are tied to the smallest of them
        down = large.select(F.greatest("a", "b").alias("a"), F.least("a", "b").alias("b"))
        small = _with_least(down, False, spread).select(F.when(F.col("b") == F.col("m"), F.col("a")).otherwise(F.col("b")).alias("a"), F.col("m").alias("b")).where("a <> b").distinct()
        nxt = stage(small)
        # done when every node has one tie and ties end in roots; a node tied to two roots still has to join them
        tops = nxt.select(F.col("b").alias("a")).distinct()
        split = nxt.groupBy("a").agg(F.count(F.lit(1)).alias("n")).where("n > 1")
        if nxt.join(tops.hint("merge"), "a", "left_semi").isEmpty() and split.isEmpty():
            return nxt.select(F.col("a").alias("node"), F.col("b").alias("root"))
        e = nxt


def simhash_dedup(docs: DataFrame, width: int = 3, radius: int = 2) -> DataFrame:
    """doc_id, fingerprint (16 hex digits), component_id (smallest doc_id reachable through links)."""
    fps = stage(fingerprints(docs, width))
    distinct = stage(fps.groupBy("fp").agg(F.min("doc_id").alias("first_id")))
    root = components(links(distinct.select("fp"), radius))
    named = distinct.join(root.withColumnRenamed("node", "fp").hint("merge"), "fp", "left").withColumn("root", F.coalesce("root", "fp"))
    smallest = named.groupBy("root").agg(F.min("first_id").alias("component_id"))
    # Staged, so that the last join is of two shuffles: Spark splits a fingerprint that very many rows share.
    labels = stage(named.select("fp", "root").join(smallest.hint("merge"), "root").select("fp", "component_id"))
    out = fps.join(labels.hint("merge"), "fp")
    return out.select(shown("doc_id"), F.lower(F.lpad(F.hex("fp"), 16, "0")).alias("fingerprint"), shown("component_id"))


def op2_gray_simhash(spark: SparkSession, sf_dir: str) -> DataFrame:
    return simhash_dedup(table(spark, sf_dir, "documents"))


ORACLE: dict[str, str] = {}
__all__ = ["NO_ID", "components", "fingerprint", "fingerprints", "links", "simhash_dedup"]
