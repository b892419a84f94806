"""One document of each group of near-duplicates: SimHash links, widened by min-wise bands, verified by similarity.

The Gray-order index links fingerprints within two bits. Texts whose sets of five-word shingles are 0.8 similar
often differ in more bits than any exact index of 64-bit fingerprints can serve, so each text also files the bands of
a one-permutation sketch of those sets. Members of a band, and of two neighbouring bands together, are paired with
the first text, and in a band with the text before, never all with all. Whatever links is only a candidate: sketches
settle pairs whose estimate is over four standard errors away from the limit, and for the pairs between, the sets of
shingles of both texts are compared.

Defined cases: texts without words (null, empty, white space) have no sketch and are near-duplicates of nothing here
(exact dedup has merged them); of a group the row with the smallest doc_id stays, a null one first, and of rows that
tie in doc_id the first read; rows that share a doc_id, or have none, are rows of their own; very long texts are read
whole, one at a time; empty tables stay empty; other columns stay, whatever their names.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import window as W

from boundspark.llm.common import NO_ID, as_bytes, mix64, numbered, release, source, stage, without
from boundspark.llm.repeats import _gram_hash, word_hashes
from boundspark.llm.simhash import LOWER, Forest, components, fingerprint, links, routes

BINS, BANDS, WIDTH, SIMILARITY = 128, 32, 5, 0.8
EMPTY = 0xFFFFFFFF
#: Rows of one band or route that the second pass judges in one place; more are dealt into blocks that meet two by two.
#: There are at most MEETS blocks, so a row travels at most MEETS times for a band, however many rows share it; beyond
#: BLOCK * MEETS rows the blocks grow.
BLOCK, MEETS = 4096, 16
DDL = "doc_id long, fp long, sketch binary, bands array<long>, twins array<long>, size int"


def shingles(text: bytes) -> np.ndarray:
    """Sorted distinct hashes of the runs of WIDTH lower-cased words; of all words where there are fewer."""
    raw = np.frombuffer(text.translate(LOWER), np.uint8)
    _, x = word_hashes(raw, np.array([len(raw)]))
    if not len(x):
        return x
    with np.errstate(over="ignore"):
        return np.unique(mix64(_gram_hash(mix64(x), min(WIDTH, len(x)))))


def sketch(h: np.ndarray) -> np.ndarray:
    """The smallest shingle hash in each of BINS equal parts of the hash range, in 32 bits; EMPTY where there is none."""
    out = np.full(BINS, EMPTY, np.uint32)
    part = (h >> np.uint64(57)).astype(np.int64)
    first = np.flatnonzero(np.r_[True, part[1:] != part[:-1]]) if len(h) else part
    out[part[first]] = (h[first] >> np.uint64(20)).astype(np.uint32) & np.uint32(0xFFFFFFFE)
    return out


def alike(a: bytes, b: bytes) -> bool:
    """Whether two texts share SIMILARITY of their shingles."""
    return _alike(shingles(a), shingles(b))


def _alike(x: np.ndarray, y: np.ndarray) -> bool:
    both = len(np.intersect1d(x, y, assume_unique=True))
    return both > 0 and both >= SIMILARITY * (len(x) + len(y) - both) - 1e-9


def band_keys(sketches: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """For each sketch the keys of its bands, and which of the bands are not empty."""
    parts = sketches.reshape(-1, BANDS, BINS // BANDS).astype(np.uint64)
    with np.errstate(over="ignore"):
        key = np.arange(1, BANDS + 1, dtype=np.uint64) + np.zeros((len(parts), 1), np.uint64)
        for k in range(parts.shape[2]):
            key = mix64(key * np.uint64(0x9E3779B97F4A7C15) + parts[:, :, k])
    return key, (parts != EMPTY).any(axis=2)


def _rows(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for b in batches:
        fps, sketches, bands, twins, sizes = [], [], [], [], []
        for t in as_bytes(b.column(1)):
            h = shingles(t)
            s = sketch(h)
            sizes.append(len(h))
            fps.append(fingerprint(t, WIDTH))
            sketches.append(s.tobytes())
            key, full = band_keys(s)
            key = key[full]
            with np.errstate(over="ignore"):
                twins.append(mix64(key[:-1] * np.uint64(3) + key[1:]).view(np.int64).tolist())
            bands.append(key.view(np.int64).tolist())
        yield pa.RecordBatch.from_arrays([b.column(0), pa.array(np.array(fps, np.uint64).view(np.int64)), pa.array(sketches, pa.binary()), pa.array(bands, pa.list_(pa.int64())), pa.array(twins, pa.list_(pa.int64())), pa.array(sizes, pa.int32())], ["doc_id", "fp", "sketch", "bands", "twins", "size"])


def _verdict(x: np.ndarray, y: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """For rows of two arrays of sketches: whether they are not ruled out, and whether they are not proven."""
    full = ((x != EMPTY) | (y != EMPTY)).sum(axis=1)
    above = ((x == y) & (x != EMPTY)).sum(axis=1) / np.maximum(full, 1) - SIMILARITY
    margin = 4 * np.sqrt(SIMILARITY * (1 - SIMILARITY) / np.maximum(full, 1))
    return (full > 0) & (above > -margin), above < margin


def _judge(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Pairs that their sketches do not rule out; ``doubt`` where the sketches do not prove them either."""
    for batch in batches:
        read = lambda c, b=batch: np.frombuffer(b"".join(b.column(c).to_pylist()), np.uint32).reshape(-1, BINS)
        keep, doubt = map(pa.array, _verdict(read("sa"), read("sb")))
        yield pa.RecordBatch.from_arrays([batch.column("a").filter(keep), batch.column("b").filter(keep), doubt.filter(keep)], ["a", "b", "doubt"])


def _compare(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        ok = pa.array([alike(x, y) for x, y in zip(as_bytes(batch.column("ta")), as_bytes(batch.column("tb")), strict=True)], pa.bool_())
        yield pa.RecordBatch.from_arrays([batch.column("a").filter(ok), batch.column("b").filter(ok)], ["a", "b"])


def _confirm(docs: DataFrame, pairs: DataFrame) -> DataFrame:
    """The pairs (a, b) whose texts are alike. Texts are dealt once by doc_id; only those of ``pairs`` go on."""
    ends = pairs.select(F.explode(F.array("a", "b")).alias("doc_id"), "a", "b").hint("merge")
    text = lambda end: F.max(F.when(F.col("doc_id") == F.col(end), F.col("text"))).alias(f"t{end}")
    return source(docs).join(ends, "doc_id").groupBy("a", "b").agg(text("a"), text("b")).mapInArrow(_compare, "a long, b long")


def near_duplicates(docs: DataFrame) -> DataFrame:
    """(node, root): documents that have a near-duplicate with a smaller doc_id, and the smallest of their group.
    The doc_ids of ``docs`` must be unique."""
    rows = stage(source(docs).mapInArrow(_rows, DDL))
    release(docs.sparkSession)
    by_band, by_twin = (rows.select("doc_id", F.explode(k).alias("key")) for k in ("bands", "twins"))
    pairs = _pair_up(by_band, "key").union(_star(by_twin, "key", _first(by_twin, "key")))
    same_fp = rows.select("doc_id", "fp")
    firsts = same_fp.groupBy("fp").agg(F.min("doc_id").alias("first"))
    close = links(firsts.select("fp"), 2)
    f = lambda name: firsts.select(F.col("fp").alias(f"fp_{name}"), F.col("first").alias(f"id_{name}")).hint("merge")
    linked = close.join(f("a"), F.col("a") == F.col("fp_a")).join(f("b"), F.col("b") == F.col("fp_b")).select(F.least("id_a", "id_b").alias("a"), F.greatest("id_a", "id_b").alias("b"))
    wanted = stage(pairs.union(_pair_up(same_fp, "fp")).union(linked).where("a < b").distinct())
    side = lambda name: rows.select(F.col("doc_id").alias(name), F.col("sketch").alias(f"s{name}")).hint("merge")
    judged = stage(wanted.join(side("a"), "a").join(side("b"), "b").mapInArrow(_judge, "a long, b long, doubt boolean"))
    release(docs.sparkSession)
    found = stage(judged.where("NOT doubt").select("a", "b").union(_confirm(docs, judged.where("doubt").select("a", "b"))))
    release(docs.sparkSession)
    known = stage(components(found))
    release(docs.sparkSession)
    rest = stage(_between_classes(docs, rows, known))
    release(docs.sparkSession)
    return known if rest.isEmpty() else components(found.union(rest))


def _between_classes(docs: DataFrame, rows: DataFrame, known: DataFrame) -> DataFrame:
    """(a, b): smallest ids of classes that a pair of near-duplicates under one band or route joins, enough to join all."""
    classed = rows.where(F.size("bands") > 0).join(known.hint("merge"), F.col("doc_id") == F.col("node"), "left").withColumn("root", F.coalesce("root", "doc_id"))
    band = F.transform("bands", lambda k: F.struct(k.alias("key"), F.lit(False).alias("route")))
    route = F.transform(routes(2), lambda k: F.struct(k.alias("key"), F.lit(True).alias("route")))
    keyed = classed.select("doc_id", "root", F.explode(F.concat(band, route)).alias("k")).select("doc_id", "root", "k.*")
    mixed = keyed.groupBy("key").agg(F.min("root").alias("low"), F.max("root").alias("high"), F.count(F.lit(1)).alias("n")).where("low < high")
    mixed = stage(mixed.select("key", F.least(F.ceil(F.col("n") / BLOCK), F.lit(MEETS)).cast("int").alias("blocks")))
    members = keyed.join(mixed.hint("merge"), "key").withColumn("block", F.pmod(F.xxhash64("doc_id"), "blocks").cast("int"))
    # A row meets every block of its key once; a cell of two blocks is named by both.
    met = members.withColumn("other", F.explode(F.sequence(F.lit(0), F.col("blocks") - 1))).withColumn("cell", F.xxhash64("key", F.least("block", "other"), F.greatest("block", "other")))
    met = met.select("doc_id", "root", "key", "route", "cell", "block", (F.col("block") == F.col("other")).alias("within"))
    n = int(rows.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    met, sketched = met.withColumn("part", F.pmod("cell", F.lit(16 * n))), rows.select("doc_id", "sketch", "size")
    # Sketches travel first: texts go only to the cells where they leave a pair of different classes in doubt.
    sifted = stage(met.hint("merge").join(sketched, "doc_id").groupBy("part").applyInPandas(_sift_cells, "a long, b long, doc_id long, cell long, block int"))
    release(rows.sparkSession)
    open_ = sifted.where("cell IS NOT NULL").select("doc_id", "cell", "block")
    whole = met.join(open_.hint("merge"), ["doc_id", "cell", "block"], "left_semi").hint("merge").join(sketched, "doc_id").join(source(docs), "doc_id")
    return sifted.where("a IS NOT NULL").select("a", "b").union(whole.groupBy("part").applyInPandas(_judge_cells, "a long, b long"))


def _cell_pairs(pdf: pd.DataFrame) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray, np.ndarray, Forest]:
    """Pairs of rows, sorted by cell and root, that their sketches do not rule out, and whether they leave them in doubt;
    the classes of the rows, the place of each row's among them, and the forest of the classes that proven pairs join."""
    cell, root, key, route, block, within, size = (pdf[c].to_numpy() for c in ("cell", "root", "key", "route", "block", "within", "size"))
    sketches = np.frombuffer(b"".join(pdf["sketch"]), np.uint32).reshape(-1, BINS)
    keys, full = band_keys(sketches)
    live, ahead, found = np.arange(len(pdf)), 0, [(np.zeros(0, np.int64), np.zeros(0, np.int64), np.zeros(0, bool))]
    while len(live):  # each row with the row so many places ahead, while that is in its cell
        ahead += 1
        live = live[live + ahead < len(pdf)]
        live = live[cell[live] == cell[live + ahead]]
        pick = live[(root[live] != root[live + ahead]) & (within[live] | (block[live] != block[live + ahead]))]
        # sets that are alike are alike in size
        pick = pick[np.minimum(size[pick], size[pick + ahead]) >= SIMILARITY * np.maximum(size[pick], size[pick + ahead]) - 1e-9]
        for at in range(0, len(pick), 1 << 13):
            a = pick[at : at + (1 << 13)]
            keep, doubt = _verdict(sketches[a], sketches[a + ahead])
            a, doubt = a[keep], doubt[keep]
            # a pair is judged under the first band it shares, and under routes only where it shares none
            shared = (keys[a] == keys[a + ahead]) & full[a] & full[a + ahead]
            first = keys[a, shared.argmax(axis=1)].view(np.int64)
            here = np.where(shared.any(axis=1), ~route[a] & (first == key[a]), route[a])
            found.append((a[here], a[here] + ahead, doubt[here]))
    a, b, doubt = (np.concatenate([f[k] for f in found]) for k in range(3))
    classes, of = np.unique(root, return_inverse=True)
    forest = Forest(len(classes))
    forest.union(of[a[~doubt]], of[b[~doubt]])
    return a, b, doubt, classes, of, forest


def _sift_cells(pdf: pd.DataFrame) -> pd.DataFrame:
    """Ties (a, b) between classes that sketches prove, and the rows (doc_id, cell, block) that a pair in doubt has."""
    pdf = pdf.sort_values(["cell", "root", "doc_id"], ignore_index=True)
    a, b, doubt, classes, of, forest = _cell_pairs(pdf)
    top = forest.roots()
    doubt &= top[of[a]] != top[of[b]]
    tied = np.flatnonzero(top != np.arange(len(classes)))
    ties = pd.DataFrame({"a": classes[top[tied]], "b": classes[tied]}, dtype="Int64")
    rows = pdf.loc[np.unique(np.r_[a[doubt], b[doubt]]), ["doc_id", "cell", "block"]].astype({"doc_id": "Int64", "cell": "Int64", "block": "Int32"})
    return pd.concat([ties, rows], ignore_index=True)[["a", "b", "doc_id", "cell", "block"]]


def _judge_cells(pdf: pd.DataFrame) -> pd.DataFrame:
    """Ties (a, b) between classes that sketches or texts prove."""
    pdf = pdf.sort_values(["cell", "root", "doc_id"], ignore_index=True)
    a, b, doubt, classes, of, forest = _cell_pairs(pdf)
    sets: dict[int, np.ndarray] = {}
    parent = forest.roots().tolist()

    def top(x: int) -> int:
        while parent[x] != x:
            parent[x] = x = parent[parent[x]]
        return x

    def held(i: int) -> np.ndarray:
        if i not in sets:
            sets[i] = shingles(pdf["text"][i].encode())
        return sets[i]

    for i, k in zip(a[doubt].tolist(), b[doubt].tolist(), strict=True):
        x, y = top(of[i]), top(of[k])
        if x != y and _alike(held(i), held(k)):
            parent[max(x, y)] = min(x, y)
    tied = [k for k in range(len(classes)) if parent[k] != k]
    return pd.DataFrame({"a": classes[[top(k) for k in tied]], "b": classes[tied]}, dtype=np.int64)


def _first(rows: DataFrame, key: str) -> DataFrame:
    """Staged, so that joins with it are of two shuffles, of which Spark splits the skewed ones."""
    return stage(rows.groupBy(key).agg(F.min("doc_id").alias("a"), F.count(F.lit(1)).alias("n")).where("n > 1"))


def _star(rows: DataFrame, key: str, first: DataFrame) -> DataFrame:
    """(a, b): each row with the first of its key."""
    return rows.join(first.hint("merge"), key).select("a", F.col("doc_id").alias("b")).where("a < b")


def _pair_up(rows: DataFrame, key: str) -> DataFrame:
    """(a, b): each row with the first of its key, and with the row before it in its part of the key."""
    first = _first(rows, key)
    # A key may hold a third of all rows: neighbours are taken within parts of some 4096 rows, by hash.
    parts = F.ceil(F.col("n") / 4096)
    chain = rows.join(first.select(key, "n").hint("merge"), key).select(F.xxhash64(key, F.pmod(F.xxhash64("doc_id"), parts)).alias("part"), key, "doc_id")
    before = F.lag("doc_id").over(W.Window.partitionBy("part", key).orderBy("doc_id"))
    return _star(rows, key, first).union(chain.select(before.alias("a"), F.col("doc_id").alias("b")).where("a IS NOT NULL AND a < b"))


def near_dedup(docs: DataFrame) -> DataFrame:
    """The rows of ``docs`` that stay, with their columns."""
    release(docs.sparkSession)
    held, row = numbered(docs)
    ids = held.select(F.col(row).alias("node"), F.coalesce(F.col("doc_id").cast("long"), F.lit(NO_ID)).alias("id"))
    known = near_duplicates(held.select(F.col(row).alias("doc_id"), "text"))
    members = known.union(known.select("root", "root").distinct())
    named = stage(members.join(ids.hint("merge"), "node").select("root", "node", "id"))
    stays = named.groupBy("root").agg(F.min(F.struct("id", "node")).getField("node").alias("node"))
    gone = stage(named.join(stays.select("node").hint("merge"), "node", "left_anti").select("node"))
    release(docs.sparkSession)
    return without(held, row, gone)
