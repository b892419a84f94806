"""Exact dedup with a log-structured merge index of text digests.

Each task drives a ``DigestIndex``: rows enter a memtable, where a digest that is hit again is verified on its bytes at
once; a full memtable is flushed as a sorted run, its texts to a value log; several runs are compacted into one, with
a filter of four bytes a digest. Runs are staged beside their logs and stay there. Between tasks the filters travel
first; digests that no other run's filter can hold take no further part, the others are merged one digest range at a
time and keep the smallest identifier. Digests that several memtables hold are verified on the bytes in their logs.

Defined cases: a null text counts as empty, and empty texts equal one another; a text of white space only equals
any other such text, not the empty one; repeated rows are copies; very long texts fill a memtable of their own; ties
in doc_id keep that doc_id, and the smallest row number where rows are numbered; a null doc_id sorts first; an empty
table gives an empty result; extra columns are ignored.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pandas as pd
import pyarrow as pa
import zstandard
from pyspark import TaskContext
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from boundspark.llm.common import NO_ID, as_bytes, fan_out, is_blank_edge, release, shown, stage, stage_by, table

MEMTABLE_BYTES, MEMTABLE_ROWS = 16 << 20, 100_000
#: Runs of one index that are compacted into one before it is staged.
RUNS = 4
RANGE_BYTES = 96 << 20
MAX_LAYOUT = 50_000
SALTS = 64
SPACE_CLASS = "[\\x20\\x09-\\x0D]+"


def normalise(text: bytes) -> bytes:
    """Every run of ASCII white space becomes one space, edges included."""
    head, tail = is_blank_edge(text)
    words = text.split()
    if not words:
        return b" " if text else b""
    return (b" " if head else b"") + b" ".join(words) + (b" " if tail else b"")


@dataclass
class Run:
    """An immutable sorted run: distinct digests, the smallest (id, row) and the count of each, and in how many
    memtables it was."""

    digests: np.ndarray
    keep: np.ndarray
    keep_row: np.ndarray
    count: np.ndarray
    tables: np.ndarray

    FIELDS = ("digests", "keep", "keep_row", "count", "tables")

    def slots(self) -> np.ndarray:
        """The filter: bytes 4 to 7 of each digest; the leading bytes choose the range."""
        return np.ascontiguousarray(self.digests.view(np.uint8).reshape(-1, 32)[:, 4:8]).view(">u4")[:, 0].astype(np.uint32)

    def part(self, at) -> Run:
        return Run(*(getattr(self, f)[at] for f in Run.FIELDS))


def compact(runs: list[Run]) -> Run:
    """Merge runs into one; only digests that two filters may share take part in the merge proper."""
    if not runs:
        return Run(np.zeros(0, "S32"), *(np.zeros(0, np.int64) for _ in range(4)))
    slots = [r.slots() for r in runs]
    shared = shared_slots([np.unique(s) for s in slots])
    among = [np.isin(s, shared) for s in slots]
    join = lambda f, masks: np.concatenate([getattr(r, f)[m] for r, m in zip(runs, masks, strict=True)])
    merged = _fold(Run(*(join(f, among) for f in Run.FIELDS)))
    alone = [~m for m in among]
    out = Run(*(np.concatenate([join(f, alone), getattr(merged, f)]) for f in Run.FIELDS))
    return out.part(np.argsort(out.digests, kind="stable"))


def shared_slots(filters: list[np.ndarray]) -> np.ndarray:
    """Slots that two or more filters hold."""
    every = np.sort(np.concatenate(filters))
    return np.unique(every[1:][every[1:] == every[:-1]])


def _fold(r: Run) -> Run:
    """Sort and fold equal digests: smallest (id, row), summed counts."""
    if not len(r.keep):
        return r
    r = r.part(np.lexsort((r.keep_row, r.keep, r.digests)))
    first = np.flatnonzero(np.r_[True, r.digests[1:] != r.digests[:-1]])
    return Run(r.digests[first], r.keep[first], r.keep_row[first], np.add.reduceat(r.count, first), np.add.reduceat(r.tables, first))


def pack(digests: list[bytes]) -> np.ndarray:
    """Digests as 32-byte strings. Numpy ignores trailing zero bytes when it compares; at equal lengths that changes nothing."""
    return np.frombuffer(b"".join(digests), "S32").copy() if digests else np.zeros(0, "S32")


class DigestIndex:
    """The index of one task: add rows, flush memtables to runs and the value log, compact, look texts up."""

    def __init__(self, memtable_bytes: int = MEMTABLE_BYTES, memtable_rows: int = MEMTABLE_ROWS):
        self.bytes, self.rows = memtable_bytes, memtable_rows
        self.runs: list[Run] = []
        #: Every row as (digest, id, row), and every text of a flushed memtable as (digest, compressed text).
        self.members: list[tuple[bytes, int, int]] = []
        self.log: list[tuple[bytes, bytes]] = []
        #: Digests that two different texts were seen to have.
        self.clashes: set[bytes] = set()
        self._table: dict[bytes, list] = {}
        self._held = 0

    def add(self, doc_id: int, text: bytes, row: int = 0) -> None:
        text = normalise(text)
        digest = hashlib.sha256(text).digest()
        self.members.append((digest, doc_id, row))
        known = self._table.get(digest)
        if known is None:
            self._table[digest] = [doc_id, row, 1, text]
            self._held += len(text) + 100
        else:
            if known[3] != text:
                self.clashes.add(digest)
            known[2] += 1
            if (doc_id, row) < (known[0], known[1]):
                known[0], known[1] = doc_id, row
        if self._held >= self.bytes or len(self._table) >= self.rows:
            self.flush()

    def flush(self) -> None:
        if self._table:
            press, order = zstandard.ZstdCompressor(level=1), sorted(self._table)
            self.log += [(d, press.compress(self._table[d][3])) for d in order]
            numbers = np.array([self._table[d][:3] for d in order], np.int64)
            self.runs.append(Run(pack(order), *numbers.T.copy(), np.ones(len(order), np.int64)))
            self._table, self._held = {}, 0

    def compact(self) -> Run:
        self.flush()
        self.runs = [compact(self.runs)]
        return self.runs[0]

    def lookup(self, text: bytes) -> int | None:
        """Smallest identifier of an equal text so far."""
        digest = hashlib.sha256(normalise(text)).digest()
        found = [self._table[digest][0]] if digest in self._table else []
        key = pack([digest])[0]
        for r in reversed(self.runs):
            at = int(np.searchsorted(r.digests, key))
            if at < len(r.digests) and r.digests[at] == key:
                found.append(int(r.keep[at]))
        return min(found, default=None)


# --- staged runs -----------------------------------------------------------------------------------------------

RUN = pa.schema(
    [("run", pa.int64()), ("bucket", pa.int32())]
    + [(f, pa.binary()) for f in (*Run.FIELDS, "slots", "member_at", "member_id", "member_row", "log_at", "log_size", "log", "clashes")]
)
RUN_DDL = "run long, bucket int, " + ", ".join(f"{f.name} binary" for f in RUN if f.name not in ("run", "bucket"))


def _ranges(digests: np.ndarray, n: int) -> np.ndarray:
    """The range of each of sorted digests; ranges ascend with them."""
    lead = np.ascontiguousarray(digests.view(np.uint8).reshape(-1, 32)[:, :4]).view(">u4")[:, 0].astype(np.int64)
    return lead * n >> 32


def _stage_rows(index: DigestIndex, run: int, n: int) -> Iterator[pa.RecordBatch]:
    """One row for each digest range of a compacted run, with the members and texts of that range."""
    r = index.compact()
    bucket = _ranges(r.digests, n)
    edges = np.r_[np.flatnonzero(np.r_[True, bucket[1:] != bucket[:-1]]), len(bucket)]
    at = np.searchsorted(r.digests, pack([d for d, _, _ in index.members]))
    ids, rows = (np.array([m[k] for m in index.members], np.int64) for k in (1, 2))
    order = np.argsort(at, kind="stable")
    at, ids, rows = at[order], ids[order], rows[order]
    log = sorted(index.log)
    log_at = np.searchsorted(r.digests, pack([d for d, _ in log]))
    clashes = sorted(index.clashes)
    clash_at = np.searchsorted(r.digests, pack(clashes))
    for a, b in zip(edges[:-1].tolist(), edges[1:].tolist(), strict=True):
        part = r.part(slice(a, b))
        m, g, c = (slice(*np.searchsorted(x, [a, b])) for x in (at, log_at, clash_at))
        texts = [z for _, z in log[g]]
        cells = [*(getattr(part, f).tobytes() for f in Run.FIELDS), part.slots().tobytes(), (at[m] - a).astype("<u4").tobytes(), ids[m].tobytes(), rows[m].tobytes(), (log_at[g] - a).astype("<u4").tobytes(), np.fromiter(map(len, texts), np.int64, len(texts)).tobytes(), b"".join(texts), b"".join(clashes[c])]
        yield pa.RecordBatch.from_arrays([pa.array([v], f.type) for v, f in zip((run, int(bucket[a]), *cells), RUN, strict=True)], schema=RUN)


def _write_runs(n: int):
    def write(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        index, run = DigestIndex(), TaskContext.get().partitionId() << 32
        for batch in batches:
            for i, t, row in zip(batch.column(0).to_pylist(), as_bytes(batch.column(1)), batch.column(2).to_pylist(), strict=True):
                index.add(i, t, row)
                if len(index.runs) >= RUNS or len(index.members) >= RUNS * MEMTABLE_ROWS:
                    yield from _stage_rows(index, run, n)
                    index, run = DigestIndex(), run + 1
        if index.members:
            yield from _stage_rows(index, run, n)

    return write


def _read_run(row: dict) -> Run:
    return Run(np.frombuffer(row["digests"], "S32"), *(np.frombuffer(row[f], np.int64) for f in Run.FIELDS[1:]))


def _compare_filters(pdf: pd.DataFrame) -> pd.DataFrame:
    """For each run of a range, one bit a digest: whether another run's filter may hold it."""
    slots = [np.frombuffer(s, np.uint32) for s in pdf["slots"]]
    shared = shared_slots([np.unique(s) for s in slots])
    out = [(run, bucket, np.packbits(np.isin(s, shared)).tobytes()) for run, bucket, s in zip(pdf["run"], pdf["bucket"], slots, strict=True)]
    return pd.DataFrame(out, columns=["run", "bucket", "may"])


def _by_bucket(right: pd.DataFrame) -> dict[int, dict]:
    return {row["bucket"]: row for row in right.to_dict("records")}


def _send_shared(left: pd.DataFrame, right: pd.DataFrame) -> pd.DataFrame:
    """What a run sends to compaction: digests that another run may hold, or that several of its memtables held."""
    may, out = _by_bucket(right), []
    for row in left.to_dict("records"):
        r = _read_run(row)
        bits = np.unpackbits(np.frombuffer(may[row["bucket"]]["may"], np.uint8), count=len(r.keep)).astype(bool)
        r = r.part(bits | (r.count > 1))
        if len(r.keep):
            out.append((row["run"], row["bucket"], *(getattr(r, f).tobytes() for f in Run.FIELDS)))
    return pd.DataFrame(out, columns=["run", "bucket", *Run.FIELDS])


def _compact_range(pdf: pd.DataFrame) -> pd.DataFrame:
    """Merge one digest range; each run gets back those of its digests that were hit twice or more."""
    runs = [_read_run(row) for row in pdf.to_dict("records")]
    whole, out = compact(runs), []
    for run, bucket, r in zip(pdf["run"], pdf["bucket"], runs, strict=True):
        hit = whole.part(np.searchsorted(whole.digests, r.digests))
        hit = hit.part(hit.count > 1)
        if len(hit.keep):
            out.append((run, bucket, *(getattr(hit, f).tobytes() for f in Run.FIELDS)))
    return pd.DataFrame(out, columns=["run", "bucket", *Run.FIELDS])


def _log_of_hits(left: pd.DataFrame, right: pd.DataFrame) -> pd.DataFrame:
    """(digest, compressed text) from the logs for digests that several memtables hold; seen clashes have no text."""
    hits, out = _by_bucket(right), []
    for row in left.to_dict("records"):
        out += [(row["clashes"][k : k + 32], b"") for k in range(0, len(row["clashes"]), 32)]
        if row["bucket"] not in hits:
            continue
        r = _read_run(hits[row["bucket"]])
        digests, at = np.frombuffer(row["digests"], "S32"), np.frombuffer(row["log_at"], "<u4")
        ends = np.cumsum(np.frombuffer(row["log_size"], np.int64))
        wanted = np.isin(digests, r.digests[r.tables > 1])[at]
        for k in np.flatnonzero(wanted).tolist():
            out.append((row["digests"][32 * int(at[k]) : 32 * int(at[k]) + 32], row["log"][int(ends[k - 1]) if k else 0 : int(ends[k])]))
    return pd.DataFrame(out, columns=["digest", "text"])


def _answer(left: pd.DataFrame, right: pd.DataFrame) -> pd.DataFrame:
    """Rows of documents from a run and its hits."""
    hits, parts = _by_bucket(right), []
    for row in left.to_dict("records"):
        r, at = _read_run(row), np.frombuffer(row["member_at"], "<u4")
        keep, keep_row, count = r.keep.copy(), r.keep_row.copy(), r.count.copy()
        if row["bucket"] in hits:
            h = _read_run(hits[row["bucket"]])
            k = np.searchsorted(r.digests, h.digests)
            keep[k], keep_row[k], count[k] = h.keep, h.keep_row, h.count
        ids, rows = (np.frombuffer(row[f], np.int64) for f in ("member_id", "member_row"))
        digests = [row["digests"][32 * k : 32 * k + 32] for k in at.tolist()]
        parts.append(pd.DataFrame({"doc_id": ids, "row": rows, "keep_id": keep[at], "keep_row": keep_row[at], "group_size": count[at], "digest": digests}))
    return pd.concat(parts) if parts else pd.DataFrame(columns=["doc_id", "row", "keep_id", "keep_row", "group_size", "digest"])


def exact_dedup(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", row_col: str | None = None) -> DataFrame:
    """One row for each row of ``docs``: doc_id, keep_id, group_size, kept, text_sha256 of the normalised text.

    ``row_col`` names a number that tells rows apart; it is returned as ``row``, and of rows that share doc_id and
    text one is kept. Without it such rows all carry kept = (doc_id = keep_id).
    """
    spark = docs.sparkSession
    row = F.col(row_col).cast("long") if row_col else F.lit(0).cast("long")
    src = docs.select(F.coalesce(F.col(id_col).cast("long"), F.lit(NO_ID)).alias("doc_id"), F.col(text_col).cast("string").alias("text"), row.alias("row"))
    rows = docs.count()
    n, layout = fan_out(spark, rows * 56, RANGE_BYTES), min(fan_out(spark, rows, MEMTABLE_ROWS), MAX_LAYOUT)
    runs = stage_by(src.mapInArrow(_write_runs(n), RUN_DDL), "run", layout)
    release(spark)
    held = ", ".join(f"{f} binary" for f in Run.FIELDS)

    def rejoin(columns: tuple[str, ...], answers: DataFrame, fn, schema: str) -> DataFrame:
        return runs.select("run", "bucket", *columns).groupBy("run").cogroup(answers.groupBy("run")).applyInPandas(fn, schema)

    may = runs.select("run", "bucket", "slots").groupBy("bucket").applyInPandas(_compare_filters, "run long, bucket int, may binary")
    sent = rejoin(Run.FIELDS, may, _send_shared, f"run long, bucket int, {held}")
    hits = stage(sent.groupBy("bucket").applyInPandas(_compact_range, f"run long, bucket int, {held}"))
    release(spark)

    # Equal digests must have equal bytes. A digest of very many runs is folded in SALTS places before it meets in one.
    texts = rejoin(("digests", "log_at", "log_size", "log", "clashes"), hits, _log_of_hits, "digest binary, text binary")
    once = texts.withColumn("salt", F.pmod(F.spark_partition_id(), F.lit(SALTS))).groupBy("digest", "salt", "text").agg(F.lit(1)).groupBy("digest", "text").agg(F.lit(1))
    clash = stage(once.groupBy("digest").agg(F.count(F.lit(1)).alias("n"), F.min(F.octet_length("text")).alias("least")).where("n > 1 OR least = 0").select("digest"))

    out = rejoin((*Run.FIELDS, "member_at", "member_id", "member_row"), hits, _answer, "doc_id long, row long, keep_id long, keep_row long, group_size long, digest binary")
    if not clash.isEmpty():  # never seen for SHA-256; then the bytes decide
        norm = F.regexp_replace(F.coalesce("text", F.lit("")), SPACE_CLASS, " ")
        clashing = src.select("doc_id", "row", norm.alias("norm")).withColumn("digest", F.unhex(F.sha2(F.col("norm").cast("binary"), 256))).join(clash, "digest", "left_semi")
        first = F.min(F.struct("doc_id", "row"))
        by_text = clashing.groupBy("digest", "norm").agg(first.alias("first"), F.count(F.lit(1)).alias("group_size"))
        split = clashing.join(by_text, ["digest", "norm"]).select("doc_id", "row", F.col("first.doc_id").alias("keep_id"), F.col("first.row").alias("keep_row"), "group_size", "digest")
        out = out.join(clash, "digest", "left_anti").select(*split.columns).unionByName(split)
    kept = (F.col("doc_id") == F.col("keep_id")) & (F.col("row") == F.col("keep_row"))
    shown_row = [F.col("row")] if row_col else []
    return out.select(shown("doc_id"), shown("keep_id"), "group_size", kept.alias("kept"), F.lower(F.hex("digest")).alias("text_sha256"), *shown_row)


def op8_lsm_exact_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return exact_dedup(table(spark, sf_dir, "documents"))


ORACLE = {
    "op8_lsm_exact_dedup": r"""
        WITH n AS (SELECT doc_id, regexp_replace(coalesce(text, ''), '[\x20\x09-\x0D]+', ' ', 'g') AS t FROM documents),
        g AS (SELECT t, min(doc_id) AS keep_id, count(*) AS group_size FROM n GROUP BY t)
        SELECT doc_id, keep_id, group_size, doc_id = keep_id AS kept, sha256(n.t) AS text_sha256 FROM n JOIN g ON n.t = g.t
    """
}
