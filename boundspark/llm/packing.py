"""Best-fit packing of token sequences in bulk-synchronous supersteps.

A piece of more than half the capacity opens a sequence; the others and the gaps of open sequences are the state of
the supersteps. In each, documents and gaps are range-sorted together by size. Every range sweeps its rows: a gap takes
the largest document that fits and has not been taken, and as many more of that size as fit. What a range cannot
match it reports as so many gaps that wait and so many documents that stand over. Ranks settle the conflicts between
ranges: the documents standing over form one stack, every waiting gap names the height at which it draws, and rows
of one height meet in a join. Then gaps shrink, and where the documents left are more than all gaps could hold, or no
gap takes any, the largest of them open sequences. No task holds more than a range, and the driver sees one row a range.

Defined cases: a null text is empty and packs as its end mark alone; documents longer than the capacity are cut into
full pieces, of which the first may be shorter; repeated rows and rows that share an id are packed once each; a null
doc_id is shown as null; among documents of equal length the one that a range reads last goes first, so ties move
whole documents only; an empty table gives an empty result; extra columns are ignored.
"""

from __future__ import annotations

import zlib
from collections.abc import Iterator
from functools import lru_cache

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import window as W

from boundspark.llm.bpe import BacktrackingBpe, Memo, load, vocabulary
from boundspark.llm.common import as_bytes, shown, source, stage, table

CAPACITY = 2048


class _Tokens:
    """Whole-text ids of the vocabulary, word by word with a memory; unknown words go to the library's encoder."""

    def __init__(self, bpe: BacktrackingBpe):
        import tiktoken

        ordinary = tiktoken.Encoding("words", pat_str=bpe.words.pattern, mergeable_ranks=bpe.vocab, special_tokens={}).encode_ordinary
        self.bpe = bpe
        self.plain = lambda text: np.array(ordinary(text), "<u4").tobytes()
        self.tail = Memo(lambda word: self.plain(" " + word))

    def __call__(self, text: str) -> bytes:
        if any(s in text for s in self.bpe.special):
            return self.bpe.encode_bytes(text)
        if "  " in text or text[-1:] == " ":
            return self.plain(text)
        first, *rest = text.split(" ")
        return (self.plain(first) if first else b"") + b"".join(map(self.tail.__getitem__, rest))


@lru_cache(maxsize=1)
def _tokens(path: str) -> _Tokens:
    return _Tokens(load(path))


PIECES = pa.schema([("doc_id", pa.int64()), ("piece", pa.int32()), ("start", pa.int64()), ("length", pa.int64()), ("ids_crc32", pa.int64()), ("uid", pa.int64())])
PIECES_DDL = "doc_id long, piece int, start long, length long, ids_crc32 long, uid long"


def pieces(docs: DataFrame, capacity: int = CAPACITY, path: str | None = None, end_id: int = 0) -> DataFrame:
    """Pieces of each document, with a number of their own."""
    path = path or vocabulary()

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        tokens, uid = _tokens(path), TaskContext.get().partitionId() << 38
        end = end_id.to_bytes(4, "little")
        for batch in batches:
            cols: list[list] = [[] for _ in PIECES]
            for i, text in zip(batch.column(0).to_pylist(), as_bytes(batch.column(1)), strict=True):
                raw = tokens(text.decode("utf-8", errors="replace")) + end
                n = len(raw) // 4
                cuts = [0, *range((n - 1) % capacity + 1, n + 1, capacity)]
                for k, (a, b) in enumerate(zip(cuts[:-1], cuts[1:], strict=True)):
                    for c, v in zip(cols, (i, k, a, b - a, zlib.crc32(raw[4 * a : 4 * b]), uid), strict=True):
                        c.append(v)
                    uid += 1
            yield pa.RecordBatch.from_arrays([pa.array(c, f.type) for c, f in zip(cols, PIECES, strict=True)], schema=PIECES)

    return source(docs).mapInArrow(run, PIECES_DDL)


#: Ranges are swept by no more tasks than give each so many rows.
TASK_ROWS = 100_000
#: Rows of a superstep. what: placed (document ``id`` in sequence ``seq``, the nth there in this step), document (left
#: over, the nth of its range), gap (of sequence ``id``; waits for ``want`` documents after ``nth`` others of its
#: range), range (how many wait, stand over and were placed; tokens left over, tokens of gaps, largest left over, gaps).
SWEPT = pa.schema([("what", pa.string()), ("part", pa.int32()), ("id", pa.int64()), ("size", pa.int64()), ("seq", pa.int64()), ("nth", pa.int64()), ("want", pa.int64()), ("totals", pa.list_(pa.int64()))])
SWEPT_DDL = "what string, part int, id long, size long, seq long, nth long, want long, totals array<long>"


def sweep(sizes: list[int], is_gap: list[bool], ids: list[int], largest: int) -> tuple[list[tuple], list[tuple], list[tuple]]:
    """Match one sorted range: (placed: id, size, sequence, nth), (documents left: id, size), (gaps: id, size, want)."""
    placed, gaps, over = [], [], []
    for size, gap, i in zip(sizes, is_gap, ids, strict=True):
        if not gap:
            over.append((i, size))
        elif not over:
            gaps.append((i, size, max(1, size // largest)))
        else:
            times = size // (largest if size >= largest else over[-1][1])
            for nth in range(min(times, len(over))):
                if over[-1][1] > size:
                    break
                d, n = over.pop()
                placed.append((d, n, i, nth))
                size, times = size - n, times - 1
            if size:
                gaps.append((i, size, 0 if over else times))
    return placed, over, gaps


def _rows(what: str, part: int, n: int, **cols) -> pa.RecordBatch:
    cols |= {"what": [what] * n, "part": [part] * n}
    return pa.RecordBatch.from_arrays([pa.array(cols[f.name], f.type) if f.name in cols else pa.nulls(n, f.type) for f in SWEPT], schema=SWEPT)


def _sweep_ranges(largest: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: list[pa.RecordBatch] = []
        for batch in batches:  # one range after another
            at = 0
            part = batch.column("part").to_numpy()
            for end in [*(np.flatnonzero(part[1:] != part[:-1]) + 1).tolist(), len(part)]:
                if held and held[0].column("part")[0].as_py() != part[at]:
                    yield from _one_range(held, largest)
                    held = []
                if end > at:
                    held.append(batch.slice(at, end - at))
                at = end
        if held:
            yield from _one_range(held, largest)

    return run


def _one_range(held: list[pa.RecordBatch], largest: int) -> Iterator[pa.RecordBatch]:
    table, part = pa.Table.from_batches(held), held[0].column("part")[0].as_py()
    placed, over, gaps = sweep(*(table.column(c).to_pylist() for c in ("size", "gap", "id")), largest)
    waiting = np.cumsum([0, *(w for _, _, w in gaps)])
    totals = [int(waiting[-1]), len(over), len(placed), sum(n for _, n in over), sum(n for _, n, _ in gaps), max((n for _, n in over), default=0), len(gaps)]
    yield _rows("range", part, 1, totals=[totals])
    for a in range(0, len(placed), 50_000):
        i, n, seq, nth = zip(*placed[a : a + 50_000], strict=True)
        yield _rows("placed", part, len(i), id=i, size=n, seq=seq, nth=nth)
    for a in range(0, len(over), 50_000):
        i, n = zip(*over[a : a + 50_000], strict=True)
        yield _rows("document", part, len(i), id=i, size=n, nth=range(a, a + len(i)))
    for a in range(0, len(gaps), 50_000):
        i, n, want = zip(*gaps[a : a + 50_000], strict=True)
        yield _rows("gap", part, len(i), id=i, size=n, nth=waiting[a : a + len(i)], want=want)


def heights(ranges: list[tuple]) -> tuple[list[tuple], int, int]:
    """For each range (part, height its gaps draw from, height its documents stand on), given (part, waiting, over) in
    order; then the height of the stack at the end, and how many gaps drew."""
    out, height, drawn = [], 0, 0
    for part, waiting, over in ranges:
        used = min(height, waiting)
        out.append((part, height, height - used))
        height, drawn = height - used + over, drawn + used
    return out, height, drawn


def supersteps(work: DataFrame, capacity: int) -> DataFrame:
    """(uid, length) to (uid, length, sequence_id, step, nth): a sequence is named by the piece that opens it."""
    spark = work.sparkSession
    large = F.col("length") * 2 > capacity
    opened = work.where(large).select("uid", "length", F.col("uid").alias("sequence_id"), F.lit(-1).alias("step"), F.lit(0).cast("long").alias("nth"))
    state = work.select(F.col("uid").alias("id"), F.when(large, capacity - F.col("length")).otherwise(F.col("length")).alias("size"), large.alias("gap")).where("size > 0")
    done, step = [opened], 0
    largest, rows_now = state.agg(F.max(F.when(~F.col("gap"), F.col("size"))), F.count(F.lit(1))).first()
    while largest:
        tasks = max(1, rows_now // TASK_ROWS)
        # By range, documents before gaps of their size. What the ranges return is staged, so their numbers stay theirs.
        ranged = state.repartitionByRange("size", "gap", "id").sortWithinPartitions("size", "gap", "id").select("*", F.spark_partition_id().alias("part"))
        swept = stage(ranged.coalesce(tasks).mapInArrow(_sweep_ranges(largest), SWEPT_DDL))
        ranges = sorted((r["part"], *r["totals"]) for r in swept.where("what = 'range'").select("part", "totals").collect())
        placed, left, room = (sum(r[k] for r in ranges) for k in (3, 4, 5))
        level, height, drawn = heights([r[:3] for r in ranges])
        more = -(-left // capacity) if not placed + drawn else max(0, -(-(left - room) // capacity))
        opening = height - min(more, height)  # documents that stand higher open sequences
        at = F.broadcast(spark.createDataFrame(level, "part int, draws long, stands long"))  # a row for each range
        stack = swept.where("what = 'document'").join(at, "part").select("id", "size", "part", (F.col("stands") + F.col("nth") + 1).alias("height"))
        gaps = swept.where("what = 'gap'").select("id", "size", "part", "nth", "want")
        if drawn:
            draw = gaps.where("want > 0").join(at, "part").withColumn("top", F.col("draws") - F.col("nth")).where("top > 0")
            draw = draw.withColumn("height", F.explode(F.sequence("top", F.greatest(F.lit(1), F.col("top") - F.col("want") + 1), F.lit(-1))))
            rows = stack.select("height", "part", F.lit(True).alias("document"), "id", "size", F.lit(0).cast("long").alias("nth"))
            rows = rows.union(draw.select("height", "part", F.lit(False), "id", "size", F.col("top") - F.col("height")))
            # At one height documents and gaps take turns; what a gap draws is the row before it, what stays is the last.
            w = W.Window.partitionBy("height").orderBy("part", "document")
            met = stage(rows.select("*", F.lag(F.struct("id", "size", "document")).over(w).alias("below"), F.lead("document").over(w).alias("above")).coalesce(tasks))
            took = met.where("NOT document AND below.document").select(F.col("below.id").alias("uid"), F.col("below.size").alias("length"), F.col("id").alias("sequence_id"), F.lit(step).alias("step"), "nth")
            stack = met.where("document AND above IS NULL").select("id", "size", "part", "height")
            done.append(took)
            spent = took.select(F.col("sequence_id").alias("id"), (-F.col("length")).alias("size"))
            gaps = gaps.where("want = 0").select("id", "size").union(gaps.where("want > 0").select("id", "size").union(spent).groupBy("id").agg(F.sum("size").alias("size")))
        done.append(swept.where("what = 'placed'").select(F.col("id").alias("uid"), F.col("size").alias("length"), F.col("seq").alias("sequence_id"), F.lit(step).alias("step"), "nth"))
        stays = stack.where(F.col("height") <= opening)
        if more:
            opens = stack.where(F.col("height") > opening)
            done.append(opens.select(F.col("id").alias("uid"), F.col("size").alias("length"), F.col("id").alias("sequence_id"), F.lit(step).alias("step"), F.lit(0).cast("long").alias("nth")))
            gaps = gaps.select("id", "size").union(opens.select("id", (capacity - F.col("size")).alias("size")))
        if height == min(more, height):
            break
        state = stage(stays.select("id", "size", F.lit(False).alias("gap")).union(gaps.where("size > 0").select("id", "size", F.lit(True))))
        largest, rows_now, step = max(r[6] for r in ranges), sum(r[2] + r[7] for r in ranges), step + 1
    out = done[0]
    for d in done[1:]:
        out = out.union(d)
    return out


def pack(docs: DataFrame, capacity: int = CAPACITY, path: str | None = None, end_id: int = 0) -> DataFrame:
    """doc_id, piece, start, length, ids_crc32, sequence_id, offset: one row for each piece."""
    rows = stage(pieces(docs, capacity, path, end_id))
    placed = supersteps(rows.select("uid", "length"), capacity)
    # At most ``capacity`` rows in a sequence.
    before = F.sum("length").over(W.Window.partitionBy("sequence_id").orderBy("step", "nth", "uid")) - F.col("length")
    places = placed.select("uid", "sequence_id", before.alias("offset"))
    return rows.join(places.hint("merge"), "uid").select(shown("doc_id"), "piece", "start", "length", "ids_crc32", "sequence_id", "offset")


def op10_bulk_best_fit(spark: SparkSession, sf_dir: str) -> DataFrame:
    return pack(table(spark, sf_dir, "documents"))


ORACLE: dict[str, str] = {}
