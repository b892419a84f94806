"""Finding repeated windows of a corpus without moving the windows.

The search is for windows of ``length`` elements (bytes or words) that occur elsewhere. Every window holds an anchor:
the k-gram with the smallest hash in it, so equal windows have equal anchors at equal offsets. Rounds:

1. Each pack of texts sends its distinct anchor hashes (five bytes each) to buckets, which answer with those that
   occur again. The rest of the corpus takes no further part.
2. Anchors that recur send a hash of their context, all the elements that windows around the anchor can cover. Equal
   contexts are folded into a class; of each class one representative goes on, if its anchor has other classes.
3. Representatives send their contexts to their anchor's bucket, where an index kernel (a suffix array or a suffix
   automaton) compares the windows of different classes. The group of an anchor with more than SPLIT_CLASSES classes,
   such as the edge of a passage in very many documents, is split: its windows travel one by one, folded in each pack,
   to the buckets that their hashes name, and the same kernel compares them there.
4. Each pack marks its matched windows, and the operator reads off what they cover.

Two rules decide what counts as elsewhere: ``earlier`` (a document with a smaller id) and ``again`` (any other place).
Nothing is capped or sampled, a task holds one bucket at a time, and a hot anchor, context or window costs one entry
in each pack.

Texts lie in chunks of about BLOCK_BYTES, chunks in packs. A longer text is cut into pieces that overlap by a window
less one element, so that each of its windows lies in one piece; to the rounds a piece is a document, and the last
round joins them again. Buckets are hash shards sized by what they receive, at most MAX_BUCKETS of them; packs grow
with the corpus, so that a message from a pack to a bucket holds many anchors; the chunk table has a layout of its own.
"""

from __future__ import annotations

import re
from collections.abc import Callable, Iterator
from dataclasses import dataclass
from itertools import islice

import numpy as np
import pandas as pd
import pyarrow as pa
import zstandard
from pyspark import TaskContext
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from boundspark.llm.common import ASCII_SPACE, BLOCK_BYTES, NO_ID, blocks, id_of, mix64, release, stage, stage_by, text_bytes

SPLIT_CLASSES = 4096
BUCKET_BYTES = 12 << 20
MAX_BUCKETS = 1 << 18
#: Spark allows 100,000 buckets in a table.
MAX_LAYOUT = 50_000
PACK_CHUNKS = 32
#: Elements that one pass over a chunk takes at a time, so that what it makes on the way stays in the processor's cache.
TILE = 1 << 15
U = np.uint64
CHUNK_DDL = "pack long, chunk int, piece int, last boolean, core long, ids binary, keys binary, sizes binary, blob binary"
CHUNK = pa.schema([("pack", pa.int64()), ("chunk", pa.int32()), ("piece", pa.int32()), ("last", pa.bool_()), ("core", pa.int64()), ("ids", pa.binary()), ("keys", pa.binary()), ("sizes", pa.binary()), ("blob", pa.binary())])


@dataclass(frozen=True)
class Layout:
    """Window length, anchor length, element kind ('bytes' or 'words') and rule ('earlier' or 'again')."""

    length: int
    k: int
    kind: str
    rule: str

    def __post_init__(self) -> None:
        if not 0 < self.k <= self.length or self.left > 63:
            raise ValueError("a window may reach at most 63 elements beyond its anchor")

    @property
    def left(self) -> int:
        return self.length - self.k

    @property
    def span(self) -> int:
        return self.left + self.length


def fan(total: int, partitions: int) -> tuple[int, int, int]:
    """Buckets of the rounds, buckets of the chunk table, and chunks in a pack, for ``total`` bytes of text."""
    n = min(max(partitions, -(-total // BUCKET_BYTES), 1), MAX_BUCKETS)
    # A message holds some 32 anchors or more while packs may grow: there is about one anchor in 14 bytes.
    return n, min(n, MAX_LAYOUT), min(max(1, 448 * n // BLOCK_BYTES), PACK_CHUNKS)


_WORD, _GAP = re.compile(rb"[^\x20\x09-\x0D]+"), re.compile(rb"[\x20\x09-\x0D]")


def pieces(text: bytes, layout: Layout, size: int) -> Iterator[tuple[bytes, int]]:
    """(piece, bytes of it that no later piece repeats). Cuts fall between characters, or between words."""
    a = 0
    while a < len(text):
        b = min(a + size, len(text))
        if layout.kind == "bytes":
            while b < len(text) and text[b] & 0xC0 == 0x80:
                b += 1
            end = b + layout.length - 1
        else:
            gap = _GAP.search(text, b) if b < len(text) else None
            b = gap.end() if gap else len(text)
            end = b
            for m in islice(_WORD.finditer(text, b), layout.length - 1):
                end = m.end()
        yield text[a:end], b - a
        a = b


def chunks(docs: DataFrame, layout: Layout, buckets: int, per_pack: int, row_col: str | None, **cols) -> DataFrame:
    """Texts in compressed chunks of about BLOCK_BYTES, staged so that a pack's number stands for the same texts, and
    bucketed by it so that the rounds join their answers to the texts without moving the texts. Documents are compared
    by doc_id and returned by their key: the number in ``row_col``, or the doc_id."""
    size = BLOCK_BYTES

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        press, base, pack, held = zstandard.ZstdCompressor(level=3), TaskContext.get().partitionId() << 32, 0, 0

        def row(both: list[dict], texts: list[bytes], piece: int, last: bool, core: int) -> pa.RecordBatch:
            sizes = np.fromiter(map(len, texts), np.int64, len(texts))
            ids, keys = (np.array([x[k] for x in both], np.int64) for k in ("doc_id", "key"))
            cells = base + pack, held, piece, last, core, ids.tobytes(), keys.tobytes(), sizes.tobytes(), press.compress(b"".join(texts))
            return pa.RecordBatch.from_arrays([pa.array([v], f.type) for v, f in zip(cells, CHUNK, strict=True)], schema=CHUNK)

        for ids, texts in blocks(batches, size):
            # only the last text of a block can be longer than a block
            cut = list(pieces(texts[-1], layout, size)) if len(texts[-1]) > size else []
            whole = len(texts) - bool(cut)
            if whole:
                yield row(ids[:whole], texts[:whole], -1, True, 0)
                held += 1
            for k, (part, core) in enumerate(cut):
                yield row(ids[-1:], [part], k, k == len(cut) - 1, core)
                held += 1
            if held >= per_pack:
                pack, held = pack + 1, 0

    src = docs.select(F.struct(id_of(cols.get("id_col", "doc_id")).alias("doc_id"), (F.col(row_col).cast("long") if row_col else id_of(cols.get("id_col", "doc_id"))).alias("key")).alias("both"), F.col(cols.get("text_col", "text")).cast("string").alias("text"))
    return stage_by(src.mapInArrow(run, CHUNK_DDL), "pack", buckets)


def _in_order(pdf: pd.DataFrame) -> list[dict]:
    return pdf.sort_values("chunk").to_dict("records")


def word_hashes(raw: np.ndarray, ends: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """First bytes and 64-bit hashes of all words of texts that lie end to end; no word crosses the end of a text.

    A word's hash is a polynomial in a random value for each byte, read off running sums, mixed with its length.
    """
    n = len(raw)
    edge = np.zeros(n + 1, bool)
    edge[np.r_[0, ends]] = True
    blank = _BLANK[raw]
    begin = np.flatnonzero(~blank & (np.r_[True, blank[:-1]] | edge[:n])) if n else np.zeros(0, np.int64)
    stop = np.flatnonzero(~blank & (np.r_[blank[1:], True] | edge[1:])) + 1 if n else begin
    with np.errstate(over="ignore"):
        power, terms = _powers(n + 1), _BYTE[raw]
        terms *= power[:n]
        total = np.zeros(n + 1, U)
        np.cumsum(terms, dtype=U, out=total[1:])
        # The power of the first byte is divided out: up to that of byte n, and then back at once.
        h = (total[stop] - total[begin]) * power[n - begin] * U(pow(_POWER, -n, 1 << 64))
    return begin, mix64(h ^ mix64((stop - begin).astype(U)))


_BLANK = np.isin(np.arange(256), list(ASCII_SPACE))
_BYTE = mix64(mix64(np.arange(1, 257, dtype=U) * U(0x9E3779B97F4A7C15)))
_MIXED = mix64(np.arange(1, 257, dtype=U))
_POWER = 0x9E3779B97F4A7C15
_KEPT: list[np.ndarray] = []


def _powers(n: int) -> np.ndarray:
    """The first n powers; those for chunks of common size are kept."""
    usual = BLOCK_BYTES + (1 << 18)
    if n > usual:
        return _power_run(n)
    if not _KEPT:
        _KEPT.append(_power_run(usual))
    return _KEPT[0][:n]


def _power_run(n: int) -> np.ndarray:
    run = np.full(n, _POWER, U)
    run[:1] = 1
    with np.errstate(over="ignore"):
        return np.cumprod(run, dtype=U, out=run)


class Chunk:
    """A chunk unpacked: texts, elements, and the element range of each document."""

    def __init__(self, layout: Layout, row: dict):
        self.layout, self.piece, self.last, self.core = layout, row["piece"], row["last"], row["core"]
        self.ids, self.keys = (np.frombuffer(row[k], np.int64) for k in ("ids", "keys"))
        ends = np.cumsum(np.frombuffer(row["sizes"], np.int64))
        raw = zstandard.ZstdDecompressor().decompress(row["blob"]) if row["blob"] else b""
        cuts = list(zip([0, *ends[:-1].tolist()], ends.tolist(), strict=True))
        self.texts = [raw[a:b] for a, b in cuts]
        if layout.kind == "bytes":
            self.elements = np.frombuffer(raw, np.uint8)
            self.ends = ends
        else:
            begin, self.elements = word_hashes(np.frombuffer(raw, np.uint8), ends)
            self.ends = np.searchsorted(begin, ends)
        self.starts = np.r_[0, self.ends[:-1]].astype(np.int64)
        # Of a piece, the elements that are its own: the rest is the next piece's.
        self.own = len(self.elements) if self.piece < 0 else self.core if layout.kind == "bytes" else int(np.searchsorted(begin, self.core))

    def grams(self) -> np.ndarray:
        """A hash of the k elements from each place on."""
        lay = self.layout
        out = np.empty(max(len(self.elements) - lay.k + 1, 0), U)
        for a in range(0, len(out), TILE):
            x = self.elements[a : a + TILE + lay.k - 1]
            x = _MIXED[x] if lay.kind == "bytes" else mix64(x + U(1))
            out[a : a + TILE] = mix64(_gram_hash(x, lay.k))
        return out

    def anchors(self) -> None:
        """pos, hash and document of every anchor whose windows lie within a document."""
        lay, n = self.layout, len(self.elements)
        self.pos, self.hash, self.doc, self.low, self.high = np.zeros(0, np.int64), np.zeros(0, U), *(np.zeros(0, np.int64) for _ in range(3))
        if n < lay.length:
            return
        self.gram = h = self.grams()
        chosen = _minimizers(h, lay.left + 1)
        doc = np.searchsorted(self.ends, chosen, "right")
        self.low = np.maximum(0, chosen + lay.length - self.ends[doc])  # offsets of the windows that fit the document
        self.high = np.minimum(lay.left, chosen - self.starts[doc])
        fits = (chosen + lay.k <= self.ends[doc]) & (self.low <= self.high)
        self.pos, self.hash, self.doc = chosen[fits], h[chosen[fits]], doc[fits]
        self.low, self.high = self.low[fits], self.high[fits]

    def keep(self, mask: np.ndarray) -> None:
        self.pos, self.hash, self.doc, self.low, self.high = (x[mask] for x in (self.pos, self.hash, self.doc, self.low, self.high))

    def contexts(self, at: np.ndarray | slice = slice(None)) -> np.ndarray:
        """(anchors, span) elements plus one; zero beyond the document."""
        lay, pos, doc = self.layout, self.pos[at], self.doc[at]
        idx = pos[:, None] + np.arange(-lay.left, lay.length)
        inside = (idx >= self.starts[doc][:, None]) & (idx < self.ends[doc][:, None])
        out = self.elements[np.clip(idx, 0, len(self.elements) - 1)].astype(U) + U(1)
        return np.where(inside, out, U(0))

    def context_hashes(self) -> np.ndarray:
        """A 64-bit hash of each anchor's context: of the k-grams in it, read off running sums, and of where it ends."""
        lay, pos, doc = self.layout, self.pos, self.doc
        if not len(pos):
            return np.zeros(0, U)
        n = len(self.gram)
        a = np.maximum(pos - lay.left, self.starts[doc])
        b = np.minimum(pos + lay.length, self.ends[doc]) - lay.k + 1
        with np.errstate(over="ignore"):
            power = _powers(n + 1)
            total = np.zeros(n + 1, U)
            np.cumsum(self.gram * power[:n], dtype=U, out=total[1:])
            # The power of the first gram is divided out: up to that of gram n, and then back at once.
            h = (total[b] - total[a]) * power[n - a] * U(pow(_POWER, -n, 1 << 64))
        return mix64(h ^ mix64(((pos - a) * 64 + (b - pos)).astype(U)))


def _minimizers(h: np.ndarray, width: int) -> np.ndarray:
    """Places that are smallest in some run of ``width`` places."""
    out = []
    for a in range(0, len(h), TILE):
        b = min(a + TILE, len(h))
        low, high = max(a - width + 1, 0), min(b + width - 1, len(h))
        least = _sweep(h[low:high], width, np.minimum)
        before, after = np.zeros(low - a + width - 1, U), np.zeros(b - high + width - 1, U)
        out.append(a + np.flatnonzero(_sweep(np.concatenate([before, least, after]), width, np.maximum) == h[a:b]))
    return np.concatenate(out)


def _gram_hash(x: np.ndarray, k: int) -> np.ndarray:
    """Polynomial hash of every k elements, by doubling."""
    power, span, part, done, out = U(0x9E3779B97F4A7C15), 1, x, 0, None
    with np.errstate(over="ignore"):
        while True:
            if k & span:
                out = part if out is None else out[: len(part) - done] * power + part[done:]
                done += span
            if done == k:
                return out
            part = part[:-span] * power + part[span:]
            if out is not None:
                out = out[: len(x) - done + 1]
            power, span = power * power, span * 2


def _sweep(x: np.ndarray, width: int, pick: Callable) -> np.ndarray:
    """pick (minimum or maximum) over every ``width`` neighbours."""
    span = 1
    while span * 2 <= width:
        x, span = pick(x[:-span], x[span:]), span * 2
    return pick(x[: len(x) - (width - span)], x[width - span :]) if span < width else x


def linear_hash(rows: np.ndarray, seed: int) -> np.ndarray:
    """A 64-bit hash of each row: a random linear form over mixed elements."""
    with np.errstate(over="ignore"):
        return mix64((mix64(rows + U(seed)) * _weights(rows.shape[1], seed)).sum(axis=1, dtype=U))


def _weights(n: int, seed: int) -> np.ndarray:
    with np.errstate(over="ignore"):
        return mix64(np.arange(1, n + 1, dtype=U) * U(0xA24BAED4963EE407) + U(seed)) | U(1)


# --- five-byte keys --------------------------------------------------------------------------------------------

_LOW = U((1 << 40) - 2)


def key_of(h: np.ndarray) -> np.ndarray:
    return h & _LOW


def bucket_of(h: np.ndarray, n: int) -> np.ndarray:
    return ((h >> U(40)) % U(n)).astype(np.int64)


def pack5(x: np.ndarray) -> bytes:
    return np.ascontiguousarray(x.astype("<u8").view(np.uint8).reshape(-1, 8)[:, :5]).tobytes()


def unpack5(b: bytes) -> np.ndarray:
    raw = np.frombuffer(b, np.uint8).reshape(-1, 5)
    out = np.zeros((len(raw), 8), np.uint8)
    out[:, :5] = raw
    return out.view("<u8")[:, 0].astype(U)


def _split(bucket: np.ndarray, *arrays: np.ndarray) -> Iterator[tuple[int, list[np.ndarray]]]:
    """Runs of equal bucket, in bucket order."""
    order = np.argsort(bucket, kind="stable")
    bucket = bucket[order]
    edges = np.r_[np.flatnonzero(np.r_[True, bucket[1:] != bucket[:-1]]), len(bucket)] if len(bucket) else np.zeros(1, np.int64)
    for a, b in zip(edges[:-1], edges[1:], strict=True):
        yield int(bucket[a]), [x[order[a:b]] for x in arrays]


def _runs(*keys: np.ndarray) -> np.ndarray:
    """Starts of runs of equal keys in sorted arrays."""
    if not len(keys[0]):
        return np.zeros(0, np.int64)
    change = np.zeros(len(keys[0]) - 1, bool)
    for k in keys:
        change |= k[1:] != k[:-1]
    return np.flatnonzero(np.r_[True, change])


# --- round 1: which anchors recur ------------------------------------------------------------------------------


def _folded(keys: list[np.ndarray], low: np.ndarray, high: np.ndarray, n: np.ndarray) -> tuple[list[np.ndarray], np.ndarray, np.ndarray, np.ndarray]:
    """Distinct keys with their smallest and largest document and their number of places."""
    order = np.lexsort(keys[::-1])
    keys = [k[order] for k in keys]
    first = _runs(*keys)
    if not len(first):
        return keys, low, high, n
    return [k[first] for k in keys], np.minimum.reduceat(low[order], first), np.maximum.reduceat(high[order], first), np.add.reduceat(n[order], first)


def _places(layout: Layout, rows: list[dict], see: Callable[[dict], tuple[Chunk, list[np.ndarray]]]) -> tuple[list[np.ndarray], np.ndarray, np.ndarray, np.ndarray]:
    """``_folded`` over the chunks of a pack, each of which ``see`` opens and gives keys for."""
    got = []
    for row in rows:
        c, keys = see(row)
        who = c.ids[c.doc]
        got.append(_folded(keys, who, who, np.ones(len(who), np.int64)))
    if len(got) == 1:
        return got[0]
    join = lambda k: np.concatenate([g[k] for g in got])
    return _folded([np.concatenate(k) for k in zip(*(g[0] for g in got), strict=True)], join(1), join(2), join(3))


def _send_anchors(layout: Layout, n: int):
    def see(row: dict) -> tuple[Chunk, list[np.ndarray]]:
        c = Chunk(layout, row)
        c.anchors()
        return c, [c.hash]

    def run(pdf: pd.DataFrame) -> pd.DataFrame:
        (h,), low, high, many = _places(layout, _in_order(pdf), see)
        again = low != high if layout.rule == "earlier" else many > 1
        pack = pdf["pack"].iloc[0]
        out = [(b, pack, pack5(k)) for b, (k,) in _split(bucket_of(h, n), key_of(h) | again.astype(U))]
        return pd.DataFrame(out, columns=["bucket", "pack", "keys"])

    return run


def _recurring(pdf: pd.DataFrame) -> pd.DataFrame:
    parts = [unpack5(k) for k in pdf["keys"]]
    every = np.sort(np.concatenate(parts))
    plain = every & _LOW
    first = _runs(plain)
    size = np.diff(np.r_[first, len(plain)])
    flagged = np.bitwise_or.reduceat(every & U(1), first) > 0
    hot = plain[first][(size > 1) | flagged]
    out = []
    for bucket, pack, p in zip(pdf["bucket"], pdf["pack"], parts, strict=True):
        mine = p & _LOW
        mine = mine[_member(mine, hot)]
        if len(mine):
            out.append((pack, "keys", np.int64(bucket).tobytes() + pack5(mine)))
    return pd.DataFrame(out, columns=["pack", "what", "data"])


ANSWER_DDL = "pack long, what string, data binary"


def _member(x: np.ndarray, sorted_set: np.ndarray) -> np.ndarray:
    if not len(sorted_set):
        return np.zeros(len(x), bool)
    return sorted_set[np.minimum(np.searchsorted(sorted_set, x), len(sorted_set) - 1)] == x


# --- round 2: classes of equal contexts ------------------------------------------------------------------------

ENTRY = np.dtype([("h", "<u8"), ("e", "<u8"), ("v", "<i8"), ("more", "u1")])
VERDICT = np.dtype([("h", "<u8"), ("e", "<u8"), ("v", "<i8"), ("code", "u1")])
#: Codes: nothing to send; the class's representative goes to the kernel; its windows do.
SETTLED, GATHER, DEAL = 0, 1, 2


def _send_classes(layout: Layout, n: int):
    def run(left: pd.DataFrame, right: pd.DataFrame) -> pd.DataFrame:
        out = []
        if len(right) and len(left):
            hot = {int(np.frombuffer(d[:8], np.int64)[0]): np.sort(unpack5(d[8:])) for d in right["data"]}

            def see(row: dict) -> tuple[Chunk, list[np.ndarray]]:
                c = Chunk(layout, row)
                c.anchors()
                c.keep(_hot(c.hash, hot, n))
                return c, [c.hash, c.context_hashes()]

            (h, e), low, high, many = _places(layout, _in_order(left), see)
            entry = np.zeros(len(h), ENTRY)
            entry["h"], entry["e"] = h, e
            if layout.rule == "earlier":
                entry["v"], entry["more"] = low, low != high
            else:
                entry["v"] = many
            out = [(b, left["pack"].iloc[0], x.tobytes()) for b, (x,) in _split(bucket_of(h, n), entry)]
        return pd.DataFrame(out, columns=["bucket", "pack", "data"])

    return run


def _hot(h: np.ndarray, hot: dict[int, np.ndarray], n: int) -> np.ndarray:
    """Which anchors are in the set of their bucket."""
    # Bucket and key together name an anchor; both are read off its hash.
    mask, keys = np.zeros(len(h), bool), key_of(h)
    for b, (at,) in _split(bucket_of(h, n), np.arange(len(h))):
        if b in hot:
            mask[at] = _member(keys[at], hot[b])
    return mask


def _judge_classes(layout: Layout):
    def run(pdf: pd.DataFrame) -> pd.DataFrame:
        parts = [np.frombuffer(d, ENTRY) for d in pdf["data"]]
        every = np.concatenate(parts)
        pack = np.repeat(pdf["pack"].to_numpy(np.int64), list(map(len, parts)))
        order = np.lexsort((pack, every["v"], every["e"], every["h"])) if layout.rule == "earlier" else np.lexsort((pack, every["e"], every["h"]))
        every, pack = every[order], pack[order]
        first = _runs(every["h"], every["e"])
        cls = np.repeat(np.arange(len(first)), np.diff(np.r_[first, len(every)]))
        value = every["v"][first] if layout.rule == "earlier" else np.add.reduceat(every["v"], first)
        group = _runs(every["h"][first])
        classes = np.repeat(np.diff(np.r_[group, len(first)]), np.diff(np.r_[group, len(first)]))
        kind = np.where(classes == 1, SETTLED, np.where(classes <= SPLIT_CLASSES, GATHER, DEAL)).astype(np.uint8)
        code = np.zeros(len(every), np.uint8)
        code[first] = kind
        out = np.zeros(len(every), VERDICT)
        out["h"], out["e"], out["v"] = every["h"], every["e"], value[cls]
        if layout.rule == "earlier":
            # Rows that share the smallest id may lie in several packs: each asks for itself. None is earlier than no id.
            tied = (every["v"] == out["v"]) & (out["v"] != NO_ID)
            code[tied] = kind[cls[tied]]
            tell = (every["v"] > out["v"]) | (every["more"] > 0) | (code > 0)
        else:
            tell = (out["v"] > 1) | (code > 0)
        out["code"] = code
        rows = [(c, "classes", x.tobytes()) for c, (x,) in _split(pack[tell], out[tell])]
        return pd.DataFrame(rows, columns=["pack", "what", "data"])

    return run


# --- round 3: windows of different classes ---------------------------------------------------------------------

WINDOW = np.dtype([("a", "<u8"), ("b", "<u8"), ("v", "<i8")])


def _verdicts(right: pd.DataFrame, what: str, dtype: np.dtype) -> np.ndarray:
    parts = [np.frombuffer(d, dtype) for w, d in zip(right["what"], right["data"], strict=True) if w == what]
    return np.concatenate(parts) if parts else np.zeros(0, dtype)


class Records:
    """What a pack was told, found by anchor and context."""

    def __init__(self, told: np.ndarray):
        self.told = told = told[np.lexsort((told["h"], told["e"]))]
        self.h, self.e = (np.ascontiguousarray(told[k]) for k in ("h", "e"))
        first = _runs(self.e)
        self.most = int(np.diff(np.r_[first, len(told)]).max()) if len(told) else 0

    def find(self, h: np.ndarray, e: np.ndarray) -> np.ndarray:
        """Index into ``told`` for each (anchor, context), or -1."""
        out, first = np.full(len(e), -1), np.searchsorted(self.e, e)
        for k in range(self.most):  # once, but for contexts of several anchors that share a hash
            at = np.minimum(first + k, len(self.e) - 1)
            hit = (self.e[at] == e) & (self.h[at] == h)
            out[hit] = at[hit]
        return out


def _reopen(layout: Layout, row: dict, records: Records) -> tuple[Chunk, np.ndarray, np.ndarray]:
    """The chunk's anchors that ``records`` speak of, their record's index and their context hash."""
    c = Chunk(layout, row)
    c.anchors()
    e = c.context_hashes()
    at = records.find(c.hash, e)
    c.keep(at >= 0)
    return c, at[at >= 0], e[at >= 0]


def _speakers(layout: Layout, c: Chunk, at: np.ndarray, verdicts: np.ndarray, code: int) -> np.ndarray:
    """Anchors whose context stands for their class."""
    mine = verdicts["code"][at] == code
    if layout.rule == "earlier":
        mine &= c.ids[c.doc] == verdicts["v"][at]
    return np.flatnonzero(mine)


def _one_each(mine: np.ndarray, at: np.ndarray, used: np.ndarray) -> np.ndarray:
    """One of the anchors for each verdict that no chunk before has spoken for."""
    mine = mine[np.unique(at[mine], return_index=True)[1]]
    mine = mine[~used[at[mine]]]
    used[at[mine]] = True
    return mine


def window_hashes(layout: Layout, rows: np.ndarray, offset: int) -> tuple[np.ndarray, np.ndarray]:
    part = rows[:, layout.left - offset : layout.left - offset + layout.length]
    return linear_hash(part, 11), linear_hash(part, 12)


def _windows(layout: Layout, c: Chunk, reps: np.ndarray) -> Iterator[tuple[int, np.ndarray, np.ndarray, np.ndarray]]:
    """(offset, anchors, hash a, hash b) of the windows of representatives.

    Hashes hold the anchor and its offset too, so that one place seen from two anchors makes two different windows.
    """
    for k in range(0, len(reps), 4096):
        some = reps[k : k + 4096]
        rows = c.contexts(some)
        for o in range(layout.left + 1):
            ok = (c.low[some] <= o) & (o <= c.high[some])
            if ok.any():
                a, b = window_hashes(layout, rows[ok], o)
                seen_from = c.hash[some[ok]] ^ U(o)
                yield o, some[ok], a ^ mix64(seen_from), b ^ mix64(seen_from ^ U(1 << 40))


def _send_contexts(layout: Layout, n: int):
    dtype = _dtype(layout)

    def run(left: pd.DataFrame, right: pd.DataFrame) -> pd.DataFrame:
        out, wins = [], []
        verdicts = _verdicts(right, "classes", VERDICT)
        verdicts = verdicts[verdicts["code"] > 0]
        if len(verdicts) and len(left):
            pack, used, records = left["pack"].iloc[0], np.zeros(len(verdicts), bool), Records(verdicts)
            verdicts = records.told
            for row in _in_order(left):
                c, at, _ = _reopen(layout, row, records)
                reps = _one_each(_speakers(layout, c, at, verdicts, GATHER), at, used)
                for b, (some,) in _split(bucket_of(c.hash[reps], n), reps):
                    body = (np.maximum(c.contexts(some), U(1)) - U(1)).astype(dtype)
                    low, high, v = c.low[some].astype(np.uint8), c.high[some].astype(np.uint8), verdicts["v"][at[some]]
                    head = np.stack([c.hash[some], verdicts["e"][at[some]], v.view(U)], 1)
                    out.append((b, pack, "contexts", len(some), head.tobytes() + low.tobytes() + high.tobytes() + body.tobytes()))
                reps = _one_each(_speakers(layout, c, at, verdicts, DEAL), at, used)
                for o, who, a, b in _windows(layout, c, reps):
                    w = np.zeros(len(a), _window_type(layout))
                    w["a"], w["b"], w["o"] = a, b, o
                    w["v"] = c.ids[c.doc[who]] if layout.rule == "earlier" else verdicts["v"][at[who]]
                    w["body"] = (c.contexts(who)[:, layout.left - o : layout.left - o + layout.length] - U(1)).astype(dtype)
                    wins.append(w)
            if wins:
                w = _fold_windows(layout, np.concatenate(wins))
                out += [(b, pack, "windows", len(x), x.tobytes()) for b, (x,) in _split(bucket_of(w["a"], n), w)]
        return pd.DataFrame(out, columns=["bucket", "pack", "what", "n", "data"])

    return run


def _dtype(layout: Layout):
    return np.uint8 if layout.kind == "bytes" else U


def _window_type(layout: Layout) -> np.dtype:
    return np.dtype([("a", "<u8"), ("b", "<u8"), ("v", "<i8"), ("more", "u1"), ("o", "u1"), ("body", _dtype(layout), (layout.length,))])


def _fold_windows(layout: Layout, w: np.ndarray) -> np.ndarray:
    """Equal windows of a pack as one: the smallest id or the number of places; ``more`` where it had several ids."""
    w = w[np.lexsort((w["v"], w["b"], w["a"]))]
    first = _runs(w["a"], w["b"])
    out = w[first].copy()
    if layout.rule == "again":
        out["v"] = np.add.reduceat(w["v"], first)
    else:
        out["more"] = out["v"] != w["v"][np.r_[first[1:], len(w)] - 1]
    return out


@dataclass
class Contexts:
    """Distinct contexts of the anchors of one bucket: anchor, class, value (id or count), offsets that fit, elements."""

    h: np.ndarray
    e: np.ndarray
    v: np.ndarray
    low: np.ndarray
    high: np.ndarray
    rows: np.ndarray
    pack: np.ndarray

    def by_anchor(self) -> Contexts:
        order = np.argsort(self.h, kind="stable")
        return Contexts(*(getattr(self, f)[order] for f in ("h", "e", "v", "low", "high", "rows", "pack")))


def _read_contexts(layout: Layout, pdf: pd.DataFrame) -> Contexts:
    dtype = _dtype(layout)
    parts: list[list[np.ndarray]] = [[] for _ in range(7)]
    for pack, n, d in zip(pdf["pack"], pdf["n"], pdf["data"], strict=True):
        head = np.frombuffer(d, U, 3 * n).reshape(n, 3)
        low, high = np.frombuffer(d, np.uint8, n, 24 * n), np.frombuffer(d, np.uint8, n, 25 * n)
        rows = np.frombuffer(d, dtype, n * layout.span, 26 * n).reshape(n, layout.span) if dtype is np.uint8 else np.frombuffer(d[26 * n :], dtype).reshape(n, layout.span)
        for p, x in zip(parts, (head[:, 0], head[:, 1], head[:, 2].astype(np.int64), low, high, rows, np.full(n, pack, np.int64)), strict=True):
            p.append(x)
    return Contexts(*(np.concatenate(p) for p in parts)).by_anchor()


MASK = np.dtype([("h", "<u8"), ("e", "<u8"), ("v", "<i8"), ("mask", "<u8")])


def _read_windows(layout: Layout, pdf: pd.DataFrame) -> tuple[Contexts, np.ndarray]:
    """Windows of split groups as contexts that fit one offset each, and their own records."""
    parts = [np.frombuffer(d, _window_type(layout)) for d in pdf["data"]]
    pack, w = np.repeat(pdf["pack"].to_numpy(np.int64), list(map(len, parts))), np.concatenate(parts)
    order = np.argsort(w["a"], kind="stable")
    w, pack = w[order], pack[order]
    rows = np.zeros((len(w), layout.span), _dtype(layout))
    for o in np.unique(w["o"]).tolist():
        mine = w["o"] == o
        rows[mine, layout.left - o : layout.left - o + layout.length] = w["body"][mine]
    return Contexts(w["a"], w["b"], w["v"], w["o"], w["o"], rows, pack), w


def _match(layout: Layout, kernel: Callable[[Layout, Contexts], np.ndarray]):
    """Answers: for each representative the set of its windows that occur elsewhere; for each window of a split group
    the id or number of places that decides over it."""

    def run(pdf: pd.DataFrame) -> pd.DataFrame:
        out = []
        gathered = pdf[pdf["what"] == "contexts"]
        if len(gathered):
            ctx = _read_contexts(layout, gathered)
            mask = kernel(layout, ctx)
            hit = np.flatnonzero(mask)
            res = np.zeros(len(hit), MASK)
            res["h"], res["e"], res["v"], res["mask"] = ctx.h[hit], ctx.e[hit], ctx.v[hit], mask[hit]
            out += [(c, "masks", x.tobytes()) for c, (x,) in _split(ctx.pack[hit], res)]
        split = pdf[pdf["what"] == "windows"]
        if len(split):
            ctx, w = _read_windows(layout, split)
            hit = kernel(layout, ctx) > 0
            told = hit | (w["more"] > 0 if layout.rule == "earlier" else w["v"] > 1)
            res = np.zeros(len(w), WINDOW)
            res["a"], res["b"], res["v"] = w["a"], w["b"], np.where(hit, NO_ID, w["v"])
            out += [(c, "windows", x.tobytes()) for c, (x,) in _split(ctx.pack[told], res[told])]
        return pd.DataFrame(out, columns=["pack", "what", "data"])

    return run


# --- round 4: coverage -----------------------------------------------------------------------------------------


def _covered(layout: Layout, row: dict, classes: Records, matched: Records, known: dict) -> tuple[Chunk, np.ndarray]:
    """Elements of the chunk that lie in a matched window."""
    verdicts, masks = classes.told, matched.told
    if not len(verdicts):
        c = Chunk(layout, row)
        return c, np.zeros(len(c.elements), bool)
    c, at, e = _reopen(layout, row, classes)
    starts = np.zeros(len(c.elements) + 1, bool)
    v, who = verdicts["v"][at], c.ids[c.doc]
    settled = who > v if layout.rule == "earlier" else v > 1
    for o in range(layout.left + 1):
        starts[c.pos[settled & (c.low <= o) & (o <= c.high)] - o] = True
    if len(masks):
        m = matched.find(c.hash, e)
        bits = np.where(m >= 0, masks["mask"][m], U(0))
        if layout.rule == "earlier":
            bits[who != masks["v"][m]] = 0
        for o in range(layout.left + 1):
            starts[c.pos[(bits >> U(o) & U(1)).astype(bool) & (c.low <= o) & (o <= c.high)] - o] = True
    if known:
        for o, some, a, b in _windows(layout, c, _speakers(layout, c, at, verdicts, DEAL)):
            for p, i, key in zip(c.pos[some].tolist(), who[some].tolist(), zip(a.tolist(), b.tolist(), strict=True), strict=True):
                if key in known and (layout.rule == "again" or i > known[key]):
                    starts[p - o] = True
    edge = np.zeros(len(c.elements) + layout.length + 1, np.int64)
    s = np.flatnonzero(starts)
    edge[s] += 1
    np.subtract.at(edge, s + layout.length, 1)
    return c, np.cumsum(edge)[: len(c.elements)] > 0


def _documents(layout: Layout, rows: list[dict], right: pd.DataFrame, finish: Callable) -> Iterator[tuple]:
    """Rows of whole documents. ``finish()`` makes an object that takes a document's stretches in turn."""
    classes, matched = (Records(_verdicts(right, what, t)) for what, t in (("classes", VERDICT), ("masks", MASK)))
    wins = _verdicts(right, "windows", WINDOW)
    known = {(a, b): x for a, b, x in zip(wins["a"].tolist(), wins["b"].tolist(), wins["v"].tolist(), strict=True)}
    open_, beyond = None, np.zeros(0, bool)
    for row in rows:
        c, gone = _covered(layout, row, classes, matched, known)
        if c.piece < 0:
            for i, text, a, b in zip(c.keys.tolist(), c.texts, c.starts.tolist(), c.ends.tolist(), strict=True):
                one = finish()
                one.add(text, gone[a:b])
                yield i, *one.row()
            continue
        if c.piece == 0:
            open_, beyond = finish(), np.zeros(0, bool)
        gone[: len(beyond)] |= beyond[: len(gone)]
        open_.add(c.texts[0][: c.core], gone[: c.own])
        beyond = gone[c.own :]
        if c.last:
            yield int(c.keys[0]), *open_.row()


def remove_repeats(docs: DataFrame, layout: Layout, kernel: Callable[[Layout, Contexts], np.ndarray], finish: Callable, ddl: str, row_col: str | None = None, **cols) -> DataFrame:
    """A row for each document, named by its key, as ``finish`` reads it off the document's stretches and what of them is covered."""
    spark = docs.sparkSession
    n, table_buckets, per_pack = fan(text_bytes(docs, cols.get("text_col", "text")), int(spark.conf.get("spark.sql.shuffle.partitions")))
    held = chunks(docs, layout, table_buckets, per_pack, row_col, **cols)
    release(spark)

    def rejoin(answers: DataFrame, fn, schema: str) -> DataFrame:
        return held.groupBy("pack").cogroup(answers.groupBy("pack")).applyInPandas(fn, schema)

    sent = held.groupBy("pack").applyInPandas(_send_anchors(layout, n), "bucket int, pack long, keys binary")
    keys = stage(sent.groupBy("bucket").applyInPandas(_recurring, ANSWER_DDL))
    release(spark)
    classes = stage(rejoin(keys, _send_classes(layout, n), "bucket int, pack long, data binary").groupBy("bucket").applyInPandas(_judge_classes(layout), ANSWER_DDL))
    release(spark)
    found = stage(rejoin(classes, _send_contexts(layout, n), "bucket int, pack long, what string, n int, data binary").groupBy("bucket").applyInPandas(_match(layout, kernel), ANSWER_DDL))
    release(spark)
    names = [c.split()[0] for c in ddl.split(", ")]

    def last(left: pd.DataFrame, right: pd.DataFrame) -> pd.DataFrame:
        return pd.DataFrame(list(_documents(layout, _in_order(left), right, finish)), columns=names)

    return rejoin(classes.union(found), last, ddl)
