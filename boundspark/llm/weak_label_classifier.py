"""Quality classifier from weak labels.

Heuristic labellers vote good, bad or nothing on every text. Expectation-maximisation over the counts of vote
patterns (at most 3 ** labellers of them, however many texts) estimates each labeller's accuracy and the share of good
texts; the posterior of a pattern is a soft label. A linear scorer over hashed words and word shapes is trained on the
soft labels of a bounded sample and scores every text. Texts are read once: votes and the counts of the slots that a
text fills are staged, and the sample and the scores come from there.

The sample is the ``train_texts`` different (doc_id, text) rows of smallest hash, the same however rows are dealt.

Defined cases: a null or wordless text scores the scorer's bias alone, and the length labeller votes it bad; repeated
rows get equal scores and count once in the sample; rows of equal hash are ordered by doc_id and votes; a null doc_id
is shown as null, and rows without one are told apart by their texts; an empty table gives an empty result; if all
labels agree the scorer learns a constant; extra columns are ignored; very long texts are read whole, one at a time.
"""

from __future__ import annotations

import re
import zlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from boundspark.llm.common import as_bytes, shown, source, stage, table
from boundspark.llm.quality_rules import COMMON_WORDS, SYMBOLS, repeat_words

GOOD, BAD, NONE = 2, 1, 0
MARKS = frozenset(SYMBOLS)
TRAIN_TEXTS = 4000
#: Slots of the scorer: of words, then SHAPES of word shapes, the last two of which measure repetition.
DIM, SHAPES = 2048, 256
COMMON = frozenset(w.encode() for ws in COMMON_WORDS.values() for w in ws)


LABELLERS = ("symbols", "uncommon", "repetition", "marked_words", "length", "word_size", "clean_prose")


def votes(text: bytes, words: list[bytes], repeated: int) -> int:
    """Votes of the labellers in the order of LABELLERS, as the digits of a number in base three.

    All but the last only ever reject; the last approves prose in which nothing speaks against it.
    """
    n = len(words)
    if not n:
        return _pattern([NONE, NONE, NONE, NONE, BAD, NONE, NONE])
    symbols = len(text) - len(text.translate(None, SYMBOLS))
    common = sum(map(COMMON.__contains__, words)) / n
    marked = sum(w[-1] in MARKS for w in words) / n
    mean = sum(map(len, words)) / n
    against = [symbols > 0.02 * len(text), common < 0.12 and n >= 20, repeated > 0.3 * n, marked > 0.05, n < 8, not 2.5 <= mean <= 12]
    prose = not any(against) and n >= 30 and common > 0.2 and repeated < 0.1 * n
    return _pattern([BAD if x else NONE for x in against] + [GOOD if prose else NONE])


def _pattern(digits: list[int]) -> int:
    out = 0
    for d in digits:
        out = 3 * out + d
    return out


def _read(text: bytes) -> tuple[list[bytes], int]:
    words = text.split()
    return words, repeat_words(words)


class LabelModel:
    """Accuracies of conditionally independent labellers with abstention, from pattern counts."""

    def __init__(self, rounds: int = 60):
        self.rounds, self.prior = rounds, 0.8

    def fit(self, patterns: np.ndarray, counts: np.ndarray) -> LabelModel:
        m = patterns.shape[1]
        self.accuracy = self.start(patterns)
        total = counts.sum()
        for _ in range(self.rounds if total else 0):
            p = self.posterior(patterns)
            self.prior = float(np.clip((p * counts).sum() / total, 0.02, 0.98))
            for k in range(m):
                cast = patterns[:, k] != NONE
                right = np.where(patterns[:, k] == GOOD, p, 1 - p)
                seen = (counts * cast).sum()
                # two added votes keep an unused labeller where it started
                self.accuracy[k] = np.clip(((counts * cast * right).sum() + 2 * self.start(patterns)[k]) / (seen + 2), 0.05, 0.99)
        return self

    @staticmethod
    def start(patterns: np.ndarray) -> np.ndarray:
        """Labellers that only ever reject start as more reliable than those that vote both ways."""
        return np.where((patterns == GOOD).any(axis=0), 0.7, 0.95) if len(patterns) else np.full(patterns.shape[1], 0.8)

    def posterior(self, patterns: np.ndarray) -> np.ndarray:
        weight = np.log(self.accuracy / (1 - self.accuracy))
        side = np.where(patterns == GOOD, 1.0, np.where(patterns == BAD, -1.0, 0.0))
        return 1 / (1 + np.exp(-(np.log(self.prior / (1 - self.prior)) + side @ weight)))


_LETTERS, _DIGITS, _HIGH = re.compile(rb"[A-Za-z]+"), re.compile(rb"[0-9]+"), re.compile(rb"[\x80-\xff]+")


def slots(word: bytes) -> tuple[int, int]:
    """Hashed places of a word and of its shape (runs of letters, digits and other characters)."""
    shape = _DIGITS.sub(b"0", _LETTERS.sub(b"a", _HIGH.sub(b"a", word)))
    return zlib.crc32(word.lower()) % (DIM - SHAPES), DIM - SHAPES + zlib.crc32(shape.replace(b"aa", b"a")) % (SHAPES - 2)


class _Slots(dict):
    def __missing__(self, word: bytes) -> tuple[int, int]:
        if len(self) > 200_000:
            self.clear()
        got = self[word] = slots(word)
        return got


def features(words: list[bytes], repeated: int, memo: dict) -> tuple[np.ndarray, np.ndarray]:
    """The slots that a text fills, and the square roots of their shares among its words."""
    if not words:
        return np.zeros(0, "<u2"), np.zeros(0, "<f4")
    at = np.fromiter((s for w in words for s in memo[w]), np.int64, 2 * len(words))
    count = np.bincount(at, minlength=DIM)
    count[-2:] = repeated, sum(map(bytes.__eq__, words[1:], words[:-1]))
    slot = np.flatnonzero(count)
    return slot.astype("<u2"), np.sqrt(count[slot] / len(words)).astype("<f4")


def train(x: np.ndarray, y: np.ndarray, steps: int = 600, rate: float = 4.0, decay: float = 1e-4) -> np.ndarray:
    """Logistic regression on soft labels by full-batch gradient steps; the last weight is the bias."""
    w = np.zeros(x.shape[1] + 1, x.dtype)
    if not len(y):
        return w
    x1 = np.hstack([x, np.ones((len(x), 1), x.dtype)])
    for _ in range(steps):
        p = 1 / (1 + np.exp(-(x1 @ w)))
        w -= (rate * ((p - y) @ x1 / len(y) + decay * w)).astype(x.dtype)
    return w


READ = pa.schema([("doc_id", pa.int64()), ("pattern", pa.int32()), ("key", pa.int64()), ("slots", pa.binary()), ("weights", pa.binary())])


def _vote_rows(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    memo = _Slots()
    for b in batches:
        cols: list[list] = [[] for _ in READ]
        for i, t in zip(b.column(0).to_pylist(), as_bytes(b.column(1)), strict=True):
            read = _read(t)
            slot, weight = features(*read, memo)
            key = xxhash.xxh64_intdigest(t, xxhash.xxh64_intdigest(str(i))) >> 1
            for c, v in zip(cols, (i, votes(t, *read), key, slot.tobytes(), weight.tobytes()), strict=True):
                c.append(v)
        yield pa.RecordBatch.from_arrays([pa.array(c, f.type) for c, f in zip(cols, READ, strict=True)], schema=READ)


def _patterns(codes: np.ndarray) -> np.ndarray:
    m = len(LABELLERS)
    return codes[:, None] // 3 ** np.arange(m - 1, -1, -1) % 3


def quality_classifier(docs: DataFrame, train_texts: int = TRAIN_TEXTS) -> DataFrame:
    """doc_id, pattern (votes), weak_label (posterior of good), score, kept (score of at least one half)."""
    voted = stage(source(docs).mapInArrow(_vote_rows, "doc_id long, pattern int, key long, slots binary, weights binary"))
    counts = sorted((r["pattern"], r["n"]) for r in voted.groupBy("pattern").agg(F.count(F.lit(1)).alias("n")).collect())
    codes = np.array([c for c, _ in counts], np.int64)
    model = LabelModel().fit(_patterns(codes), np.array([n for _, n in counts], np.float64))
    label = dict(zip(codes.tolist(), np.round(model.posterior(_patterns(codes)), 6).tolist(), strict=True)) if len(codes) else {}

    # ``train_texts`` keys, then one row for each of them: rows of one key are copies.
    order = ["key", "doc_id", "pattern"]
    chosen = voted.select(*order).distinct().orderBy(*order).limit(train_texts)
    sample = sorted(voted.join(F.broadcast(chosen), order, "left_semi").groupBy(*order).agg(F.first("slots").alias("slots"), F.first("weights").alias("weights")).collect())
    x = np.zeros((len(sample), DIM), np.float32)
    for row, r in zip(x, sample, strict=True):
        row[np.frombuffer(r["slots"], "<u2")] = np.frombuffer(r["weights"], "<f4")
    w = train(x, np.array([label[r["pattern"]] for r in sample], np.float32)).astype(np.float64)

    def score(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            code, held = b.column(1).to_pylist(), b.column(2).to_pylist()
            n = np.fromiter((len(h) // 2 for h in held), np.int64, len(held))
            part = np.frombuffer(b"".join(b.column(3).to_pylist()), "<f4") * w[np.frombuffer(b"".join(held), "<u2")]
            sums = np.bincount(np.repeat(np.arange(len(n)), n), weights=part, minlength=len(n))
            yield pa.RecordBatch.from_arrays([b.column(0), b.column(1), pa.array([label[c] for c in code], pa.float64()), pa.array(np.round(1 / (1 + np.exp(-(sums + w[-1]))), 6))], ["doc_id", "pattern", "weak_label", "score"])

    out = voted.select("doc_id", "pattern", "slots", "weights").mapInArrow(score, "doc_id long, pattern int, weak_label double, score double")
    return out.select(shown("doc_id"), "pattern", "weak_label", "score", (F.col("score") >= 0.5).alias("kept"))


def op6_weak_label_scorer(spark: SparkSession, sf_dir: str) -> DataFrame:
    return quality_classifier(table(spark, sf_dir, "documents"))


ORACLE: dict[str, str] = {}
