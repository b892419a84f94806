"""The pipeline's stages in order: on the smallest table, on rows that only a row number tells apart, and against brute force."""

from __future__ import annotations

import collections
import hashlib
import random

import pytest

import corpus_pipeline as P
from boundspark.llm import simhash
from boundspark.llm.common import stage
from tests.llm.test_operators import byte_spans, quality_brute

DDL = "doc_id long, text string, lang string, source string, n_chars long, _gone int, _node int, _id int, _text string, row_number int, gone int, number int, text_left string, node int"


def test_stages_keep_columns_and_take_effect(spark, sf):
    docs = spark.read.parquet(f"{sf}/documents.parquet")
    columns, counts = docs.columns, [docs.count()]
    for name, fn in P.STAGES[:-1]:
        docs = stage(fn(spark, docs, sf))
        assert docs.columns == columns, name
        counts.append(docs.count())
    assert counts[0] > counts[1] >= counts[2] >= counts[3] == counts[4] > 0
    assert docs.where("n_chars <> length(text)").count() == 0
    packed = P.STAGES[-1][1](spark, docs, sf)
    assert packed.select("doc_id").distinct().count() == counts[-1]


def test_run_returns_the_packing(spark, sf):
    assert {"doc_id", "sequence_id", "offset"} <= set(P.run(spark, sf).columns)


def prose(seed: int, n: int = 80) -> str:
    r = random.Random(seed)
    common = "the of and to in is was for on that by with as at it from are an be this".split()
    return " ".join(r.choice(common) if r.random() < 0.4 else "".join(r.choice("etaoinshrdlu") for _ in range(r.randint(3, 8))) for _ in range(n))


def odd_rows() -> list[tuple]:
    """Null and shared ids, junk, copies, near copies, shared passages, and columns whose names the stages use."""
    base, passage = [prose(k) for k in range(12)], prose(99, 30)
    texts = [(k, t) for k, t in enumerate(base)]
    texts += [(None, "short junk"), (None, None), (None, base[0]), (None, base[1] + "  "), (3, base[3]), (3, "### | " * 30), (4, prose(50)), (50, base[5] + " end"), (50, base[6].upper())]
    texts += [(60, prose(61, 60) + " " + passage), (62, passage + " " + prose(63, 60)), (None, prose(64, 40) + " " + passage)]
    return [(i, t, "en", "s", 5, 1, 2, 3, "x", 4, 5, 6, "y", 7) for i, t in texts]


@pytest.fixture(scope="module")
def odd(spark):
    return spark.createDataFrame(odd_rows(), DDL).repartition(3)


def texts(df) -> list:
    return sorted(((r["doc_id"], r["text"]) for r in df.collect()), key=repr)


def test_rows_are_told_apart_by_their_number(spark, odd, tmp_path):
    """Each stage against brute force over its own input."""
    docs = odd
    # quality rules: no row with a null or shared id stays or goes with another
    rows = [(k, r["text"], r["lang"]) for k, r in enumerate(docs.collect())]
    verdict = quality_brute(rows)
    kept = stage(P.quality(spark, docs, ""))
    want = sorted(((r["doc_id"], r["text"]) for k, r in enumerate(docs.collect()) if verdict[k][6]), key=repr)
    assert kept.columns == odd.columns and len(texts(kept)) == len(want) < len(rows)
    # exact dedup: one row of each text, with the smallest id, null first
    one = stage(P.exact(spark, kept, ""))
    groups = collections.defaultdict(list)
    for i, t in texts(kept):
        groups[" ".join((t + "|").split())].append(-1 if i is None else i)
    assert one.columns == odd.columns
    left = [(-1 if i is None else i, t) for i, t in texts(one)]
    assert sorted(i for i, _ in left) == sorted(sum(([min(g)] for g in _by_norm(kept).values()), []))
    # near dedup: shingle sets of 0.8 meet, and fingerprints within two bits
    single = stage(P.near(spark, one, ""))
    assert single.columns == odd.columns and len(texts(single)) == len(_classes([t for _, t in texts(one)]))
    # substrings: as many rows, and the bytes that the operator's law leaves
    cut = stage(P.substrings(spark, single, ""))
    law = byte_spans([(-1 if i is None else i, t.encode()) for i, t in texts(single)])
    got = [hashlib.sha256(t.encode()).hexdigest() for _, t in texts(cut)]
    assert cut.columns == odd.columns and sorted(got) == sorted(x[4] for x in law) and sum(x[2] for x in law) > 0
    packed = P.packing(spark, cut, "").collect()
    assert len({(x["sequence_id"], x["offset"]) for x in packed}) == len(packed) == cut.count()


def _by_norm(df) -> dict:
    import re

    groups = collections.defaultdict(list)
    for r in df.collect():
        groups[re.sub("[\x20\x09-\x0D]+", " ", r["text"] or "")].append(-1 if r["doc_id"] is None else r["doc_id"])
    return groups


def _classes(some: list[str]) -> set[int]:
    sets = [{tuple(t.lower().split()[k : k + 5]) for k in range(max(1, len(t.split()) - 4))} for t in some]
    label = list(range(len(some)))
    for _ in some:
        for i in range(len(some)):
            for j in range(i):
                if 10 * len(sets[i] & sets[j]) >= 8 * len(sets[i] | sets[j]):
                    label[i] = label[j] = min(label[i], label[j])
    return set(label)


def test_equal_rows_leave_one(spark):
    t = prose(7)
    docs = spark.createDataFrame([(5, t)] * 3 + [(None, t + " x y")] * 2, "doc_id long, text string")
    assert [(r["doc_id"], r["text"]) for r in P.exact(spark, docs, "").orderBy("doc_id").collect()] == [(None, t + " x y"), (5, t)]
    assert P.substrings(spark, docs.withColumn("n_chars", P.F.lit(1)), "").count() == 5


def test_empty_table_through_all_stages(spark, odd):
    docs = odd.limit(0)
    for _, fn in P.STAGES[:-1]:
        docs = stage(fn(spark, docs, ""))
        assert docs.count() == 0 and docs.columns == odd.columns
    assert P.packing(spark, docs, "").count() == 0


def test_recall_of_near_copies(spark, sf):
    """Of the pairs of whole documents that are 0.8 similar on five-word shingles, nine in ten or more lose a member."""
    docs = spark.read.parquet(f"{sf}/documents.parquet")
    held = [(r["doc_id"], r["text"]) for r in docs.collect() if r["text"] and r["text"].split()]
    words = {i: t.lower().split() for i, t in held}
    sets = {i: {tuple(w[k : k + 5]) for k in range(max(1, len(w) - 4))} for i, w in words.items()}
    ids = sorted(sets)
    pairs = [(a, b) for k, a in enumerate(ids) for b in ids[k + 1 :] if 10 * len(sets[a] & sets[b]) >= 8 * len(sets[a] | sets[b])]
    kept = {r["doc_id"] for r in P.near(spark, docs, sf).select("doc_id").collect()}
    caught = sum(not {a, b} <= kept for a, b in pairs)
    assert pairs and caught >= 0.9 * len(pairs)
    assert simhash.fingerprint(b"") == 0
