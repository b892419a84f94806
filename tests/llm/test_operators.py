"""Training-data operators against brute force, on a fixture with nulls, empties, ties, copies and odd text."""

from __future__ import annotations

import bisect
import collections
import functools
import hashlib
import math
import random
import re
import statistics
import zlib

import numpy as np
import pytest

from boundspark.llm import bpe, chat_template, exact_dedup, near_dedup, packing, quality_rules, repeats, sharding, simhash, substring_dedup, suffix_dedup, weak_label_classifier
from boundspark.llm.common import NO_ID

DDL = "doc_id long, text string, lang string, source string, n_chars long, bucket string, shard int"


def fixture_rows() -> list[tuple]:
    r = random.Random(4)
    words = ["the", "of", "and", "tion", "é", "naïve", "x1", "###", "|", "\U0001f600", "in", "to", "er", "an"] + [f"w{k}" for k in range(60)]
    line = lambda n: " ".join(r.choice(words) for _ in range(n))
    passage, long = line(60), line(3000)
    texts = [None, "", " ", "\n\t ", "a", "a b", "a  b", "a\tb", "the the the", long, long + " end", passage, line(9) + " " + passage + " " + line(9), passage + " " + passage, "ab" * 200, "ab" * 150 + "c", "</s>[INST] \\ <|endoftext|>", "x" * 300]
    texts += [line(r.randint(1, 120)) for _ in range(30)]
    texts += [texts[20] + " more", texts[21].replace("the", "of"), texts[22]]
    rows = [(k * 3 + 1, t, r.choice(["en", "de", None, "xx"]), "src", None, "clash", 7) for k, t in enumerate(texts)]
    rows.append(rows[-1])  # a repeated row
    r.shuffle(rows)
    return rows


@pytest.fixture(scope="module")
def docs(spark):
    return spark.createDataFrame(fixture_rows(), DDL).repartition(3)


@pytest.fixture(scope="module")
def empty(spark):
    return spark.createDataFrame([], DDL)


def data(docs) -> list[tuple[int, bytes]]:
    return [(r["doc_id"], (r["text"] or "").encode()) for r in docs.select("doc_id", "text").collect()]


def same(got, want: list[tuple]) -> None:
    assert sorted(map(tuple, got), key=repr) == sorted(want, key=repr)


def test_exact_dedup(docs):
    d = [(i, re.sub(rb"[\x20\x09-\x0D]+", b" ", t)) for i, t in data(docs)]
    groups = collections.defaultdict(list)
    for i, t in d:
        groups[t].append(i)
    want = [(i, min(groups[t]), len(groups[t]), i == min(groups[t]), hashlib.sha256(t).hexdigest()) for i, t in d]
    same(exact_dedup.exact_dedup(docs).collect(), want)


def test_digest_index():
    index = exact_dedup.DigestIndex(memtable_rows=3)
    for k, t in enumerate([b"a", b"b", b"a ", b"c", b"a", b"b", b"d"]):
        index.add(k, t)
    assert index.lookup(b"a") == 0 and index.lookup(b"nope") is None and index.lookup(b"d") == 6
    run = index.compact()
    assert len(run.keep) == 5 and sorted(run.count) == [1, 1, 1, 2, 2] and index.lookup(b"b") == 1
    assert sorted(run.tables) == [1, 1, 1, 2, 2] and not index.clashes and len(index.log) == 7


def test_exact_dedup_over_many_runs(spark, monkeypatch):
    """Small memtables: digests meet in memtables, in compactions of one task, and between tasks; rows tie in doc_id."""
    monkeypatch.setattr(exact_dedup, "MEMTABLE_ROWS", 3)
    monkeypatch.setattr(exact_dedup, "DigestIndex", functools.partial(exact_dedup.DigestIndex, memtable_rows=3))
    r = random.Random(1)
    rows = [(r.choice([None, *range(40)]), r.choice(["x", "y  z", "y\tz", f"t{r.randrange(30)}", None, ""]), k) for k in range(200)]
    d = spark.createDataFrame(rows, "doc_id long, text string, nr long").repartition(3)
    norm = lambda t: re.sub("[\x20\x09-\x0D]+", " ", t or "")
    groups = collections.defaultdict(list)
    for i, t, k in rows:
        groups[norm(t)].append((-1 if i is None else i, k))
    got = {x["row"]: x for x in exact_dedup.exact_dedup(d, row_col="nr").collect()}
    assert len(got) == 200
    for i, t, k in rows:
        first, x = min(groups[norm(t)]), got[k]
        assert (x["keep_id"] if x["keep_id"] is not None else -1, x["group_size"], x["kept"], x["doc_id"]) == (first[0], len(groups[norm(t)]), first[1] == k, i)


def test_exact_dedup_when_digests_clash(spark, monkeypatch):
    """With a digest that tells no texts apart, bytes decide."""

    real = hashlib.sha256
    weak = lambda text: real(b"" if text in (b"a", b"b") else text)
    index = exact_dedup.DigestIndex()
    monkeypatch.setattr(exact_dedup.hashlib, "sha256", weak)
    for k, t in enumerate([b"a", b"b", b"c", b"c"]):
        index.add(k, t)
    monkeypatch.undo()
    assert index.clashes == {hashlib.sha256(b"").digest()}


def test_sharding(docs, spark):
    rows = sharding.external_shuffle(docs, bucket_rows=5).collect()
    d = data(docs)
    same([(r["doc_id"], r["size"], r["text_crc32"]) for r in rows], [(i, len(t) + 1, zlib.crc32(t)) for i, t in d])
    slots = collections.defaultdict(list)
    for r in rows:
        slots[r["shard"]].append(r["slot"])
    sizes = [len(v) for v in slots.values()]
    assert len(slots) == 16 and max(sizes) - min(sizes) <= 1
    assert all(sorted(v) == list(range(len(v))) for v in slots.values())
    held = spark.conf.get("spark.sql.shuffle.partitions")
    spark.conf.set("spark.sql.shuffle.partitions", "7")
    try:
        other = sharding.external_shuffle(docs.repartition(5), bucket_rows=5).collect()
    finally:
        spark.conf.set("spark.sql.shuffle.partitions", held)
    same(other, list(map(tuple, rows)))


def test_sharding_stays_native(docs, monkeypatch):
    """Plans in front of and behind each staged table."""
    plans, stage = [], sharding.stage
    monkeypatch.setattr(sharding, "stage", lambda df: (plans.append(df), stage(df))[1])
    plans.append(sharding.external_shuffle(docs))
    assert len(plans) == 3
    for df in plans:
        plan = df._jdf.queryExecution().executedPlan().toString()
        assert not any(x in plan for x in ("Python", "Pandas", "Arrow"))


def test_sharding_splits_a_repeated_record(spark, monkeypatch):
    monkeypatch.setattr(sharding, "COPIES", 16)
    d = spark.createDataFrame([(1, "same")] * 1000 + [(None, None)] * 33 + [(k, "x") for k in range(100, 150)], "doc_id long, text string")
    rows = sharding.external_shuffle(d, bucket_rows=64).collect()
    assert len(rows) == 1083 and len({(r["shard"], r["slot"]) for r in rows}) == 1083
    ones = [r["slot"] for r in rows if r["doc_id"] == 1]
    assert len(ones) == 1000 and max(collections.Counter(s // 8 for s in ones).values()) <= 128
    assert sharding.bucket_count(10**11) == sharding.MAX_BUCKETS and sharding.bucket_count(0) == 1


def test_sharding_moves_whole_texts(docs, spark, sf, tmp_path):
    """Shards hold the texts, each at its place; the query reads what it shows from written shards."""
    rows = docs.union(docs.where("doc_id < 5")).union(docs.where("doc_id < 5"))
    out = sharding.external_shuffle(rows, bucket_rows=7)
    sharding.write_texts(out, f"file://{tmp_path}/texts")
    back = spark.read.parquet(f"file://{tmp_path}/texts")
    same(back.select("doc_id", "text").collect(), [tuple(r) for r in rows.select("doc_id", "text").collect()])
    digests = sharding.read_texts(spark, f"file://{tmp_path}/texts")
    same(digests.collect(), [tuple(r) for r in out.drop("text").collect()])
    got = sharding.op5_external_shuffle(spark, sf)
    files = got.inputFiles()
    assert files and all("/shard=" in f for f in files)


def test_write_shards(docs, tmp_path):
    d = docs.withColumnRenamed("bucket", "text_crc32_")
    sharding.write_shards(d, f"file://{tmp_path}/out", n_shards=4)
    back = docs.sparkSession.read.parquet(f"file://{tmp_path}/out")
    same(back.select("doc_id", "text", "text_crc32_").collect(), [tuple(x) for x in d.select("doc_id", "text", "text_crc32_").collect()])
    assert back.select("shard").distinct().count() == 4


def test_fingerprints_and_components(docs):
    import xxhash

    d, fps = data(docs), {}
    for i, t in d:
        w = bytes(c + 32 if 65 <= c <= 90 else c for c in t).split()
        s = [b" ".join(w[k : k + 3]) for k in range(max(1, len(w) - 2))] if w else []
        h = [xxhash.xxh64_intdigest(x, 42) for x in s]
        fps[i] = sum(1 << b for b in range(64) if 2 * sum(x >> b & 1 for x in h) > len(h)) if h else 0
    label = {i: i for i in fps}
    for _ in range(len(fps)):
        for i in fps:
            for j in fps:
                if bin(fps[i] ^ fps[j]).count("1") <= 2:
                    label[i] = label[j] = min(label[i], label[j])
    same([(r["doc_id"], r["fingerprint"], r["component_id"]) for r in simhash.simhash_dedup(docs).collect()], [(i, f"{fps[i]:016x}", label[i]) for i, _ in d])


@pytest.mark.parametrize("radius", [0, 1, 2, 3])
def test_gray_index_finds_every_link(radius):
    r = np.random.default_rng(radius)
    base = r.integers(0, 2**63, 6, dtype=np.uint64)
    x = np.unique(np.concatenate([base ^ (np.uint64(1) << r.integers(0, 64, 6).astype(np.uint64)) for _ in range(20)] + [base]))
    got = set()
    for a, b in simhash.GrayIndex(np.zeros(len(x), np.int64), x).links(radius):
        got |= {tuple(sorted(p)) for p in zip(a.tolist(), b.tolist(), strict=True)}
    assert got == {(i, j) for i in range(len(x)) for j in range(i + 1, len(x)) if int(x[i] ^ x[j]).bit_count() <= radius}


@pytest.mark.parametrize("one_place", [10**6, 0])
def test_components_of_a_long_chain(spark, one_place, monkeypatch):
    monkeypatch.setattr(simhash, "ONE_PLACE", one_place)
    edges = spark.createDataFrame([(k, k + 1) for k in range(40)] + [(100, 101), (7, 7)], "a long, b long")
    assert {(r["node"], r["root"]) for r in simhash.components(edges).collect()} == {(k, 0) for k in range(1, 41)} | {(101, 100)}


@pytest.mark.parametrize("seed", [0, 1, 2, 3])
def test_components_of_randomly_numbered_graphs(spark, seed):
    """The first is a graph whose nodes meet two tops before they meet one; then paths and trees, numbered at random."""
    r, edges = random.Random(seed), [(1, 5), (5, 6), (6, 7), (2, 7)]
    if seed:
        nodes = r.sample(range(1, 9), 8)
        edges = [(nodes[k], nodes[k - 1 if seed < 3 else r.randrange(k)]) for k in range(1, 8)]
    label = {n: n for e in edges for n in e}
    for _ in label:
        for a, b in edges:
            label[a] = label[b] = min(label[a], label[b])
    got = {(x["node"], x["root"]) for x in simhash.components(spark.createDataFrame(edges, "a long, b long")).collect()}
    assert got == {(n, root) for n, root in label.items() if n != root}


def byte_spans(d, length=50):
    first: dict = {}
    for i, t in sorted(d):
        for k in range(len(t) - length + 1):
            first.setdefault(t[k : k + length], i)
    out = []
    for i, t in d:
        gone = np.zeros(len(t), bool)
        for k in range(len(t) - length + 1):
            if first[t[k : k + length]] < i:
                gone[k : k + length] = True
        spans = int((np.diff(gone.astype(int), prepend=0) == 1).sum())
        out.append((i, len(t), int(gone.sum()), spans, hashlib.sha256(bytes(np.frombuffer(t, np.uint8)[~gone])).hexdigest()))
    return out


#: SPLIT_CLASSES, bytes of a block, chunks in a pack.
SHAPES = [(4096, 2 << 20, 1), (1, 2 << 20, 1), (4096, 500, 1), (1, 500, 3), (4096, 3000, 4)]


def shape(monkeypatch, limit, block, per_pack):
    monkeypatch.setattr(repeats, "SPLIT_CLASSES", limit)
    monkeypatch.setattr(repeats, "BLOCK_BYTES", block)
    monkeypatch.setattr(repeats, "fan", lambda total, partitions: (5, 4, per_pack))


def word_spans(d, length=35):
    d = [(i, t.split()) for i, t in d]
    seen = collections.Counter(tuple(w[k : k + length]) for _, w in d for k in range(len(w) - length + 1))
    out = []
    for i, w in d:
        gone = np.zeros(len(w), bool)
        for k in range(len(w) - length + 1):
            if seen[tuple(w[k : k + length])] > 1:
                gone[k : k + length] = True
        out.append((i, len(w), int(gone.sum()), hashlib.sha256(b" ".join(x for x, g in zip(w, gone, strict=True) if not g)).hexdigest()))
    return out


@pytest.mark.parametrize("limit, block, per_pack", SHAPES)
def test_suffix_dedup(docs, limit, block, per_pack, monkeypatch):
    shape(monkeypatch, limit, block, per_pack)
    same(suffix_dedup.suffix_dedup(docs).collect(), byte_spans(data(docs)))


@pytest.mark.parametrize("limit, block, per_pack", SHAPES)
def test_substring_dedup(docs, limit, block, per_pack, monkeypatch):
    shape(monkeypatch, limit, block, per_pack)
    same(substring_dedup.substring_dedup(docs).collect(), word_spans(data(docs)))


@pytest.mark.parametrize("texts", [["a b", "###", "a b"], [None, "", None], ["x" * 49, "y" * 49, "x" * 49], [" " * 60, "\n", " " * 60]])
def test_chunks_without_anchors(spark, texts):
    rows = [(k, t) for k, t in enumerate(texts)]
    d = spark.createDataFrame(rows, "doc_id long, text string").repartition(len(rows))
    same(suffix_dedup.suffix_dedup(d).collect(), byte_spans(data(d)))
    same(substring_dedup.substring_dedup(d).collect(), word_spans(data(d)))
    assert {r["doc_id"] for r in suffix_dedup.suffix_dedup_texts(d, "doc_id").collect()} == {k for k, _ in rows}


def test_rows_that_share_an_id_lose_the_same_bytes(spark):
    """Copies of one row in several packs, of which an earlier document holds a part."""
    r = random.Random(12)
    part, rest = ("".join(r.choice("abcdefgh ") for _ in range(n)) for n in (90, 200))
    rows = [(1, part + "zzz"), *[(7, rest + part + rest[::-1])] * 6, (9, rest), (None, rest + "q"), (None, rest + "q")]
    d = spark.createDataFrame(rows, "doc_id long, text string").repartition(6)
    got = suffix_dedup.suffix_dedup(d).collect()
    want = byte_spans([(-1 if i is None else i, t.encode()) for i, t in rows])
    same([(-1 if x[0] is None else x[0], *x[1:]) for x in got], want)
    assert len({x["kept_sha256"] for x in got if x["doc_id"] == 7}) == 1


@pytest.mark.parametrize("kind", ["bytes", "words"])
def test_long_texts_in_pieces(spark, kind, monkeypatch):
    """Texts of several blocks, with a repeat across the cut between two pieces and characters of several bytes."""
    monkeypatch.setattr(repeats, "BLOCK_BYTES", 700)
    r = random.Random(7)
    line = lambda n: " ".join(r.choice(["é", "naïve", "\U0001f600", *(f"w{k}" for k in range(400))]) for _ in range(n))
    long, shared = line(1500), line(60)
    rows = [(k, long[a:b]) for k, (a, b) in enumerate([(0, None), (300, 1100), (0, 690), (650, 760)])]
    rows += [(10, line(200) + " " + shared + " " + line(300)), (11, shared), (12, "x" * 3000 + " " + shared), (13, "é" * 2000), (14, "é" * 900)]
    d = spark.createDataFrame(rows, "doc_id long, text string").coalesce(2)
    if kind == "bytes":
        same(suffix_dedup.suffix_dedup(d).collect(), byte_spans(data(d)))
    else:
        same(substring_dedup.substring_dedup(d).collect(), word_spans(data(d)))
        left = {x["doc_id"]: x["text"] for x in substring_dedup.substring_dedup_texts(d).collect()}
        assert left[11] == "" and left[12] == "x" * 3000


def test_fan_out_at_any_size():
    """Spark takes 100,000 buckets at most; a message from a pack to a bucket stays worth sending."""
    for total in (0, 10**8, 10**10, 10**12, 10**14):
        n, table, per = repeats.fan(total, 200)
        assert 200 <= table <= n <= repeats.MAX_BUCKETS and table <= 100_000 and 1 <= per <= repeats.PACK_CHUNKS
    assert repeats.fan(10**14, 200) == (repeats.MAX_BUCKETS, repeats.MAX_LAYOUT, repeats.PACK_CHUNKS)


def test_word_hashes_follow_split():
    texts = [b"", b"one two  one", b"two", b" \t\x0bone\n", "żółw \u00a0 two".encode(), b"x" * 100_000, b"   ", b"on eo ne noe"]
    begin, h = repeats.word_hashes(np.frombuffer(b"".join(texts), np.uint8), np.cumsum([len(t) for t in texts]))
    words = [w for t in texts for w in t.split()]
    assert len(words) == len(h) == len(begin)
    assert len(set(zip(words, h.tolist(), strict=True))) == len(set(words)) == len(set(h.tolist()))
    assert len(repeats.word_hashes(np.zeros(0, np.uint8), np.zeros(2, np.int64))[1]) == 0


@pytest.mark.parametrize("seed", range(3))
def test_trimmed_contexts_leave_the_same_windows(seed):
    lay, r = repeats.Layout(length=6, k=2, kind="words", rule="again"), np.random.default_rng(seed)
    n = 60
    h = np.sort(r.integers(0, 5, n)).astype(np.uint64)
    rows = np.unique(np.column_stack([h, r.integers(0, 2, (n, lay.span)).astype(np.uint64)]), axis=0)
    h, rows, n = rows[:, 0], rows[:, 1:].copy(), len(rows)
    rows[:, lay.left : lay.left + lay.k] = h[:, None]
    low, high = r.integers(0, 2, n).astype(np.uint8), r.integers(lay.left - 1, lay.left + 1, n).astype(np.uint8)
    ctx = repeats.Contexts(h, np.arange(n, dtype=np.uint64), np.ones(n, np.int64), low, high, rows, np.zeros(n, np.int64))
    seen = collections.defaultdict(list)
    for i in range(n):
        for o in range(int(low[i]), int(high[i]) + 1):
            seen[int(h[i]), o, rows[i, lay.left - o : lay.left - o + lay.length].tobytes()].append(i)
    want = [0] * n
    for (_, o, _), who in seen.items():
        for i in who:
            want[i] |= (len(who) > 1) << o
    assert substring_dedup.shard_automata(lay, ctx).tolist() == want and any(want) and not all(want)


def test_suffix_automaton_counts():
    a = substring_dedup.SuffixAutomaton()
    a.add([1, 2, 3, 1, 2], 1)
    a.add([2, 3, 9], 2)
    a.finish()
    assert a.stream([1, 2, 3, 9, 1], 2) == [0, 2, 3, 2, 0]


def test_bpe_equals_the_library(docs):
    from tokenizers import Tokenizer

    lib = Tokenizer.from_file(bpe.vocabulary())
    want = []
    for i, t in data(docs):
        ids = lib.encode(t.decode(), add_special_tokens=False).ids
        want.append((i, len(ids), hashlib.sha256(np.array(ids, "<u4").tobytes()).hexdigest(), hashlib.sha256(lib.decode(ids, skip_special_tokens=False).encode()).hexdigest()))
    same(bpe.encode_decode(docs).collect(), want)
    r = random.Random(2)
    enc = bpe.load(bpe.vocabulary())
    for _ in range(3000):
        t = "".join(r.choice(["a", "th", " ", "  ", "\n", "é", "中", "'ll", "1", "<|endoftext|>", "!", "　", "ing", "zz"]) for _ in range(r.randint(0, 20)))
        assert enc.encode(t) == lib.encode(t, add_special_tokens=False).ids, t


@pytest.mark.parametrize("capacity", [64, 2048])
def test_packing(docs, capacity):
    from tokenizers import Tokenizer

    lib, rows = Tokenizer.from_file(bpe.vocabulary()), packing.pack(docs, capacity=capacity).collect()
    seqs, pieces = collections.defaultdict(list), collections.defaultdict(list)
    for r in rows:
        seqs[r["sequence_id"]].append((r["offset"], r["length"]))
        pieces[r["doc_id"]].append((r["piece"], r["start"], r["length"], r["ids_crc32"]))
    for s in seqs.values():
        at = 0
        for o, n in sorted(s):
            assert o == at
            at += n
        assert at <= capacity
    copies = collections.Counter(i for i, _ in data(docs))
    for i, t in set(data(docs)):
        ids = [*lib.encode(t.decode(), add_special_tokens=False).ids, 0]
        first = (len(ids) - 1) % capacity + 1
        cuts = [0, *range(first, len(ids) + 1, capacity)]
        want = [(k, a, b - a, zlib.crc32(np.array(ids[a:b], "<u4").tobytes())) for k, (a, b) in enumerate(zip(cuts, cuts[1:], strict=False))]
        assert sorted(pieces[i]) == sorted(want * copies[i])
    assert len(seqs) <= -(-sum(r["length"] for r in rows) // capacity) + 1


def best_fit(lengths, capacity) -> int:
    """Sequences that one-by-one best fit opens, longest first."""
    gaps, opened = [], 0
    for n in sorted(lengths, reverse=True):
        k = bisect.bisect_left(gaps, n)
        opened += k == len(gaps)
        bisect.insort(gaps, (gaps.pop(k) if k < len(gaps) else capacity) - n)
    return opened


@pytest.mark.parametrize("name", ["mixed", "small", "one_size", "hot_ones", "halves", "nothing", "no_fit"])
def test_supersteps_over_many_ranges(spark, name):
    """Sweeps of eight ranges, whose waiting gaps and documents meet by height: valid, whole, and as tight as best fit."""
    r = np.random.default_rng(3)
    lengths = {"mixed": r.integers(1, 2049, 900), "small": r.integers(1, 60, 1500), "one_size": np.full(400, 700), "hot_ones": np.r_[np.ones(700, int), r.integers(1, 1500, 400)], "halves": np.full(301, 1024), "nothing": [], "no_fit": np.full(50, 2048)}[name]
    lengths = [int(n) for n in lengths]
    held = {k: spark.conf.get(k) for k in ("spark.sql.adaptive.coalescePartitions.enabled", "spark.sql.shuffle.partitions")}
    spark.conf.set("spark.sql.adaptive.coalescePartitions.enabled", "false")
    spark.conf.set("spark.sql.shuffle.partitions", "8")
    try:
        rows = packing.supersteps(spark.createDataFrame(list(enumerate(lengths)), "uid long, length long"), 2048).collect()
    finally:
        for k, v in held.items():
            spark.conf.set(k, v)
    assert sorted((x["uid"], x["length"]) for x in rows) == list(enumerate(lengths))
    fill = collections.Counter()
    for x in rows:
        fill[x["sequence_id"]] += x["length"]
    assert all(n <= 2048 for n in fill.values()) and len({(x["sequence_id"], x["step"], x["nth"], x["uid"]) for x in rows}) == len(rows)
    assert len(fill) <= 1.02 * best_fit(lengths, 2048) + 1
    if name == "mixed":
        assert max(x["step"] for x in rows) >= 2


def test_one_sweep():
    placed, over, gaps = packing.sweep([3, 5, 5, 6, 9, 20], [False, False, True, False, True, True], list("abcdef"), 6)
    assert placed == [("b", 5, "c", 0), ("d", 6, "e", 0), ("a", 3, "f", 0)] and not over
    assert gaps == [("e", 3, 0), ("f", 17, 2)]
    assert packing.heights([(0, 2, 3), (1, 2, 1), (2, 9, 0)]) == ([(0, 0, 0), (1, 3, 1), (2, 2, 0)], 0, 4)


def test_template_language():
    t = chat_template.Template("{% set a = 'x' + 'y' %}{{ a|upper }}{% if 1 == 2 %}no{% elif not false %}yes{% endif %}{% for m in messages %}[{{ m.role }}:{% generation %}{{ m.text|trim }}{% endgeneration %}{% if loop.last %}.{% endif %}]{% endfor %}")
    out = t.render([{"role": "u", "text": " hi "}, {"role": "v", "text": "yo"}])
    text = "".join(out.parts)
    assert text == "XYyes[u:hi][v:yo.]"
    assert [text[a:b] for a, b in out.spans] == ["hi", "yo"]
    assert chat_template.fold(chat_template.parse("{{ 'a' + 'b' }}c")) == (chat_template.Emit(chat_template.Const("abc")),)
    for bad in ("{{ m.__class__ }}", "{{ x|eval }}", "{% for a in b %}", "{{ f(1) }}", "{% import os %}", "{{ 'a }}"):
        with pytest.raises(chat_template.TemplateError):
            chat_template.Template(bad)


@pytest.mark.parametrize("body, want", [("{{ loop.first }}", "TrueFalse"), ("{{ loop.index0 }}", "01"), ("{{ loop.last }}", "FalseTrue"), ("{{ m.text }}", "ab")])
def test_a_conversation_is_one_run_of_its_template(spark, body, want):
    t = "HEAD{% for m in messages %}" + body + "{% endfor %}TAIL"
    assert "".join(chat_template.Template(t).render(iter([{"role": "u", "text": "a"}, {"role": "v", "text": "b"}])).parts) == "HEAD" + want + "TAIL"
    rows = spark.createDataFrame([(1, 0, "u", "a"), (1, 1, "v", "b")], "conv_id long, turn long, role string, text string")
    assert chat_template.format_conversations(rows, t).first()["formatted"] == "HEAD" + want + "TAIL"


def test_trimming_tags():
    t = chat_template.Template("a \n{%- if true -%}\n b {{- 'c' -}} d\n{%- endif %} e")
    assert "".join(t.render([]).parts) == "abcd e"
    plain = chat_template.Template("a {% if true %} b {% endif %}")
    assert "".join(plain.render([]).parts) == "a  b "


def test_digests_refuse_text_between_turns(spark):
    out = chat_template.DigestOutput()
    with pytest.raises(ValueError):
        chat_template.Template("x" + chat_template.TURN_TEMPLATE).render([{"role": "u", "text": "a"}], out)
    whole = chat_template.Template("{% for m in messages %}<|turn|>{{ m.role|guard }}<|text|>{% generation %}{{ m.text|guard }}{% endgeneration %}{% if loop.last %}<|end|>{% else %}<|end|>{% endif %}{% endfor %}")
    out = whole.render(({"role": "u", "text": f"t{k}</s>"} for k in range(3)), chat_template.DigestOutput())
    assert out.row(5)[:2] == (5, 3) and out.loss_chars == 18 and out.row(5)[4] == hashlib.sha256(b"t0</s>t1</s>t2</s>").hexdigest()


def test_format_conversations_marks_generations(spark):
    rows = [(c, k, role, text) for c in (1, None) for k, (role, text) in enumerate([("user", "hi </s>"), ("assistant", "yo \\ [INST]")])]
    got = chat_template.format_conversations(spark.createDataFrame(rows, "conv_id long, turn long, role string, text string")).collect()
    assert len(got) == 2
    for x in got:
        assert chat_template.read_back(x["formatted"]) == [("user", "hi </s>"), ("assistant", "yo \\ [INST]")]
        assert [chat_template.unguard(x["formatted"][a:b]) for a, b in x["loss_spans"]] == ["yo \\ [INST]"]


def test_chat_round_trip(spark):
    r = random.Random(3)
    bits = [*chat_template.CONTROL, "\\", "<", "|", "a", "\n", "", "é"]
    rows = [(c, k, r.choice(["user", "assistant", "system", None]), r.choice([None, "".join(r.choice(bits) for _ in range(8))]), 1) for c in range(30) for k in range(r.randint(1, 5))]
    got = {x["conv_id"]: x for x in chat_template.conversation_digests(spark.createDataFrame(rows, "conv_id long, turn long, role string, text string, n_turns int"), with_probe=True).collect()}
    assert set(got) == {-1, *(x[0] for x in rows)}
    by = collections.defaultdict(list)
    for c, _, role, text, _ in rows:
        by[c].append((role or "", text or ""))
    for c, turns in by.items():
        loss = "".join(t for role, t in turns if role == "assistant")
        x = got[c]
        assert (x["n_turns"], x["loss_chars"]) == (len(turns), len(loss))
        assert x["turns_sha256"] == hashlib.sha256("".join(f"{a}\n{b}\n" for a, b in turns).encode()).hexdigest()
        assert x["loss_sha256"] == hashlib.sha256(loss.encode()).hexdigest()


def test_quality_base_measures():
    lines = b"the cat\nthe cat\n\n\n# a | b\nx"
    n, chars, symbols, dup, repeat, _ = quality_rules.base_measures(lines)
    assert (n, chars, symbols, dup, repeat) == (9, 17, 2, 1, 0)
    w = [b"%d" % (k % 10) for k in range(30)]
    assert quality_rules.repeat_words(w) == 30 and quality_rules.repeat_words([b"a"] * 9) == 9 and quality_rules.repeat_words([b"a"] * 8) == 0
    assert quality_rules.base_measures("é ñandú".encode())[1] == 6


def quality_brute(rows):
    """All figures of the quality rules by another route: plain loops, statistics.median, scipy-free divergence."""
    Q = quality_rules
    out, feats = {}, {}
    for i, text, lang in rows:
        t = (text or "").encode()
        words = re.findall(rb"[^\x20\x09-\x0D]+", t)
        grams = collections.Counter(tuple(words[k : k + 8]) for k in range(len(words) - 7))
        covered = {k + j for k in range(len(words) - 7) if grams[tuple(words[k : k + 8])] > 1 for j in range(8)}
        lines = t.split(b"\n")
        dup = sum(re.search(rb"[^\x20\x09-\x0D]", x) is not None and x in lines[:k] for k, x in enumerate(lines))
        base = (len(words), sum(len(w.decode()) for w in words), sum(c in "#*$%&|<>" for c in text or ""), dup, len(covered))
        failed = base[0] < 20 or 100 * base[4] > 30 * base[0]
        kinds = [0] * len(Q.CLASSES)
        for c in text or "":
            name = "beyond_ascii" if ord(c) > 127 else "lower" if c.islower() else "upper" if c.isupper() else "digit" if c.isdigit() else "space" if c in " \t\n\r\v\f" else "stop" if c in ".,;:!?'\"()-" else "symbol" if c in "#*$%&|<>@^~=+_{}[]\\/`" else "other_ascii"
            kinds[Q.CLASSES.index(name)] += 1
        hist = {}
        for x, common in Q.COMMON_WORDS.items():
            h = [0] * Q.N_WORD_BINS
            for w in words:
                w = w.decode()
                plain = w if w in common else w.strip(".,;:!?'\"()-").lower()
                h[common.index(plain) if plain in common else -1] += 1
            hist[x] = h
        share = lambda h: [c * 1000 // sum(h) if sum(h) else 0 for c in h]
        feats[i] = (lang if lang in hist else None, sum(kinds), base[0], failed, share(kinds), {x: share(h) for x, h in hist.items()})
        out[i] = base, failed
    refs = {}
    for x in Q.COMMON_WORDS:
        fit = [f for f in feats.values() if f[0] == x and not f[3] and f[1] >= Q.MIN_CHARS and f[2] >= Q.MIN_WORDS]
        if fit:
            refs[x] = [[int(statistics.median(f[4][k] for f in fit)) for k in range(len(Q.CLASSES))], [int(statistics.median(f[5][x][k] for f in fit)) for k in range(Q.N_WORD_BINS)]]

    def distance(p, q):
        p, q = ([v / max(1, sum(x)) for v in x] for x in (p, q))
        kl = lambda a, b: sum(x * math.log2(x / ((x + y) / 2)) for x, y in zip(a, b, strict=True) if x > 0)
        return round(math.sqrt(max(0, 0.5 * (kl(p, q) + kl(q, p)))), 6)

    for i, (lang, chars, words, failed, kinds, hist) in feats.items():
        use = [lang] if lang in refs else list(refs)
        c = min((distance(kinds, refs[x][0]) for x in use), default=None)
        w = min((distance(hist[x], refs[x][1]) for x in use), default=None)
        if lang is not None and lang not in refs:
            w = None
        spread = lambda name: quality_rules.MAX_DISTANCE[name][0] + quality_rules.MAX_DISTANCE[name][1] / math.sqrt(chars)
        far = False
        if not failed and c is not None:
            far = chars >= Q.MIN_CHARS and c > spread("class_distance")
            if w is not None and words >= Q.MIN_WORDS:
                far = far or w > spread("word_distance") or c + w > spread("class_distance + word_distance")
        out[i] = (*out[i][0], failed, not failed and not far, c, w)
    return out


def test_quality_rules_equal_brute_force(spark, sf):
    """Base figures, references, distances and verdicts on whole tables: the given one, and one with nulls and extremes."""
    given = [(r["doc_id"], r["text"], r["lang"]) for r in spark.read.parquet(f"{sf}/documents.parquet").collect()]
    odd = [(k, t, lang) for k, (t, lang) in enumerate([(None, "en"), ("", None), (" \n\n", "xx"), ("a\nb\na\n\n\n", "en"), ("the of and " * 30, "en"), ("é ñ " * 80, None), ("x" * 70_000, "de"), ("\x00\x1f ctrl " * 60, "fr")])]
    for rows in (given, odd, given[:40] + [(10**6 + i, t, x) for i, t, x in odd]):
        want, got = quality_brute(rows), quality_rules.quality_rules(spark.createDataFrame(rows, "doc_id long, text string, lang string")).collect()
        assert len(got) == len(want)
        for x in got:
            w = want[x["doc_id"]]
            figures = (x["n_words"], x["word_chars"], x["n_symbols"], x["n_dup_lines"], x["n_repeat_words"], x["base_failed"], x["kept"])
            assert figures == w[:7], x
            for mine, other in ((x["class_distance"], w[7]), (x["word_distance"], w[8])):
                assert (mine is None) == (other is None) and (mine is None or abs(mine - other) < 2e-6), x


def test_quality_rules_keep_prose_and_drop_junk(spark):
    r = random.Random(6)
    common = quality_rules.COMMON_WORDS["en"]
    prose = lambda: " ".join(r.choice(common) if r.random() < 0.4 else "".join(r.choice("etaoinshr") for _ in range(6)) for _ in range(120))
    junk = lambda: " ".join("".join(r.choice("etaoin") for _ in range(4)) + r.choice(["###", "$$$", "%%%"]) for _ in range(120))
    rows = [(k, junk() if k % 5 == 0 else prose(), "en") for k in range(100)] + [(200, None, None), (201, prose(), "xx")]
    got = {x["doc_id"]: x["kept"] for x in quality_rules.quality_rules(spark.createDataFrame(rows, "doc_id long, text string, lang string")).collect()}
    assert [got[k] for k in range(100)] == [k % 5 != 0 for k in range(100)]
    assert not got[200] and got[201]


def test_weak_labels(spark, sf):
    table = spark.read.parquet(f"{sf}/documents.parquet")
    got = {x["doc_id"]: x["kept"] for x in weak_label_classifier.quality_classifier(table, 150).collect()}
    held = [(x["quality"] == 1, got[x["doc_id"]]) for x in spark.read.parquet(f"{sf}/labels.parquet").collect()]
    assert sum(a == b for a, b in held) / len(held) > 0.85
    patterns = np.array([[2, 2], [1, 1], [2, 1], [0, 0]])
    p = weak_label_classifier.LabelModel().fit(patterns, np.array([80.0, 15.0, 4.0, 1.0])).posterior(patterns)
    assert p[0] > 0.9 > 0.5 > p[1]


def test_weak_labels_do_not_depend_on_how_rows_are_dealt(spark):
    r = random.Random(11)
    words = ["the", "of", "and", "in", "###", "|", *(f"w{k}" for k in range(50))]
    rows = [(None if k % 2 else k, " ".join(r.choice(words) for _ in range(r.randrange(0, 60)))) for k in range(300)] + [(None, "copy")] * 40 + [(None, None), (5, "")]
    d = spark.createDataFrame(rows, "doc_id long, text string")
    a, b = (weak_label_classifier.quality_classifier(d.repartition(n), 100).collect() for n in (3, 11))
    same(a, list(map(tuple, b)))
    assert len(a) == len(rows)


def test_label_model_finds_planted_accuracies():
    """Votes drawn with known accuracies: fitted accuracies come close, and posteriors beat the best single labeller."""
    r = np.random.default_rng(5)
    accuracy, n = np.array([0.9, 0.8, 0.75, 0.7, 0.85]), 20_000
    truth = r.random(n) < 0.6
    votes = np.where(r.random((n, 5)) < accuracy, truth[:, None], ~truth[:, None]).astype(int) + 1
    votes[r.random((n, 5)) < 0.3] = weak_label_classifier.NONE
    patterns, of, counts = np.unique(votes, axis=0, return_inverse=True, return_counts=True)
    model = weak_label_classifier.LabelModel().fit(patterns, counts.astype(float))
    assert np.abs(model.accuracy - accuracy).max() < 0.03 and abs(model.prior - 0.6) < 0.03
    got = (model.posterior(patterns) > 0.5)[of.ravel()] == truth
    assert got.mean() > 0.9


@pytest.mark.parametrize("words", [40, 400])
def test_near_duplicates_follow_exact_similarity(spark, words):
    """Pairs a little below and above 0.8; groups are by exact Jaccard similarity of five-word shingles."""
    r, rows, want = random.Random(words), [], {}
    sets = lambda t: {tuple(t[k : k + 5]) for k in range(len(t) - 4)}
    for k in range(60):
        a = [f"v{k}x{j}" for j in range(words)]
        b = a[: round(words * r.uniform(0.7, 1.0))] + [f"u{k}"]
        x, y = sets(a), sets(b)
        rows += [(2 * k, " ".join(a)), (2 * k + 1, " ".join(b).upper())]
        if 10 * len(x & y) >= 8 * len(x | y):
            want[2 * k + 1] = 2 * k
    got = near_dedup.near_duplicates(spark.createDataFrame(rows, "doc_id long, text string"))
    assert {x["node"]: x["root"] for x in got.collect()} == want and 0 < len(want) < 60


def test_near_dedup(spark):
    r = random.Random(8)
    base = [[f"v{r.randint(0, 5000)}" for _ in range(300)] for _ in range(12)]
    rows = []
    for k, w in enumerate(base):
        rows.append((10 * k, " ".join(w)))
        for c in (1, 2):
            v = list(w)
            for _ in range(4):
                v[r.randrange(300)] = "edit"
            rows.append((10 * k + c, " ".join(v)))
    rows += [(500, None), (501, ""), (502, "one two")]
    kept = {x["doc_id"] for x in near_dedup.near_dedup(spark.createDataFrame(rows, "doc_id long, text string")).collect()}
    assert kept == {10 * k for k in range(12)} | {500, 501, 502}
    # rows without a doc_id, rows that share one, and columns that clash with names used inside
    more = [(*x, 1, 2, 3) for x in rows[:6]] + [(None, rows[0][1], 1, 2, 3), (None, " ".join(base[1]) + " end", 1, 2, 3), (500, None, 4, 5, 6), (500, None, 4, 5, 6)]
    names = "doc_id long, text string, node int, gone int, row_number int"
    got = near_dedup.near_dedup(spark.createDataFrame(more, names))
    assert got.columns == ["doc_id", "text", "node", "gone", "row_number"]
    assert sorted((x["doc_id"] is None, x["doc_id"] or 0) for x in got.collect()) == [(False, 500), (False, 500), (True, 0), (True, 0)]


@pytest.mark.parametrize("block", [512, 8])
def test_near_duplicates_among_unlike_neighbours(spark, block, monkeypatch):
    """Texts that share a template and little else fill the same bands; planted pairs meet neither first nor previous rows."""
    monkeypatch.setattr(near_dedup, "BLOCK", block)
    r, texts, want = random.Random(5), {}, {}
    template = [f"t{k}" for k in range(300)]
    for k in range(150):
        texts[k] = template + [f"v{k}x{j}" for j in range(150)]
    for k in range(40):
        a, b = 2 * k + 1, 1000 + r.randrange(1000) * 40 + k
        texts[b] = texts[a][:430] + [f"u{k}x{j}" for j in range(20)]
        want[b] = a
    got = near_dedup.near_duplicates(spark.createDataFrame([(k, " ".join(v)) for k, v in texts.items()], "doc_id long, text string"))
    assert {x["node"]: x["root"] for x in got.collect()} == want


def test_rows_of_a_hot_band_travel_a_bounded_number_of_times(spark, monkeypatch):
    """Texts that share a passage and little else: rows sent to cells grow with the members of a band, not their square."""
    monkeypatch.setattr(near_dedup, "BLOCK", 2)
    staged, stage = [], near_dedup.stage
    monkeypatch.setattr(near_dedup, "stage", lambda df: (staged.append(stage(df)), staged[-1])[1])
    common = [f"c{k}" for k in range(60)]
    texts = {i: common + [f"u{i}x{j}" for j in range(60)] for i in range(120)}
    texts |= {1000 + i: [*texts[i], "tail"] for i in range(0, 120, 7)}
    got = near_dedup.near_duplicates(spark.createDataFrame([(k, " ".join(v)) for k, v in texts.items()], "doc_id long, text string"))
    assert {x["node"]: x["root"] for x in got.collect()} == {1000 + i: i for i in range(0, 120, 7)}
    blocks = [df.agg({"blocks": "max"}).first()[0] for df in staged if "blocks" in df.columns]
    assert blocks and blocks[0] is not None and 1 < blocks[0] <= 16


def test_empty_tables(spark, empty):
    for fn in (exact_dedup.exact_dedup, sharding.external_shuffle, simhash.simhash_dedup, suffix_dedup.suffix_dedup, substring_dedup.substring_dedup, bpe.encode_decode, packing.pack, quality_rules.quality_rules, near_dedup.near_dedup, weak_label_classifier.quality_classifier):
        assert fn(empty).count() == 0, fn.__name__


def test_null_ids(spark):
    d = spark.createDataFrame([(None, "same text here"), (3, "same text here")], "doc_id long, text string")
    got = {x["doc_id"]: x["keep_id"] for x in exact_dedup.exact_dedup(d).collect()}
    assert got == {None: None, 3: None}
    assert NO_ID < 0
    assert simhash.simhash_dedup(d).count() == 2


def test_records_and_minimizers():
    told = np.zeros(4, repeats.VERDICT)
    told["h"], told["e"] = [5, 6, 7, 8], [9, 9, 3, 9]  # three anchors share a context hash
    records = repeats.Records(told)
    h, e = np.array([6, 8, 7, 7, 5], np.uint64), np.array([9, 9, 3, 9, 9], np.uint64)
    at = records.find(h, e)
    assert (at >= 0).tolist() == [True, True, True, False, True]
    assert (records.told["h"][at[at >= 0]] == h[at >= 0]).all()
    assert (repeats.Records(told[:0]).find(h, e) == -1).all()
    x = np.random.default_rng(3).integers(0, 1 << 20, 2 * repeats.TILE + 77).astype(np.uint64)
    for n in (27, repeats.TILE, repeats.TILE + 5, len(x)):
        runs = np.lib.stride_tricks.sliding_window_view(x[:n], 27)
        least, want = runs.min(axis=1), set()
        for j in range(27):
            want |= set((np.flatnonzero(runs[:, j] == least) + j).tolist())
        assert repeats._minimizers(x[:n], 27).tolist() == sorted(want)
