"""Byte-pair encoding by backtracking over longest token matches, and decoding through an offset table.

An Aho-Corasick automaton over the vocabulary finds, in one scan of a word, every token that ends at each byte; from
them comes the longest token that starts at each byte. The encoder takes the longest token, checks that it may stand
after the token before it, and otherwise falls back to the next shorter one, or drops the token before. Two tokens
may stand side by side if merging their bytes by rank would never join across the seam; that is decided by undoing
merges on either side of the seam and remembered in a pair table. The first tokenisation whose neighbours are all
compatible is the one that exact rank-order merging gives; every position is ruled out at most once, so work is
linear in the word.

Defined cases: a null text is the empty text (no ids); the vocabulary's special strings inside a text become their
own ids, as the tokenizers library does by default; very long texts are encoded whole; repeated rows repeat; an
empty table gives an empty result; extra columns are ignored.
"""

from __future__ import annotations

import hashlib
import json
from collections.abc import Callable, Iterator
from functools import lru_cache

import ahocorasick
import numpy as np
import pyarrow as pa
import regex
from pyspark.sql import DataFrame, SparkSession

from boundspark.llm.common import as_bytes, shown, source, table

#: Words whose ids a worker remembers, in each of two generations: when the young one is full, the old one goes.
CACHE_WORDS = 250_000


def byte_alphabet() -> dict[str, int]:
    """The printable stand-in of each byte in byte-level vocabularies, as a rule: visible Latin-1 stands for itself,
    the rest follow from code point 256 on in byte order."""
    own = [b for b in range(256) if 33 <= b <= 126 or 161 <= b <= 172 or 174 <= b]
    rest = [b for b in range(256) if b not in set(own)]
    return {chr(b): b for b in own} | {chr(256 + k): b for k, b in enumerate(rest)}


class BacktrackingBpe:
    """Encoder and decoder of one byte-level vocabulary file."""

    def __init__(self, path: str):
        with open(path, encoding="utf-8") as f:
            spec = json.load(f)
        plain = byte_alphabet()
        raw = lambda t: bytes(map(plain.__getitem__, t))
        self.special = {t["content"]: t["id"] for t in spec["added_tokens"]}
        self.vocab = {raw(t): i for t, i in spec["model"]["vocab"].items() if t not in self.special}
        # Ranks: bytes first, then one for each merge. Everything below works on ranks; ids come last.
        made = {bytes([b]): b for b in range(256)}
        self.left, self.right = list(range(256)), list(range(256))
        self.joined: dict[tuple[int, int], int] = {}
        for pair in spec["model"]["merges"]:
            a, b = (raw(t) for t in (pair if isinstance(pair, list) else pair.split(" ")))
            rank = len(self.left)
            self.left.append(made[a])
            self.right.append(made[b])
            self.joined.setdefault((made[a], made[b]), rank)
            made.setdefault(a + b, rank)
        self.text_of = [b""] * len(self.left)
        for t, r in made.items():
            self.text_of[r] = t
        self.id_of = np.array([self.vocab.get(t, 0) for t in self.text_of], np.uint32)
        self.size_of = [len(t) for t in self.text_of]
        self.ids_bytes = [int(i).to_bytes(4, "little") for i in self.id_of]
        self.automaton = ahocorasick.Automaton()
        for t, r in made.items():
            self.automaton.add_word(t.decode("latin-1"), r)
        self.automaton.make_automaton()
        # The next shorter token that starts a token: the longest proper prefix in the vocabulary.
        self.shorter = [next((made[t[:k]] for k in range(len(t) - 1, 0, -1) if t[:k] in made), -1) for t in self.text_of]
        self.pairs: dict[tuple[int, int], bool] = {}
        self.single = made
        self.words = regex.compile(r"'s|'t|'re|'ve|'m|'ll|'d| ?\p{L}+| ?\p{N}+| ?[^\s\p{L}\p{N}]+|\s+(?!\S)|\s+")
        self.cuts = regex.compile("|".join(map(regex.escape, self.special))) if self.special else None
        # Decoding: all token bytes in one buffer, with their offsets.
        size = max([*self.vocab.values(), *self.special.values()]) + 1
        parts = [b""] * size
        for t, i in self.vocab.items():
            parts[i] = t
        for t, i in self.special.items():
            parts[i] = t.encode()
        self.lengths = np.array(list(map(len, parts)), np.int64)
        self.offsets = np.concatenate([[0], np.cumsum(self.lengths)])[:-1]
        self.buffer = np.frombuffer(b"".join(parts), np.uint8)
        self.pretokens = Memo(self._encode_pretoken)
        self.tail = Memo(lambda word: self._encode_split(" " + word))

    def compatible(self, a: int, b: int) -> bool:
        """May rank ``b`` follow rank ``a``? No, if some stage of their merging would have joined over the seam."""
        known = self.pairs.get((a, b))
        if known is None:
            known = self.pairs[a, b] = self._seam_holds(a, b)
            if len(self.pairs) > 1_000_000:
                self.pairs.clear()
        return known

    def _seam_holds(self, a: int, b: int) -> bool:
        # Walk back in time: at each step the later-made side is taken apart, and the piece at the seam stays.
        # ``until`` is the moment from which the present two pieces no longer face each other.
        until = len(self.left)
        while True:
            merged = self.joined.get((a, b))
            if merged is not None and merged < until:
                return False
            if a < 256 and b < 256:
                return True
            # Where both pieces are equal the left one is older: merges of one rank run from left to right.
            if a > b:
                until, a = a, self.right[a]
            else:
                until, b = b + 1, self.left[b]

    def encode_word(self, word: bytes) -> list[int]:
        """Ranks of one pre-token."""
        whole = self.single.get(word)
        n, longest = len(word), [-1] * len(word)
        size = self.size_of
        for end, rank in self.automaton.iter(word.decode("latin-1")):
            at = end + 1 - size[rank]
            if longest[at] < 0 or size[rank] > size[longest[at]]:
                longest[at] = rank
        if whole is not None:
            longest[0] = whole
        out: list[int] = []
        closed = bytearray(n + 1)  # positions from which no rest can be encoded
        at, token = 0, longest[0] if n else -1
        while at < n:
            while token >= 0:
                end = at + size[token]
                if not closed[end] and (not out or self.compatible(out[-1], token)):
                    out.append(token)
                    at = end
                    token = longest[at] if at < n else -1
                    break
                token = self.shorter[token]
            else:
                closed[at] = 1
                token = out.pop()
                at -= size[token]
                token = self.shorter[token]
        return out

    def encode_bytes(self, text: str) -> bytes:
        """Ids of a whole text as little-endian 32-bit integers."""
        if self.cuts is None or not any(s in text for s in self.special):
            return self._encode_plain(text)
        out, at = [], 0
        for m in self.cuts.finditer(text):
            out += [self._encode_plain(text[at : m.start()]), self.special[m[0]].to_bytes(4, "little")]
            at = m.end()
        return b"".join([*out, self._encode_plain(text[at:])])

    def _encode_plain(self, text: str) -> bytes:
        # A word behind one single blank splits the same way wherever it stands, so it can be looked up whole.
        if "  " in text or text[-1:] == " ":
            return self._encode_split(text)
        first, *rest = text.split(" ")
        return self._encode_split(first) + b"".join(map(self.tail.__getitem__, rest))

    def _encode_split(self, text: str) -> bytes:
        return b"".join(map(self.pretokens.__getitem__, self.words.findall(text)))

    def _encode_pretoken(self, word: str) -> bytes:
        return b"".join(map(self.ids_bytes.__getitem__, self.encode_word(word.encode())))

    def encode(self, text: str) -> list[int]:
        return np.frombuffer(self.encode_bytes(text), "<u4").tolist()

    def decode_bytes(self, ids: np.ndarray) -> bytes:
        """One gather: for every output byte its place in the buffer of token bytes."""
        size = self.lengths[ids]
        ends = np.cumsum(size)
        if not len(ends):
            return b""
        shift = np.repeat(self.offsets[ids] - (ends - size), size)
        return self.buffer[shift + np.arange(int(ends[-1]))].tobytes()

    def decode(self, ids) -> str:
        return self.decode_bytes(np.asarray(ids, np.int64)).decode("utf-8", errors="replace")


class Memo(dict):
    """Remembers ``make(key)`` for up to two generations of CACHE_WORDS keys."""

    def __init__(self, make: Callable[[str], bytes]):
        self.make, self.old = make, {}

    def __missing__(self, key: str) -> bytes:
        got = self.old.get(key)
        if got is None:
            got = self.make(key)
        if len(key) <= 64:
            if len(self) >= CACHE_WORDS:
                self.old = dict(self)
                self.clear()
            self[key] = got
        return got


@lru_cache(maxsize=2)
def load(path: str) -> BacktrackingBpe:
    """One encoder for each worker process and file."""
    return BacktrackingBpe(path)


def vocabulary(name: str = "byte_bpe_50k.json") -> str:
    import public_tokenizers

    return public_tokenizers.path(name)


OUT = pa.schema([("doc_id", pa.int64()), ("n_tokens", pa.int64()), ("ids_sha256", pa.string()), ("decoded_sha256", pa.string())])


def encode_decode(docs: DataFrame, path: str | None = None, keep: bool = False) -> DataFrame:
    """doc_id, n_tokens and digests of ids and decoded text; with ``keep`` also ids (array) and decoded (string)."""
    path = path or vocabulary()
    schema = pa.schema([*OUT, ("ids", pa.list_(pa.int64())), ("decoded", pa.string())]) if keep else OUT

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        bpe = load(path)
        for batch in batches:
            rows: list[tuple] = []
            for i, text in zip(batch.column(0).to_pylist(), as_bytes(batch.column(1)), strict=True):
                raw = bpe.encode_bytes(text.decode("utf-8", errors="replace"))
                ids = np.frombuffer(raw, "<u4")
                back = bpe.decode_bytes(ids.astype(np.int64))
                if back != text:  # ids that split a character decode to replacement characters
                    back = back.decode("utf-8", errors="replace").encode()
                rows.append((i, len(ids), hashlib.sha256(raw).hexdigest(), hashlib.sha256(back).hexdigest(), *((ids.tolist(), back.decode()) if keep else ())))
            yield pa.RecordBatch.from_arrays([pa.array(c, f.type) for c, f in zip(zip(*rows, strict=True), schema, strict=True)], schema=schema) if rows else schema.empty_table().to_batches()[0]

    ddl = "doc_id long, n_tokens long, ids_sha256 string, decoded_sha256 string" + ", ids array<long>, decoded string" * keep
    out = source(docs).mapInArrow(run, ddl)
    return out.select(shown("doc_id"), *out.columns[1:])


def op7_backtracking_bpe(spark: SparkSession, sf_dir: str) -> DataFrame:
    return encode_decode(table(spark, sf_dir, "documents"))


ORACLE: dict[str, str] = {}
