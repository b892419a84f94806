"""Quality rules by distribution divergence.

Every text becomes two histograms: over character classes and over its language's common words. Each is compared
with the language's reference by Jensen-Shannon distance (base 2, square root of the divergence). References are
learnt from all documents: component by component, the exact median over the texts that pass the base rules and the
minimum-length guards, so that a third of junk cannot move them far. Histograms are only judged above the guards.

Defined cases: a null text has no words and fails the base rule (fewer than 20 words); a language that is null,
unknown or without a reference is judged against the nearest reference there is, and passes if there is none; very
long texts are read whole; repeated rows give repeated results; an empty table gives an empty result.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from boundspark.llm.common import NO_ID, as_bytes, shown, stage, table

# Common words by language.
COMMON_WORDS = {
    "en": "the of and to in is was for on that by with as at it from are an be this".split(),
    "fr": "de la le et les des en un une du que qui dans est pour par sur au pas il".split(),
    "de": "der die und in den von zu das mit sich des auf für ist im dem nicht ein eine als".split(),
    "es": "de la que el en y a los se del las un por con no una su para es al".split(),
}
CLASSES = ("lower", "upper", "digit", "space", "stop", "symbol", "other_ascii", "beyond_ascii")
SCALE = 1000
MIN_CHARS, MIN_WORDS = 120, 40
#: Largest distance: a floor plus a share of 1 / sqrt(characters), the spread that short clean texts have by chance.
MAX_DISTANCE = {"class_distance": (0.15, 2.4), "word_distance": (0.18, 3.6), "class_distance + word_distance": (0.33, 3.7)}
SYMBOLS = b"#*$%&|<>"
REPEAT_WINDOW = 8


def _class_table() -> np.ndarray:
    kind = np.full(256, CLASSES.index("other_ascii"), np.int64)
    for name, members in (("lower", range(97, 123)), ("upper", range(65, 91)), ("digit", range(48, 58)), ("space", b" \t\n\r\v\f"), ("stop", b".,;:!?'\"()-"), ("symbol", SYMBOLS + b"@^~=+_{}[]\\/`")):
        kind[list(members)] = CLASSES.index(name)
    kind[128:192] = len(CLASSES)  # continuation bytes are no characters
    kind[192:] = CLASSES.index("beyond_ascii")
    return kind


CLASS_OF = _class_table()
STRIP = b".,;:!?'\"()-"


def repeat_words(words: list[bytes], width: int = REPEAT_WINDOW) -> int:
    """Words that lie in a window of ``width`` words found twice or more in the text, first windows included."""
    n = len(words) - width + 1
    if n < 2:
        return 0
    number: dict[bytes, int] = {}
    ids = np.array([number.setdefault(w, len(number)) for w in words], np.int64)
    if len(number) == len(words):
        return 0
    rank, span = ids, 1
    while span < width:  # names of 2, 4, 8 words: exact, no hashing
        step = min(span, width - span)
        pair = rank[: len(rank) - step] * (int(rank.max()) + 1) + rank[step:]
        rank, span = np.unique(pair, return_inverse=True)[1].astype(np.int64), span + step
    again = np.bincount(rank)[rank] > 1
    edge = np.zeros(len(words) + 1, np.int64)
    at = np.flatnonzero(again)
    np.add.at(edge, at, 1)
    np.add.at(edge, at + width, -1)
    return int((np.cumsum(edge[:-1]) > 0).sum())


def base_measures(text: bytes) -> tuple[int, int, int, int, int, list[bytes]]:
    """n_words, word_chars, n_symbols, n_dup_lines, n_repeat_words, words."""
    words = text.split()
    inside = b"".join(words)
    chars = len(inside) - len(inside.translate(None, bytes(range(0x80, 0xC0)))) if not inside.isascii() else 0
    seen: set[bytes] = set()
    dup = 0
    if b"\n" in text:
        for line in text.split(b"\n"):
            if line in seen:
                dup += 1
            elif line.strip():
                seen.add(line)
    return len(words), len(inside) - chars, len(text) - len(text.translate(None, SYMBOLS)), dup, repeat_words(words), words


_WORD_AT = {lang: {w.encode(): k for k, w in enumerate(ws)} for lang, ws in COMMON_WORDS.items()}
LANGS = tuple(COMMON_WORDS)
N_WORD_BINS = max(map(len, COMMON_WORDS.values())) + 1


def word_histogram(words: list[bytes], lang: str) -> np.ndarray:
    """Counts of the language's common words, lower-cased and stripped of punctuation; the last bin holds the rest."""
    at, out = _WORD_AT[lang], np.zeros(N_WORD_BINS, np.int64)
    for w in words:
        k = at.get(w)
        if k is None and (not w.isalpha() or w[:1].isupper()):
            k = at.get(w.strip(STRIP).lower())
        out[-1 if k is None else k] += 1
    return out


def shares(counts: np.ndarray) -> list[int]:
    total = int(counts.sum())
    return [int(c) * SCALE // total for c in counts] if total else [0] * len(counts)


FEATURES = pa.schema(
    [("doc_id", pa.int64()), ("lang", pa.string())]
    + [(c, pa.int64()) for c in ("n_chars", "n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words")]
    + [("class_share", pa.list_(pa.int32())), ("word_share", pa.list_(pa.list_(pa.int32())))]
)


def _features(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        cols: list[list] = [[] for _ in FEATURES]
        for i, text, lang in zip(batch.column(0).to_pylist(), as_bytes(batch.column(1)), batch.column(2).to_pylist(), strict=True):
            n_words, word_chars, symbols, dup, repeat, words = base_measures(text)
            classes = np.bincount(CLASS_OF[np.frombuffer(text, np.uint8)], minlength=len(CLASSES) + 1)[: len(CLASSES)]
            langs = (lang,) if lang in _WORD_AT else LANGS
            row = (i, lang if lang in _WORD_AT else None, int(classes.sum()), n_words, word_chars, symbols, dup, repeat, shares(classes), [shares(word_histogram(words, x)) for x in langs])
            for c, v in zip(cols, row, strict=True):
                c.append(v)
        yield pa.RecordBatch.from_arrays([pa.array(c, f.type) for c, f in zip(cols, FEATURES, strict=True)], schema=FEATURES)


FEATURES_DDL = "doc_id long, lang string, n_chars long, n_words long, word_chars long, n_symbols long, n_dup_lines long, n_repeat_words long, class_share array<int>, word_share array<array<int>>"


def js_distance(p: str, q: str) -> str:
    """SQL for the Jensen-Shannon distance of two arrays of shares; each is scaled to sum to one."""
    total = lambda a: f"greatest(1, aggregate({a}, 0, (s, v) -> s + v))"
    part = "(CASE WHEN {x} > 0 THEN {x} * log2({x} / (({x} + {y}) / 2)) ELSE 0D END)"
    pair = f"zip_with({p}, {q}, (a, b) -> named_struct('x', a / {total(p)}, 'y', b / {total(q)}))"
    body = f"{part.format(x='v.x', y='v.y')} + {part.format(x='v.y', y='v.x')}"
    return f"round(sqrt(greatest(0D, 0.5D * aggregate({pair}, 0D, (s, v) -> s + {body}))), 6)"


BASE_FAILED = "n_words < 20 OR 100 * n_repeat_words > 30 * n_words"


def measure(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", lang_col: str = "lang") -> DataFrame:
    """Base measures and histogram shares, staged: small rows, without texts."""
    src = docs.select(F.coalesce(F.col(id_col).cast("long"), F.lit(NO_ID)), F.col(text_col).cast("string"), F.col(lang_col).cast("string"))
    return stage(src.mapInArrow(_features, FEATURES_DDL))


def references(features: DataFrame) -> DataFrame:
    """Exact component medians by language; shares are integers up to SCALE, so each median's state is bounded."""
    fit = features.where(f"lang IS NOT NULL AND NOT ({BASE_FAILED}) AND n_chars >= {MIN_CHARS} AND n_words >= {MIN_WORDS}")
    med = lambda a, n: F.array(*(F.percentile(F.col(a)[k], 0.5).cast("int") for k in range(n)))
    flat = fit.select("lang", "class_share", F.col("word_share")[0].alias("words"))
    return flat.groupBy("lang").agg(med("class_share", len(CLASSES)).alias("ref_class"), med("words", N_WORD_BINS).alias("ref_word"))


def quality_rules(docs: DataFrame, **cols) -> DataFrame:
    """doc_id, n_words, word_chars, n_symbols, n_dup_lines, n_repeat_words, base_failed, kept and both distances."""
    features = measure(docs, **cols)
    refs = {r["lang"]: (r["ref_class"], r["ref_word"]) for r in references(features).collect()}  # a row for each of four languages
    class_d, word_d = F.lit(None).cast("double"), F.lit(None).cast("double")
    any_class, any_word = [], []
    for lang in sorted(refs):
        ref_c, ref_w = ("array({})".format(", ".join(map(str, r))) for r in refs[lang])
        c = F.expr(js_distance("class_share", ref_c))
        class_d = F.when(F.col("lang") == lang, c).otherwise(class_d)
        word_d = F.when(F.col("lang") == lang, F.expr(js_distance("word_share[0]", ref_w))).otherwise(word_d)
        any_class.append(c)
        any_word.append(F.expr(js_distance(f"word_share[{LANGS.index(lang)}]", ref_w)))
    if refs:
        least = lambda xs: xs[0] if len(xs) == 1 else F.least(*xs)
        known = F.col("lang").isin(*refs)
        class_d = F.when(known, class_d).otherwise(least(any_class))
        word_d = F.when(known, word_d).when(F.size("word_share") > 1, least(any_word))
    long_enough = {"class_distance": f"n_chars >= {MIN_CHARS}"}
    far = F.expr(" OR ".join(f"({long_enough.get(d, f'n_words >= {MIN_WORDS}')} AND {d} > {floor} + {spread} / sqrt(n_chars))" for d, (floor, spread) in MAX_DISTANCE.items()))
    out = features.withColumns({"class_distance": class_d, "word_distance": word_d, "base_failed": F.expr(BASE_FAILED)})
    keep = ~F.col("base_failed") & ~F.coalesce(far, F.lit(False))
    return out.select(shown("doc_id"), "n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", "base_failed", keep.alias("kept"), "class_distance", "word_distance")


def op1_divergence_rules(spark: SparkSession, sf_dir: str) -> DataFrame:
    return quality_rules(table(spark, sf_dir, "documents"))


ORACLE: dict[str, str] = {}
