"""The corpus pipeline: quality rules, exact dedup, near dedup, suffix-array dedup, best-fit packing.

Each stage takes (spark, docs, sf_dir) and returns a DataFrame; all but the last keep the columns of documents. Rows
are numbered anew in each stage and told apart by that number alone, so rows without a doc_id, rows that share one,
and columns of any name are rows and columns like others. A null text counts as empty: the quality rules reject it.
Very long texts are worked on whole or in overlapping pieces, as the operators say; empty tables stay empty.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from boundspark.llm.common import fresh, numbered, stage, table, without
from boundspark.llm.exact_dedup import exact_dedup
from boundspark.llm.near_dedup import near_dedup
from boundspark.llm.packing import pack
from boundspark.llm.quality_rules import quality_rules
from boundspark.llm.suffix_dedup import suffix_dedup_texts


def quality(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Rows that the quality rules keep."""
    held, row = numbered(docs)
    return without(held, row, quality_rules(held, id_col=row).where("NOT kept").select("doc_id"))


def exact(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Of rows with equal texts the one with the smallest doc_id; of those that tie in it, one."""
    held, row = numbered(docs)
    return without(held, row, exact_dedup(held, row_col=row).where("NOT kept").select("row"))


def near(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One row of each group of near-duplicates."""
    return near_dedup(docs)


def substrings(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Texts lose the bytes that an earlier document has; n_chars follows; every row stays."""
    held, row = numbered(docs)
    left = suffix_dedup_texts(held.select(row, "doc_id", "text"), row)
    number, text = (fresh(held, name) for name in ("number", "text_left"))
    both = held.join(left.toDF(number, text).hint("merge"), F.col(row) == F.col(number))
    values = {"text": F.col(text), "n_chars": F.length(text).cast("long")}
    return both.select(*(values[c].alias(c) if c in values else F.col(c) for c in docs.columns))


def packing(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Pieces of all texts and their places in sequences."""
    return pack(docs)


STAGES = [("quality_rules", quality), ("exact_dedup", exact), ("near_dedup", near), ("suffix_dedup", substrings), ("packing", packing)]
#: SQL has no form of the SimHash and packing stages.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    for k, (_, fn) in enumerate(STAGES):
        docs = fn(spark, docs, sf_dir)
        if k < len(STAGES) - 1:
            docs = stage(docs)
    return docs
