"""Shared pieces of the training-data operators: reading, staging, Arrow helpers."""

from __future__ import annotations

import gc
import re
import tempfile
import uuid
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

#: Bytes of text that one numpy pass holds at a time inside a Python worker.
BLOCK_BYTES = 2 << 20
ASCII_SPACE = b"\x20\x09\x0a\x0b\x0c\x0d"


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def shared_dir(spark: SparkSession) -> str:
    """The shared folder that the session names in spark.checkpoint.dir; a private one only for a session of one process."""
    named, sc = spark.conf.get("spark.checkpoint.dir", None), spark.sparkContext
    if named is None and sc.getCheckpointDir() is None and not re.fullmatch(r"local(\[.*\])?", sc.master):
        raise RuntimeError("spark.checkpoint.dir must name a folder that the driver and all executors share")
    if sc.getCheckpointDir() is None:
        sc.setCheckpointDir(named or "file://" + tempfile.mkdtemp(prefix="boundspark-"))
    return named or sc.getCheckpointDir()


def fresh(docs: DataFrame, name: str) -> str:
    """A column name that ``docs`` does not have."""
    taken = {c.lower() for c in docs.columns}
    while name.lower() in taken:
        name += "_"
    return name


def numbered(docs: DataFrame) -> tuple[DataFrame, str]:
    """``docs`` with a number for each row, and the number's column: rows may share a doc_id or have none.

    Rows read from files are numbered by file and place in the file, which no other way of dealing them to tasks
    changes; any others are staged first.
    """
    if docs._jdf.queryExecution().analyzed().nodeName() != "LogicalRelation" or not docs.inputFiles():
        docs = stage(docs)
    row, path, at = (fresh(docs, name) for name in ("row_number", "file_path", "row_index"))
    located = docs.select("*", F.col("_metadata.file_path").alias(path), F.col("_metadata.row_index").alias(at))
    paths = sorted(r[0] for r in located.select(path).distinct().collect())  # as many as the driver has listed
    files = F.broadcast(docs.sparkSession.createDataFrame([(p, k) for k, p in enumerate(paths)], f"{path} string, {row} long"))
    return located.join(files, path).select(*docs.columns, (F.shiftleft(row, 38) + F.col(at)).alias(row)), row


def without(held: DataFrame, row: str, gone: DataFrame) -> DataFrame:
    """``held`` without the rows whose numbers are the one column of ``gone``, and without the numbers."""
    other = fresh(held, "gone")
    return held.join(gone.toDF(other).hint("merge"), F.col(row) == F.col(other), "left_anti").drop(row)


def stage(df: DataFrame) -> DataFrame:
    """Cut lineage: write ``df`` as a compressed table in the shared folder and read it back."""
    path = f"{shared_dir(df.sparkSession).rstrip('/')}/stage-{uuid.uuid4().hex}"
    df.write.option("compression", "zstd").parquet(path)
    return df.sparkSession.read.schema(df.schema).parquet(path)


def stage_by(df: DataFrame, key: str, buckets: int) -> DataFrame:
    """``stage`` as a table bucketed by ``key``: joins and cogroups on the key then move only their other side."""
    spark, name = df.sparkSession, f"boundspark_{uuid.uuid4().hex}"
    path = f"{shared_dir(spark).rstrip('/')}/{name}"
    df.write.bucketBy(buckets, key).option("path", path).option("compression", "zstd").format("parquet").saveAsTable(name)
    held = spark.table(name)
    held.schema  # resolved while the name exists; the files outlive it
    spark.sql(f"DROP TABLE {name}")
    return held


def release(spark: SparkSession) -> None:
    """Let Spark drop the shuffle files of jobs whose results are staged; it does so when the driver collects garbage."""
    gc.collect()
    spark.sparkContext._jvm.System.gc()


def fan_out(spark: SparkSession, total_bytes: int, per_task: int) -> int:
    """Number of buckets so that none holds much more than ``per_task`` bytes of what was measured."""
    return max(int(spark.conf.get("spark.sql.shuffle.partitions")), -(-int(total_bytes) // per_task), 1)


def text_bytes(docs: DataFrame, col: str = "text") -> int:
    return docs.agg(F.coalesce(F.sum(F.octet_length(col)), F.lit(0)).alias("b")).first()["b"]


def as_bytes(column: pa.Array) -> list[bytes]:
    """UTF-8 bytes of a string column without decoding; null counts as empty."""
    return [b"" if v is None else v for v in column.cast(pa.binary()).to_pylist()]


def blocks(batches: Iterator[pa.RecordBatch], size: int = BLOCK_BYTES) -> Iterator[tuple[list, list[bytes]]]:
    """(ids, texts) of rows, cut after about ``size`` bytes of text so that worker memory stays bounded."""
    ids, texts, held = [], [], 0
    for batch in batches:
        for i, t in zip(batch.column(0).to_pylist(), as_bytes(batch.column(1)), strict=True):
            ids.append(i)
            texts.append(t)
            held += len(t) + 64
            if held >= size:
                yield ids, texts
                ids, texts, held = [], [], 0
    if ids:
        yield ids, texts


def record_batch(schema: pa.Schema, **cols) -> pa.RecordBatch:
    return pa.RecordBatch.from_arrays([pa.array(cols[f.name], f.type) for f in schema], schema=schema)


def is_blank_edge(text: bytes) -> tuple[bool, bool]:
    return text[:1] in _SPACES, text[-1:] in _SPACES


_SPACES = frozenset(bytes([c]) for c in ASCII_SPACE)


def mix64(x: np.ndarray) -> np.ndarray:
    """A bijective 64-bit finaliser on uint64 arrays."""
    y = x >> np.uint64(32)
    y ^= x
    for _ in range(2):
        y *= np.uint64(0xD6E8FEB86659FD93)
        y ^= y >> np.uint64(32)
    return y


#: Stands for a null identifier inside kernels; results show null again.
NO_ID = -(1 << 63)


def source(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(doc_id, text): the two columns that operators read; a null id sorts before all others."""
    return docs.select(id_of(id_col).alias("doc_id"), F.col(text_col).cast("string").alias("text"))


def id_of(col: str) -> Column:
    return F.coalesce(F.col(col).cast("long"), F.lit(NO_ID))


def shown(name: str):
    """An id column as results show it."""
    return F.when(F.col(name) != NO_ID, F.col(name)).alias(name)
