"""Readers of the given tables and round trips through other file formats."""

from __future__ import annotations

import re
import tempfile
import uuid

from pyspark.sql import DataFrame, SparkSession

TABLES = ("region", "nation", "customer", "supplier", "part", "orders", "lineitem", "events", "documents", "embeddings", "pages", "benchmark", "labels", "conversations")


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def views(spark: SparkSession, sf_dir: str, names: tuple[str, ...] = TABLES) -> None:
    """Temporary views over the tables, for queries given as SQL text."""
    for name in names:
        table(spark, sf_dir, name).createOrReplaceTempView(name)


def scratch(spark: SparkSession, tag: str) -> str:
    """A fresh path under the shared folder the session names; a temporary one only for a session of one process."""
    base = spark.conf.get("spark.checkpoint.dir", None)
    if base is None and not re.fullmatch(r"local(\[.*\])?", spark.sparkContext.master):
        raise RuntimeError("spark.checkpoint.dir must name a folder that the driver and all executors share")
    base = base or "file://" + tempfile.mkdtemp(prefix="boundspark-")
    return f"{base.rstrip('/')}/{tag}-{uuid.uuid4().hex}"


def staged(df: DataFrame, tag: str) -> DataFrame:
    """``df`` written to the shared folder and read back."""
    path = scratch(df.sparkSession, tag)
    df.write.parquet(path)
    return df.sparkSession.read.schema(df.schema).parquet(path)


def format_roundtrip(df: DataFrame, fmt: str, **options: str) -> DataFrame:
    """Write ``df`` in a format and read it back with its declared schema."""
    path = scratch(df.sparkSession, fmt)
    df.write.format(fmt).options(**options).save(path)
    return df.sparkSession.read.format(fmt).options(**options).schema(df.schema).load(path)
