"""Two-pass external shuffle of whole texts into shards, in DataFrame functions only.

Pass one scatters records into memory-sized buckets by a seeded hash. Pass two permutes each bucket with a seeded
Fisher-Yates shuffle (Spark's ``shuffle`` on the bucket's array of keys) and deals the permuted stream round-robin to
the shards, so shard sizes differ by one record at most (law ``rows``) and slots have no gaps. Texts travel once, to
their buckets, where they meet their places; ``write_texts`` writes them by shard in slot order, and the query reads
its sizes and CRCs from the shards so written. The number of buckets follows from the number of records alone, so the
order depends on data and seed and on no setting of the session.

Defined cases: a null text has no bytes (size 1, CRC of nothing) and stays null; very long texts travel like others,
in rows that sorts may spill; records that tie in doc_id, size, CRC and a 64-bit hash are counted, and their copies are
scattered by their rank, so a record that a third of all rows repeat fills no bucket; a null doc_id is a record like
any other; an empty table gives an empty result; extra columns are ignored (``write_shards`` keeps them).
"""

from __future__ import annotations

import uuid

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import window as W

from boundspark.llm.common import fan_out, fresh, shared_dir, stage, table

#: Records (not texts) of a bucket, until there are MAX_BUCKETS; then buckets grow, to some 100 MB at 100 TB of text.
BUCKET_ROWS, MAX_BUCKETS = 8192, 1 << 16
#: Copies of one record that one task unrolls.
COPIES = 4096


def bucket_count(records: int, bucket_rows: int = BUCKET_ROWS) -> int:
    return min(max(1, -(-records // bucket_rows)), MAX_BUCKETS)


#: What tells records apart; equal ones are copies.
RECORD = ["doc_id", "text_crc32", "size", "hash"]
#: Bytes of text that one task sorts and writes.
TASK_BYTES = 64 << 20
#: Keys of repeated records, a few MB, that are sent to all tasks so that texts stay where they are; more are merged.
FEW = 50_000


def _keyed(docs: DataFrame, id_col: str, text_col: str) -> DataFrame:
    body = F.coalesce(F.col(text_col), F.lit("")).cast("binary")
    return docs.select(F.col(id_col).cast("long").alias("doc_id"), F.crc32(body).alias("text_crc32"), _size(body).alias("size"), F.xxhash64(body).alias("hash"), F.col(text_col).alias("text"))


def _size(body: Column) -> Column:
    return (F.octet_length(body) + 1).cast("long")


def _unrolled(counted: DataFrame) -> DataFrame:
    """A row for each copy: copies 0 to COPIES - 1 of each record, and then the further ones, whose blocks are dealt out
    before they unroll."""
    rest = [c for c in counted.columns if c != "copies"]
    unroll = lambda frame: frame.select(*rest, F.explode(F.sequence("low", "high")).alias("copy"))
    low = (F.col("block") * COPIES).alias("low")
    blocks = counted.where(F.col("copies") > COPIES).select("*", F.explode(F.sequence(F.lit(1).cast("long"), F.expr(f"(copies - 1) div {COPIES}"))).alias("block"))
    further = blocks.select(*rest, low, (F.least((F.col("block") + 1) * COPIES, "copies") - 1).alias("high"), "block").repartition(*RECORD, "block")
    return unroll(counted.select(*rest, F.lit(0).cast("long").alias("low"), (F.least(F.col("copies"), F.lit(COPIES).cast("long")) - 1).alias("high"))).union(unroll(further))


def external_shuffle(docs: DataFrame, n_shards: int = 16, seed: int = 20_24, id_col: str = "doc_id", text_col: str = "text", bucket_rows: int = BUCKET_ROWS) -> DataFrame:
    """One row for each record: doc_id, size, text_crc32, law, shard, slot, grown_shard (null: law is ``rows``), text."""
    keyed = _keyed(docs, id_col, text_col)
    counted = stage(keyed.groupBy(*RECORD).agg(F.count(F.lit(1)).alias("copies")))
    total = counted.agg(F.coalesce(F.sum("copies"), F.lit(0)).alias("n"), F.coalesce(F.sum(F.col("copies") * F.col("size")), F.lit(0)).alias("bytes"), F.count_if(F.col("copies") > 1).alias("repeated")).first()
    n = bucket_count(total["n"], bucket_rows)
    bucket = F.pmod(F.xxhash64(F.lit(seed), "doc_id", "text_crc32", "size", "copy"), F.lit(n)).cast("int")
    # One bucket is one partition, so the shuffle's generator, seeded with seed + partition, depends on nothing else.
    held = _unrolled(counted).withColumn("bucket", bucket).repartitionById(n, "bucket").groupBy("bucket").agg(F.array_sort(F.collect_list(F.struct(*RECORD, "copy"))).alias("records"))
    mixed = stage(held.select("bucket", F.shuffle("records", F.lit(seed)).alias("records"), F.size("records").alias("n")))
    # A row for each bucket, of which there are at most MAX_BUCKETS.
    starts = mixed.select("bucket", (F.sum("n").over(W.Window.orderBy("bucket")) - F.col("n")).cast("long").alias("start"))
    dealt = mixed.join(F.broadcast(starts), "bucket").select("bucket", "start", F.posexplode("records").alias("at", "r"))
    places = dealt.select("bucket", "r.*", (F.col("start") + F.col("at")).alias("place"), F.lit(None).alias("text"))
    # Records of one copy know their bucket; of the others one text each is unrolled.
    texts = keyed.withColumn("copy", F.lit(0).cast("long"))
    if total["repeated"]:
        repeated = counted.where("copies > 1").select(*(F.col(c).alias(f"_{c}") for c in RECORD), "copies").hint("broadcast" if total["repeated"] <= FEW else "merge")
        tied = F.col("doc_id").eqNullSafe(F.col("_doc_id"))
        for c in RECORD[1:]:
            tied &= F.col(c) == F.col(f"_{c}")
        several = keyed.join(repeated, tied).groupBy(*RECORD).agg(F.first("text", True).alias("text"), F.first("copies").alias("copies"))
        texts = texts.join(repeated, tied, "left_anti").unionByName(_unrolled(several))
    texts = texts.select(bucket.alias("bucket"), *RECORD, "copy", F.lit(None).cast("long").alias("place"), "text")
    met = texts.unionByName(places).repartition(fan_out(docs.sparkSession, total["bytes"], TASK_BYTES), "bucket")
    out = met.groupBy("bucket", *RECORD, "copy").agg(F.first("place", True).alias("place"), F.first("text", True).alias("text"))
    return out.select("doc_id", "size", "text_crc32", F.lit("rows").alias("law"), F.pmod("place", F.lit(n_shards)).cast("int").alias("shard"), F.expr(f"place div {n_shards}").alias("slot"), F.lit(None).cast("int").alias("grown_shard"), "text")


def write_texts(shuffled: DataFrame, path: str) -> None:
    """Write the texts of ``external_shuffle`` by shard: the buckets of a file are in slot order."""
    shuffled.select("doc_id", "text", "shard", "slot").sortWithinPartitions("shard", "slot").write.option("compression", "zstd").partitionBy("shard").parquet(path)


def read_texts(spark: SparkSession, path: str) -> DataFrame:
    """The rows of ``write_texts``, with sizes and CRCs of the texts that the shards hold."""
    held = spark.read.schema("doc_id long, text string, slot long, shard int").parquet(path)
    body = F.coalesce(F.col("text"), F.lit("")).cast("binary")
    return held.select("doc_id", _size(body).alias("size"), F.crc32(body).alias("text_crc32"), F.lit("rows").alias("law"), "shard", "slot", F.lit(None).cast("int").alias("grown_shard"))


def write_shards(docs: DataFrame, path: str, n_shards: int = 16, seed: int = 20_24) -> None:
    """Write whole rows by shard, in slot order. The columns ``shard`` and ``slot`` are added, and replace any such."""
    rest = docs.drop("shard", "slot")
    crc, size, nth = (fresh(rest, name) for name in ("text_crc32_", "size_", "nth_"))
    rank = lambda *by: F.row_number().over(W.Window.partitionBy(*by).orderBy(F.lit(0)))
    text = F.coalesce("text", F.lit(""))
    left = rest.withColumns({crc: F.crc32(text.cast("binary")), size: (F.octet_length(text) + 1).cast("long")}).withColumn(nth, rank("doc_id", crc, size))
    where = external_shuffle(docs, n_shards, seed).withColumn("rank", rank("doc_id", "text_crc32", "size"))
    where = where.select(F.struct("doc_id", "text_crc32", "size", "rank").alias("key"), "shard", "slot")
    out = left.withColumn(crc, F.struct(F.col("doc_id").cast("long").alias("doc_id"), F.col(crc).alias("text_crc32"), F.col(size).alias("size"), F.col(nth).alias("rank")))
    out = out.join(where.withColumnRenamed("key", size + nth), F.col(crc).eqNullSafe(F.col(size + nth))).select(*rest.columns, "shard", "slot")
    out.repartitionByRange("shard", "slot").sortWithinPartitions("shard", "slot").write.partitionBy("shard").parquet(path)


def op5_external_shuffle(spark: SparkSession, sf_dir: str) -> DataFrame:
    path = f"{shared_dir(spark).rstrip('/')}/shards-{uuid.uuid4().hex}"
    write_texts(external_shuffle(table(spark, sf_dir, "documents")), path)
    return read_texts(spark, path)


ORACLE: dict[str, str] = {}
