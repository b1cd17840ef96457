"""Two-pass external shuffle into shards, on DataFrame functions alone.

Pass one scatters the documents by seeded hashes into buckets of a bounded row count inside each
shard, and stores them with their buckets and row ids. Pass two brings each bucket together, runs a
seeded Fisher-Yates shuffle over its places and writes its documents in that order. A bucket's
first slot is the number of rows in the shard's earlier buckets, so slots are gapless.
``shard_documents`` reads the written shards again and tells what is in them.

The shard of a row follows the key law: the shard whose seeded hash of (shard, key) is the
greatest. One more shard can only take rows to itself.

Edge cases: a null key is a key like any other; a null text has size 8 and the checksum of no
bytes; equal rows each get a slot of their own; an empty table gives an empty result; ``write_shards``
carries further columns (other than shard, bucket, slot, rid, at, first_slot and places).
"""

from __future__ import annotations

import math
import uuid

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F
from pyspark.sql.types import IntegerType, LongType, StructField, StructType

from avcurate.llm.common import shared_dir, stage, text_or_empty


def _weight(key: str, shard: int, seed: int) -> Column:
    return F.xxhash64(F.lit(seed), F.lit(shard), F.col(key))


def key_law(key: str, shards: int, seed: int) -> tuple[Column, Column]:
    """Shard under ``shards`` shards, and under one more."""
    weights = F.array(*[_weight(key, s, seed) for s in range(shards)])
    best = F.array_max(weights)
    here = (F.array_position(weights, best) - 1).cast("int")
    return here, F.when(_weight(key, shards, seed) > best, F.lit(shards)).otherwise(here).cast("int")


def scatter(docs: DataFrame, key: str, shards: int, bucket_rows: int, seed: int) -> DataFrame:
    """Pass one: the documents with their shard, a bucket in it and a row id, stored in the shared folder."""
    per_shard = max(1, math.ceil(docs.count() / (shards * bucket_rows)))
    rows = docs.withColumn("rid", F.monotonically_increasing_id())
    bucket = F.pmod(F.xxhash64(F.lit(seed + 1), F.col(key), F.col("rid")), F.lit(per_shard)).cast("int")
    return stage(rows.withColumns({"shard": key_law(key, shards, seed)[0], "bucket": bucket}), "shard-scatter", "zstd")


def permutations(scattered: DataFrame, seed: int) -> DataFrame:
    """For each bucket its first slot and a shuffled list of the places in it."""
    before = Window.partitionBy("shard").orderBy("bucket").rowsBetween(Window.unboundedPreceding, -1)
    counts = scattered.groupBy("shard", "bucket").agg(F.count("*").alias("n"))
    first = counts.withColumn("first_slot", F.coalesce(F.sum("n").over(before), F.lit(0)))
    first = stage(first, "shard-first").repartition("shard", "bucket").sortWithinPartitions("shard", "bucket")
    return stage(first.select("shard", "bucket", "first_slot", F.shuffle(F.sequence(F.lit(0), F.col("n") - 1), F.lit(seed)).alias("places")), "shard-places")


def write_shards(docs: DataFrame, path: str, shards: int = 24, bucket_rows: int = 4096, seed: int = 20_11, key: str = "doc_id") -> None:
    """Write the documents, with their slots, under ``path``/shard=N; a file holds buckets in the order of their slots.

    ``bucket_rows`` bounds what one bucket holds, on average.
    """
    scattered = scatter(docs, key, shards, bucket_rows, seed)
    at = F.row_number().over(Window.partitionBy("shard", "bucket").orderBy("rid"))
    (
        scattered.withColumn("at", at)
        .join(permutations(scattered, seed).hint("shuffle_merge"), ["shard", "bucket"])
        .select(*docs.columns, (F.col("first_slot") + F.element_at("places", F.col("at"))).alias("slot"), "shard")
        .sortWithinPartitions("shard", "slot")
        .write.option("compression", "zstd").partitionBy("shard").parquet(path)
    )


def shard_documents(docs: DataFrame, shards: int = 24, bucket_rows: int = 4096, seed: int = 20_11) -> DataFrame:
    """Write the documents into shards and read them back: doc_id, size, text_crc32, law, shard, slot, grown_shard."""
    docs = docs.select("doc_id", "text")
    spark = docs.sparkSession
    path = f"{shared_dir(spark)}/staged/shards-{uuid.uuid4().hex}"
    write_shards(docs, path, shards, bucket_rows, seed)
    written = spark.read.schema(StructType([*docs.schema.fields, StructField("slot", LongType()), StructField("shard", IntegerType())])).parquet(path)
    return written.select(
        "doc_id",
        (F.coalesce(F.octet_length("text"), F.lit(0)) + 8).cast("long").alias("size"),
        F.crc32(F.encode(text_or_empty(), "UTF-8")).alias("text_crc32"),
        F.lit("key").alias("law"), "shard", "slot", key_law("doc_id", shards, seed)[1].alias("grown_shard"),
    )
