"""Table scans with declared schemas, format round trips, media files and sinks."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

#: Columns of the given tables, as DDL.
SCHEMAS = {
    "documents": "doc_id bigint, text string, lang string, source string, n_chars bigint",
    "events": "event_id bigint, ts timestamp_ntz, user_id bigint, event_type string, value double, props string",
    "embeddings": "vec_id bigint, embedding array<float>, label int",
    "conversations": "conv_id bigint, turn bigint, role string, text string",
    "labels": "doc_id bigint, quality int, toxic int",
    "benchmark": "item_id bigint, text string",
    "pages": "page_id bigint, url string, html string",
}


def load(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    """Scan of one table; a declared schema saves the look into the files."""
    reader = spark.read
    if name in SCHEMAS:
        reader = reader.schema(SCHEMAS[name])
    return reader.parquet(f"{sf_dir}/{name}.parquet")


def deal(scan: DataFrame) -> DataFrame:
    """Rows of a scan of few splits dealt evenly before costly columns are made; a scan of splits enough stays as it is."""
    cores = scan.sparkSession.sparkContext.defaultParallelism
    return scan if scan.rdd.getNumPartitions() >= cores else scan.repartition(cores)


def assert_columns(df: DataFrame, names: list[str]) -> DataFrame:
    missing = [n for n in names if n not in df.columns]
    if missing:
        raise ValueError(f"columns {missing} are missing; there are {df.columns}")
    return df


def roundtrip(df: DataFrame, fmt: str, path: str) -> DataFrame:
    """Write in one of csv, json, orc, parquet or text, and read with the same schema."""
    writer, reader = df.write.mode("overwrite"), df.sparkSession.read.schema(df.schema)
    if fmt == "csv":
        writer, reader = writer.options(header=True, escape='"', quoteAll=True, emptyValue="", nullValue="\\N"), reader.options(header=True, escape='"', multiLine=True, emptyValue="", nullValue="\\N")
    writer.format(fmt).save(path)
    return reader.format(fmt).load(path)


def load_media(spark: SparkSession, path_glob: str, decoder=None, schema: str = "path string, content binary") -> DataFrame:
    """Binary files; ``decoder`` (an iterator of pandas frames to the same) may turn them into samples or frames."""
    raw = spark.read.format("binaryFile").load(path_glob).select("path", "content")
    return raw.mapInPandas(decoder, schema) if decoder else raw


def write_curated(curated: DataFrame, path: str) -> None:
    """Scores with ``split`` as the directory, so that a training phase reads its own subset alone."""
    curated.write.mode("overwrite").partitionBy("split").parquet(path)


def write_frames_bucketed(frames: DataFrame, table: str, buckets: int = 16) -> None:
    """Frames stored by clip and in order: later passes over clips need neither a shuffle of pixels nor, with one file a bucket, a sort."""
    frames.repartition(buckets, "clip_id").write.mode("overwrite").bucketBy(buckets, "clip_id").sortBy("clip_id", "frame_no").saveAsTable(table)


def write_scores_once(df: DataFrame, path: str) -> DataFrame:
    """Materialise per-clip signals that are read twice (statistics, then scores); returns the stored table."""
    df.write.mode("overwrite").parquet(path)
    return df.sparkSession.read.schema(df.schema).parquet(path)


def with_k(events: DataFrame) -> DataFrame:
    """The integer that an event's properties hold."""
    return events.withColumn("k", F.get_json_object("props", "$.k").cast("int"))
