"""Views that read the given tables as clips, audio, video, landmarks, tokens, systems and instructions."""

from __future__ import annotations

from decimal import Decimal

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from avcurate.functions.text import by_utterance, utterances
from avcurate.sources.tables import deal, load, with_k

def clip_text(spark: SparkSession, sf_dir: str, dealt: bool = True) -> DataFrame:
    """clip_id, speaker, category, ref_text, hyp_text: whole texts as utterances; a fifth of the clips each: exact, no vowels, cut, fewer h, reversed.

    ``dealt`` False leaves rows where the scan has them, for callers that deal texts themselves.
    """
    ref, way = F.col("ref_text"), F.col("clip_id") % 5
    hyp = (
        F.when(way == 0, ref).when(way == 1, F.regexp_replace(ref, "[aeiou]", ""))
        .when(way == 2, by_utterance(ref, lambda r: F.left(r, F.floor(F.length(r) * F.lit(0.6)).cast("int"))))
        .when(way == 3, F.replace(ref, F.lit("th"), F.lit("t"))).otherwise(by_utterance(ref, F.reverse))
    )
    docs = load(spark, sf_dir, "documents").select("doc_id", "source", "lang", "text")
    docs = deal(docs) if dealt else docs
    clips = docs.select(F.col("doc_id").alias("clip_id"), F.col("source").alias("speaker"), F.col("lang").alias("category"), utterances("text").alias("ref_text"))
    return clips.withColumn("hyp_text", hyp)


def clip_audio(spark: SparkSession, sf_dir: str) -> DataFrame:
    """clip_id, t, clean, noisy: ten events are one clip."""
    e = with_k(load(spark, sf_dir, "events"))
    return e.select(
        F.floor(F.col("event_id") / 10).alias("clip_id"), (F.col("event_id") % 10).cast("int").alias("t"),
        F.col("value").alias("clean"), (F.col("value") + (F.col("k") / 10.0 - 4.95)).alias("noisy"),
    )


def order_audio(spark: SparkSession, sf_dir: str) -> DataFrame:
    """clip_id, clean, noisy: the lines of an order as a series; discounts of zero leave no residual."""
    line = load(spark, sf_dir, "lineitem")
    clean = F.col("l_extendedprice")
    return line.select(F.col("l_orderkey").alias("clip_id"), clean.alias("clean"), (clean - clean * F.col("l_discount")).alias("noisy"))


def clip_frames(spark: SparkSession, sf_dir: str) -> DataFrame:
    """clip_id, frame_no, pixels, height, width, channels: six frames of 8 x 8 grey values a clip."""
    emb = load(spark, sf_dir, "embeddings")
    n = emb.agg(F.count("*").alias("n_emb"))
    j = F.col("frame_no")
    want = (
        load(spark, sf_dir, "documents").select(F.col("doc_id").alias("clip_id"))
        .crossJoin(F.broadcast(n))
        .withColumn("frame_no", F.explode(F.sequence(F.lit(0), F.lit(5))))
        .withColumn("vec_id", (F.col("clip_id") + F.floor(j * (F.col("clip_id") % 6) / 5)) % F.col("n_emb"))
    )
    return want.join(emb.select("vec_id", F.col("embedding").alias("pixels")), "vec_id").select(
        "clip_id", "frame_no", "pixels", F.lit(8).alias("height"), F.lit(8).alias("width"), F.lit(1).alias("channels")
    )


def numbered(df: DataFrame, by: str, order: str, out: str, width: int = 4096) -> DataFrame:
    """Rows of each ``by`` numbered from 0 by an integer ``order``: counted in ranges of it first, so that a task numbers one range alone."""
    x = df.withColumn("_range", F.floor(F.col(order) / width))
    before = F.sum("c").over(Window.partitionBy(by).orderBy("_range").rowsBetween(Window.unboundedPreceding, -1))
    counts = x.groupBy(by, "_range").agg(F.count("*").alias("c")).select(by, "_range", F.coalesce(before, F.lit(0)).alias("_base"))
    inner = F.row_number().over(Window.partitionBy(by, "_range").orderBy(order))
    return x.withColumn("_at", inner).join(counts, [by, "_range"]).withColumn(out, (F.col("_base") + F.col("_at") - 1).cast("bigint")).drop("_range", "_base", "_at")


def landmark_frames(spark: SparkSession, sf_dir: str) -> DataFrame:
    """clip_id, frame_no, points (null where the detector misses)."""
    from avcurate.operators.lips import unpack_points

    return numbered(load(spark, sf_dir, "embeddings"), "label", "vec_id", "frame_no").select(
        F.col("label").alias("clip_id"), "frame_no",
        F.when(F.col("vec_id") % 7 != 3, unpack_points(F.col("embedding"))).alias("points"),
    )


LIP_INDICES = list(range(20, 32))


def tokens(spark: SparkSession, sf_dir: str) -> DataFrame:
    return load(spark, sf_dir, "embeddings").select(F.col("label").alias("clip_id"), F.col("vec_id").alias("token_no"), F.col("embedding").cast("array<double>").alias("vec"))


def queries(spark: SparkSession, sf_dir: str, n: int = 64, gain: float = 1.0) -> DataFrame:
    vec = F.transform(F.col("embedding").cast("array<double>"), lambda x: x * gain)
    return load(spark, sf_dir, "embeddings").where(F.col("vec_id") < n).select(F.col("vec_id").alias("query_no"), vec.alias("vec"))


def trainable(spark: SparkSession, sf_dir: str) -> DataFrame:
    """vec_id, vec, y, part."""
    return load(spark, sf_dir, "embeddings").select(
        "vec_id", F.col("embedding").cast("array<double>").alias("vec"), F.col("label").alias("y"),
        F.when(bucket100(F.col("vec_id")) < 80, "train").otherwise("test").alias("part"),
    )


def bucket100(key: Column) -> Column:
    """0..99 from md5 of the key's decimal form, alike in every engine."""
    return F.pmod(F.conv(F.substring(F.md5(key.cast("string").cast("binary")), 1, 8), 16, 10).cast("bigint"), F.lit(100)).cast("bigint")


def turns(spark: SparkSession, sf_dir: str) -> DataFrame:
    return load(spark, sf_dir, "conversations")


#: The printed results (id, group, parameters in billions, audio, video, similarity, error rate, score).
PRINTED = (
    ("sys01", "asr", "1.6", True, False, "0.79", "0.32", "0.74"),
    ("sys02", "asr", "0.3", True, False, "0.71", "0.35", "0.68"),
    ("sys03", "asr", "0.2", True, False, "0.70", "0.38", "0.66"),
    ("sys04", "asr", "1.1", True, False, "0.77", "0.38", "0.70"),
    ("sys05", "audio_lm", "7", True, False, "0.74", "0.44", "0.65"),
    ("sys06", "audio_lm", "7", True, False, "0.67", "0.53", "0.57"),
    ("sys07", "audio_lm", "7", True, False, "0.67", "0.54", "0.57"),
    ("sys08", "audio_lm", "7", True, False, "0.79", "0.34", "0.73"),
    ("sys09", "multimodal", "3", True, True, "0.73", "0.44", "0.65"),
    ("sys10", "multimodal", "7", True, True, "0.75", "0.42", "0.67"),
    ("sys11", "multimodal", "3", True, True, "0.77", "0.37", "0.70"),
    ("sys12", "multimodal", "3", True, True, "0.84", "0.27", "0.79"),
    ("sys13", "ablation", None, True, False, "0.74", "0.46", "0.64"),
)


def golden(spark: SparkSession) -> DataFrame:
    d = lambda x: None if x is None else Decimal(x)
    rows = [(i, g, d(p), a, v, d(s), d(c), d(cs)) for i, g, p, a, v, s, c, cs in PRINTED]
    return spark.createDataFrame(rows, "system_id string, family string, params_b decimal(4,1), has_audio boolean, has_video boolean, emb_sim decimal(5,3), cer decimal(5,3), cs decimal(5,3)")


def line_board(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The systems' board measured on ``lineitem``: each line is a pair of one system (its supplier's number by 13), its discount the pair's error rate, 1 - tax its similarity.

    Sums are of decimals. The systems' groups and sizes are those of ``golden``.
    """
    d = lambda c: F.col(c).cast("decimal(4,2)")
    line = load(spark, sf_dir, "lineitem").select(F.concat(F.lit("sys"), F.lpad((F.col("l_suppkey") % 13 + 1).cast("string"), 2, "0")).alias("system_id"), d("l_discount").alias("e"), (1 - d("l_tax")).alias("s"))
    mean = lambda x: F.round((F.sum(x).cast("double") / F.count("*")), 6).cast("decimal(9,6)")
    measured = line.groupBy("system_id").agg(mean(F.col("s")).alias("emb_sim"), mean(F.col("e")).alias("cer"), mean(F.lit(Decimal("0.5")) * (1 - F.col("e")) + F.lit(Decimal("0.5")) * F.col("s")).alias("cs"))
    return measured.join(F.broadcast(golden(spark).drop("emb_sim", "cer", "cs")), "system_id")
