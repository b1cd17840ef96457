"""Stages of alignment: what trains, what is frozen, on which part of which corpus."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from avcurate.sources.fixtures import bucket100

#: Stage, step, corpus (its stand-in table), share of it, trained modules, frozen modules.
STAGES = (
    ("1a", 1, "pages", 1.0, ["resampler"], ["vision_encoder", "language_model", "audio_encoder"]),
    ("1b", 2, "embeddings", 0.3, ["resampler"], ["vision_encoder", "language_model", "audio_encoder"]),
    ("2", 3, "documents", 1.0, ["resampler", "audio_encoder"], ["vision_encoder", "language_model"]),
    ("3", 4, "conversations", 1.0, ["resampler", "audio_encoder", "vision_encoder", "language_model"], []),
)


def stage_plan(spark: SparkSession) -> DataFrame:
    return spark.createDataFrame(list(STAGES), "stage string, step int, corpus string, fraction double, trainable array<string>, frozen array<string>")


def trainable(plan: DataFrame, stage: str) -> DataFrame:
    return plan.where(F.col("stage") == stage).select(F.explode("trainable").alias("module"))


def fraction_sample(df: DataFrame, fraction: float, key: str, method: str = "hash", seed: int = 1) -> DataFrame:
    """The same rows in every run (hash of the key), or a seeded Bernoulli sample."""
    if method == "bernoulli":
        return df.sample(fraction=fraction, seed=seed)
    return df.where(bucket100(F.col(key)) < round(100 * fraction))
