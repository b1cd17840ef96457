"""Motion of frames and its cap over the dataset."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from avcurate.functions.vectors import mean_difference
from avcurate.operators.normalise import exact_quantile


def motion_magnitude(frames: DataFrame, norm: str = "l1") -> DataFrame:
    """clip_id, pairs, motion: the mean over neighbouring frames of their mean pixel difference; null for one frame."""
    w = Window.partitionBy("clip_id").orderBy("frame_no")
    pairs = frames.select("clip_id", F.lag("pixels").over(w).alias("before"), "pixels")
    same = F.col("before").isNull() | (F.size("before") == F.size("pixels"))
    d = F.when(same, mean_difference("before", "pixels", norm)).otherwise(F.raise_error(F.lit("frames of unlike sizes")).cast("double"))
    return pairs.select("clip_id", d.alias("d")).groupBy("clip_id").agg(F.count("d").alias("pairs"), F.avg("d").alias("motion"))


def motion_by_chunks(frames: DataFrame, chunk: int = 256, norm: str = "l1") -> DataFrame:
    """The same for clips of any length: cut into chunks that share a frame; sums of differences add up."""
    at = F.floor(F.col("frame_no") / chunk)
    both = F.when((F.col("frame_no") % chunk == 0) & (F.col("frame_no") > 0), F.array(at, at - 1)).otherwise(F.array(at))
    w = Window.partitionBy("clip_id", "chunk").orderBy("frame_no")
    d = mean_difference("before", "pixels", norm)
    parts = (
        frames.withColumn("chunk", F.explode(both)).select("clip_id", "chunk", F.lag("pixels").over(w).alias("before"), "pixels")
        .select("clip_id", "chunk", d.alias("d")).groupBy("clip_id", "chunk").agg(F.count("d").alias("n"), F.sum("d").alias("s"))
    )
    return parts.groupBy("clip_id").agg(F.sum("n").alias("pairs"), F.try_divide(F.sum("s"), F.sum("n")).alias("motion"))


def motion_cap(motion: DataFrame, q: float = 0.9, method: str = "exact", accuracy: int = 10000) -> DataFrame:
    """One row: motion_cap, rank_error. ``exact`` takes two passes of counts; ``approx`` and ``kll`` one of sketches."""
    if method == "exact":
        return exact_quantile(motion, "motion", q, "motion_cap").withColumn("rank_error", F.lit(0.0))
    if method == "approx":
        return motion.agg(F.percentile_approx("motion", q, accuracy).alias("motion_cap"), F.lit(1.0 / accuracy).alias("rank_error"))
    sketch = motion.agg(F.expr("kll_sketch_agg_double(motion)").alias("s"))
    return sketch.select(F.expr(f"kll_sketch_get_quantile_double(s, {q}D)").alias("motion_cap"), F.lit(0.0133).alias("rank_error"))


def video_score(motion: Column | str, cap: Column | str) -> Column:
    """min(motion / cap, 1); zero where the cap is zero, null where there is no motion value."""
    m, c = (F.col(x) if isinstance(x, str) else x for x in (motion, cap))
    return F.when(m.isNull() | c.isNull(), None).when(c == 0, 0.0).otherwise(F.least(m / F.nullif(c, F.lit(0.0)), F.lit(1.0)))
