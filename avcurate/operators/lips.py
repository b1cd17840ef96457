"""Lip-region extraction: points, boxes, one crop size a clip, centroids without gaps, crops."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F


def detect_landmarks(frames: DataFrame, detector, n_points: int = 468) -> DataFrame:
    """Slot for a neural detector: ``detector`` maps an iterator of pandas frames with pixels to the same with points."""
    out = ", ".join(f"{f.name} {f.dataType.simpleString()}" for f in frames.schema)
    return frames.mapInPandas(detector, f"{out}, points array<struct<idx:int,x:double,y:double>>")


def unpack_points(values: Column, scale: float = 512.0, origin: float = 256.0) -> Column:
    """Stand-in detector: neighbouring values are the x and y of a point."""
    return F.transform(
        F.sequence(F.lit(0), F.floor(F.size(values) / 2).cast("int") - 1),
        lambda i: F.struct(
            i.alias("idx"),
            (origin + scale * F.element_at(values, 2 * i + 1).cast("double")).alias("x"),
            (origin + scale * F.element_at(values, 2 * i + 2).cast("double")).alias("y"),
        ),
    )


def select_lips(frames: DataFrame, lip_idx: list[int]) -> DataFrame:
    wanted = F.array(*[F.lit(i) for i in lip_idx])
    return frames.withColumn("points", F.filter("points", lambda p: F.array_contains(wanted, p["idx"])))


def lip_track(lips: DataFrame, keep_missing: bool = False) -> DataFrame:
    f = F.explode_outer if keep_missing else F.explode
    return lips.select("clip_id", "frame_no", f("points").alias("p")).select("clip_id", "frame_no", "p.idx", "p.x", "p.y")


def _valid(lips: DataFrame) -> DataFrame:
    return lips.where(F.coalesce(F.size("points"), F.lit(0)) > 0)


def bounding_boxes(lips: DataFrame, form: str = "array") -> DataFrame:
    """x0, y0, x1, y1, w, h of each valid frame; ``long`` groups exploded points instead."""
    if form == "long":
        b = lip_track(lips).groupBy("clip_id", "frame_no").agg(F.min("x").alias("x0"), F.min("y").alias("y0"), F.max("x").alias("x1"), F.max("y").alias("y1"))
    else:
        xs, ys = F.transform("points", lambda p: p["x"]), F.transform("points", lambda p: p["y"])
        b = _valid(lips).select("clip_id", "frame_no", F.array_min(xs).alias("x0"), F.array_min(ys).alias("y0"), F.array_max(xs).alias("x1"), F.array_max(ys).alias("y1"))
    return b.withColumns({"w": F.col("x1") - F.col("x0"), "h": F.col("y1") - F.col("y0")})


def even_ceil(x: Column) -> Column:
    """The smallest even integer that isn't below x; round to nine places first, so that products of decimals count as written."""
    return (2 * F.ceil(F.round(x, 9) / 2)).cast("bigint")


def crop_size(boxes: DataFrame, gamma: float = 1.2, scope: str = "clip") -> DataFrame:
    """mean_w, mean_h, crop, for each clip; scope ``dataset`` gives every clip the same size."""
    means = (F.avg("w").alias("mean_w"), F.avg("h").alias("mean_h"))
    per = boxes.groupBy("clip_id").agg(*means)
    if scope == "dataset":
        per = per.select("clip_id").crossJoin(F.broadcast(boxes.agg(*means)))
    return per.withColumn("crop", even_ceil(gamma * F.greatest("mean_w", "mean_h")))


def crop_size_sweep(boxes: DataFrame, gammas: list[float]) -> DataFrame:
    g = F.explode(F.array(*[F.lit(float(x)) for x in gammas])).alias("gamma")
    return crop_size(boxes).select("clip_id", "mean_w", "mean_h", g).withColumn("crop", even_ceil(F.col("gamma") * F.greatest("mean_w", "mean_h")))


def centroids(lips: DataFrame) -> DataFrame:
    """cx, cy of every frame; null where there are no points."""
    def mean(axis: str) -> Column:
        s = F.aggregate(F.transform("points", lambda p: p[axis]), F.lit(0.0), lambda a, v: a + v)
        return F.when(F.size("points") > 0, s / F.size("points"))
    return lips.select("clip_id", "frame_no", mean("x").alias("cx"), mean("y").alias("cy"))


def interpolate(cents: DataFrame, edge: str = "hold") -> DataFrame:
    """Gaps become points on the line between the valid frames around them; at the ends the nearest holds, or null."""
    w = Window.partitionBy("clip_id").orderBy("frame_no")
    point = F.when(F.col("cx").isNotNull(), F.struct("frame_no", "cx", "cy"))
    before = F.last(point, ignorenulls=True).over(w.rowsBetween(Window.unboundedPreceding, 0))
    after = F.first(point, ignorenulls=True).over(w.rowsBetween(0, Window.unboundedFollowing))
    x = cents.select("clip_id", "frame_no", "cx", "cy", before.alias("b"), after.alias("a"))

    def at(c: str) -> Column:
        b, a = F.col(f"b.{c}"), F.col(f"a.{c}")
        share = (F.col("frame_no") - F.col("b.frame_no")) / F.nullif(F.col("a.frame_no") - F.col("b.frame_no"), F.lit(0))
        held = F.coalesce(b, a) if edge == "hold" else F.lit(None).cast("double")
        return F.when(F.col(c).isNotNull(), F.col(c)).when(b.isNotNull() & a.isNotNull(), b + (a - b) * share).otherwise(held)

    return x.select("clip_id", "frame_no", at("cx").alias("cx2"), at("cy").alias("cy2"), F.col("cx").isNull().alias("filled")).withColumnsRenamed({"cx2": "cx", "cy2": "cy"})


def crop_windows(cents: DataFrame, sizes: DataFrame, clamp: tuple[int, int] | None = None) -> DataFrame:
    """Windows of a clip's size around the centroids; clamp (width, height) moves them into the image."""
    j = cents.where("cx is not null").join(sizes.select("clip_id", "crop"), "clip_id")
    x0, y0 = F.col("cx") - F.col("crop") / 2, F.col("cy") - F.col("crop") / 2
    if clamp:
        x0, y0 = (F.greatest(F.lit(0.0), F.least(v, F.lit(float(m)) - F.col("crop"))) for v, m in ((x0, clamp[0]), (y0, clamp[1])))
    return j.select("clip_id", "frame_no", "crop", x0.alias("x0"), y0.alias("y0")).withColumns({"x1": F.col("x0") + F.col("crop"), "y1": F.col("y0") + F.col("crop")})


def crop_pixels(frames: DataFrame, windows: DataFrame, pad: float | None = 0.0) -> DataFrame:
    """Pixels of integer windows (x0, y0, crop) in row-major order; outside the image ``pad``, or dropped where it is None."""
    j = frames.join(windows.select("clip_id", "frame_no", "x0", "y0", "crop"), ["clip_id", "frame_no"])

    def pixel(i: Column) -> Column:
        x = F.col("x0") + i % F.col("crop")
        y = F.col("y0") + F.floor(i / F.col("crop"))
        inside = (x >= 0) & (x < F.col("width")) & (y >= 0) & (y < F.col("height"))
        value = F.element_at("pixels", (y * F.col("width") + x + 1).cast("int")).cast("double")
        return F.when(inside, value).otherwise(F.lit(pad).cast("double"))

    cut = F.transform(F.sequence(F.lit(0).cast("bigint"), F.col("crop") * F.col("crop") - 1), pixel)
    return j.select("clip_id", "frame_no", "crop", (F.filter(cut, lambda v: v.isNotNull()) if pad is None else cut).alias("pixels"))


def coverage(lips: DataFrame) -> DataFrame:
    valid = F.coalesce(F.size("points"), F.lit(0)) > 0
    return lips.groupBy("clip_id").agg(F.count("*").alias("frames"), F.count_if(valid).alias("valid_frames")).withColumn("coverage", F.col("valid_frames") / F.col("frames"))


def screen(clips: DataFrame, min_coverage: float = 0.8, min_consistency: float = 0.2) -> DataFrame:
    """clips (clip_id, coverage, s_asr) -> clip_id, keep, reason; thresholds are inclusive, unknown values fail."""
    low_c = F.coalesce(F.round("coverage", 9) < min_coverage, F.lit(True))
    low_s = F.coalesce(F.round("s_asr", 9) < min_consistency, F.lit(True))
    reason = F.when(low_c, "occluded").when(low_s, "mismatched").otherwise("ok")
    return clips.select("clip_id", (~low_c & ~low_s).alias("keep"), reason.alias("reason"))


def track_jitter(cents: DataFrame, windows: DataFrame) -> DataFrame:
    """Mean step of the centroid in the frame, and within its crop."""
    w = Window.partitionBy("clip_id").orderBy("frame_no")
    j = cents.join(windows.select("clip_id", "frame_no", "x0", "y0"), ["clip_id", "frame_no"])

    def step(x: Column, y: Column) -> Column:
        return F.sqrt(F.pow(x - F.lag(x).over(w), 2) + F.pow(y - F.lag(y).over(w), 2))

    s = j.select("clip_id", step(F.col("cx"), F.col("cy")).alias("raw"), step(F.col("cx") - F.col("x0"), F.col("cy") - F.col("y0")).alias("crop"))
    return s.groupBy("clip_id").agg(F.avg("raw").alias("jitter_raw"), F.avg("crop").alias("jitter_crop"))
