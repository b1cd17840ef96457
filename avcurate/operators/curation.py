"""Quality scores of clips and the split into accepted and rejected ones."""

from __future__ import annotations

from dataclasses import dataclass, field

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from avcurate.functions.text import asr_confidence, asr_confidence_bounded, length_gap, longer_length
from avcurate.operators.motion import motion_cap, motion_magnitude, video_score
from avcurate.operators.normalise import apply_minmax, exact_quantile, fit_minmax
from avcurate.operators.signal import snr_db


@dataclass(frozen=True)
class CurationPolicy:
    w_asr: float = 0.5
    w_snr: float = 0.5
    w_audio: float = 0.6
    w_video: float = 0.4
    threshold: float = 0.55
    motion_quantile: float = 0.9
    motion_norm: str = "l1"
    cap_method: str = "exact"
    scope: str = "dataset"  # or speaker: min and max of the ratio for each
    inf_policy: str = "cap"
    modalities: str = "both"  # or audio, video
    renormalise: bool = False  # weigh what is there where a modality is missing
    mode: str = "threshold"  # or stochastic
    extra: dict = field(default_factory=dict)


def clip_signals(clips: DataFrame, audio: DataFrame, frames: DataFrame, policy: CurationPolicy = CurationPolicy(), with_text: bool = False) -> DataFrame:
    """One narrow row for each clip: s_asr (or the texts), snr_db, snr_kind, motion. Worth writing once at scale."""
    text = ["ref_text", "hyp_text"] if with_text else [asr_confidence("hyp_text", "ref_text").alias("s_asr")]
    return (
        clips.select("clip_id", "speaker", "category", *text)
        .join(snr_db(audio).select("clip_id", "snr_db", "snr_kind"), "clip_id", "left")
        .join(motion_magnitude(frames, policy.motion_norm).select("clip_id", "motion"), "clip_id", "left")
        .withColumn("snr_kind", F.coalesce("snr_kind", F.lit("none")))
    )


def fit_stats(signals: DataFrame, policy: CurationPolicy = CurationPolicy()) -> DataFrame:
    """One row: snr_min, snr_max, motion_cap, n. A stored copy scores later batches and streams."""
    cap = motion_cap(signals, policy.motion_quantile, policy.cap_method)
    span = signals.agg(F.min("snr_db").alias("snr_min"), F.max("snr_db").alias("snr_max"), F.count("*").alias("n"))
    return span.crossJoin(F.broadcast(cap.select("motion_cap")))


def audio_score(s_asr: Column, snr_norm: Column, weights: tuple[float, float] = (0.5, 0.5)) -> Column:
    parts = [w * c for w, c in zip(weights, (s_asr, snr_norm)) if w]
    return sum(parts[1:], parts[0])


def composite_score(s_audio: Column, s_video: Column, policy: CurationPolicy = CurationPolicy()) -> Column:
    if policy.modalities != "both":
        return s_audio if policy.modalities == "audio" else s_video
    both = policy.w_audio * s_audio + policy.w_video * s_video
    return F.coalesce(both, s_audio, s_video) if policy.renormalise else both


def uniform(key: Column) -> Column:
    """A number in [0, 1) from md5 of the key."""
    return F.conv(F.substring(F.md5(key.cast("string").cast("binary")), 1, 8), 16, 10).cast("double") / 4294967296.0


def partition(df: DataFrame, threshold: float = 0.55, mode: str = "threshold") -> DataFrame:
    """split and reason. Scores are compared after rounding to nine places, so that decimals count as written."""
    s = F.round("s_comp", 9)
    take = s >= threshold if mode == "threshold" else uniform(F.col("clip_id")) < F.least(F.lit(1.0), s / threshold)
    split = F.when(F.coalesce(take, F.lit(False)), "accept").otherwise("reject")
    reason = F.when(F.col("s_comp").isNull(), "missing_modality").when(take, "score").otherwise("low_score")
    return df.withColumns({"split": split, "reason": reason})


def score(signals: DataFrame, stats: DataFrame, policy: CurationPolicy = CurationPolicy()) -> DataFrame:
    """Scores and split of clips by given statistics; narrow but for scope ``speaker``."""
    if policy.scope == "speaker":
        norm = apply_minmax(signals, fit_minmax(signals, "snr_db", ["speaker"]), "snr_db", "snr_norm", "snr_kind", policy.inf_policy, ["speaker"])
        norm = norm.crossJoin(F.broadcast(stats.select("motion_cap")))
    else:
        both = stats.select(F.col("snr_min").alias("lo"), F.col("snr_max").alias("hi"), "motion_cap")
        norm = apply_minmax(signals, both, "snr_db", "snr_norm", "snr_kind", policy.inf_policy)
    audio = audio_score(F.col("s_asr"), F.col("snr_norm"), (policy.w_asr, policy.w_snr))
    norm = norm.withColumns({"s_audio": audio, "s_video": video_score("motion", "motion_cap")})
    scored = norm.withColumn("s_comp", composite_score(F.col("s_audio"), F.col("s_video"), policy)).drop("motion_cap")
    return partition(scored, policy.threshold, policy.mode)


def curate(clips: DataFrame, audio: DataFrame, frames: DataFrame, policy: CurationPolicy = CurationPolicy(), stats: DataFrame | None = None, fit_on: DataFrame | None = None) -> DataFrame:
    """One row for every clip; ``fit_on`` (clip_id) limits what statistics are fitted on, for instance to the training part."""
    signals = clip_signals(clips, audio, frames, policy)
    if stats is None:
        stats = fit_stats(signals if fit_on is None else signals.join(fit_on.select("clip_id"), "clip_id", "left_semi"), policy)
    return score(signals, stats, policy)


def hard_examples(curated: DataFrame) -> DataFrame:
    """Rejected clips stay: they are the later phase's training set."""
    return curated.where("split = 'reject'")


def accept_curve(curated: DataFrame, thresholds: list[float]) -> DataFrame:
    """threshold, accepted, rate: one pass with one conditional count for each threshold."""
    s = F.round("s_comp", 9)
    counts = curated.agg(F.count("*").alias("n"), *[F.count_if(s >= t).alias(f"t{i}") for i, t in enumerate(thresholds)])
    rows = F.explode(F.array(*[F.struct(F.lit(float(t)).alias("threshold"), F.col(f"t{i}").alias("accepted")) for i, t in enumerate(thresholds)]))
    return counts.select("n", rows.alias("r")).select("r.threshold", "r.accepted", (F.col("r.accepted") / F.col("n")).alias("rate"))


def threshold_for_rate(curated: DataFrame, rate: float) -> DataFrame:
    """The threshold that accepts about the given share of scored clips."""
    return exact_quantile(curated, "s_comp", 1.0 - rate, "threshold")


def uncertain(signals: DataFrame, policy: CurationPolicy) -> DataFrame:
    """clip_id, low, high: clips whose split a cap within the sketch's rank error could change, with their scores under the outer caps.

    Scores fall as the cap grows, so the caps at the two ends of the error bound all between them.
    """
    error = {"exact": 0.0, "approx": 1e-4, "kll": 0.0133}[policy.cap_method]
    span = signals.agg(F.min("snr_db").alias("snr_min"), F.max("snr_db").alias("snr_max"))
    ends = []
    for q in (min(1.0, policy.motion_quantile + error), max(0.0, policy.motion_quantile - error)):
        stats = span.crossJoin(F.broadcast(motion_cap(signals, q, policy.cap_method).select("motion_cap")))
        ends.append(score(signals, stats, policy).select("clip_id", "s_comp", "split"))
    low, high = ends[0].toDF("clip_id", "low", "low_split"), ends[1].toDF("clip_id", "high", "high_split")
    return low.join(high, "clip_id").where("low_split <> high_split").select("clip_id", "low", "high")


def exact_mean(col: str) -> Column:
    """Mean of values of nine places, summed as decimals, so that it doesn't depend on the order of rows."""
    return F.try_divide(F.sum(F.round(col, 9).cast("decimal(28,9)")).cast("double"), F.count(col))


def curation_report(curated: DataFrame, by: tuple[str, ...] = ("split", "speaker")) -> DataFrame:
    return curated.rollup(*by).agg(
        F.grouping_id().cast("bigint").alias("level"), F.count("*").alias("n"), exact_mean("s_asr").alias("mean_asr"), exact_mean("snr_db").alias("mean_snr"), exact_mean("motion").alias("mean_motion"), exact_mean("s_comp").alias("mean_comp")
    )


def curate_bounded(clips: DataFrame, audio: DataFrame, frames: DataFrame, policy: CurationPolicy = CurationPolicy()) -> DataFrame:
    """The same split, with edit distances only for clips that the other scores leave open.

    With N and V known, the text adds at most its own weight; a difference in length bounds the
    distance from below; what is left needs a distance within a band that the threshold sets.
    """
    signals = clip_signals(clips, audio, frames, policy, with_text=True)
    stats = fit_stats(signals, policy).select(F.col("snr_min").alias("lo"), F.col("snr_max").alias("hi"), "motion_cap")
    x = apply_minmax(signals, stats, "snr_db", "snr_norm", "snr_kind", policy.inf_policy).withColumn("s_video", video_score("motion", "motion_cap"))
    w_text = policy.w_audio * policy.w_asr
    base = policy.w_audio * policy.w_snr * F.col("snr_norm") + policy.w_video * F.col("s_video")
    longer, gap = longer_length("hyp_text", "ref_text"), length_gap("hyp_text", "ref_text")
    slack = 1e-9
    x = x.withColumns({"base": base, "longer": longer, "need": (policy.threshold - base) / w_text})
    k = F.floor((1 - F.col("need")) * F.col("longer") + 1e-6).cast("int")
    x = x.withColumn("k", F.greatest(F.lit(-1), F.least(k, F.col("longer"))))
    text = asr_confidence_bounded("hyp_text", "ref_text", F.col("k"))
    passes = F.round(F.col("base") + w_text * text, 9) >= policy.threshold
    decided = (
        F.when(F.col("base").isNull() | F.col("longer").isNull(), "missing")
        .when(F.round("base", 9) >= policy.threshold, "bounds")
        .when(F.col("base") + w_text + slack < policy.threshold, "bounds")
        .when(gap > F.col("k"), "length").otherwise("banded")
    )
    x = x.withColumn("decided_by", decided)
    take = F.when(F.col("decided_by") == "bounds", F.round("base", 9) >= policy.threshold).when(F.col("decided_by") == "banded", F.coalesce(passes, F.lit(False))).otherwise(False)
    return x.select("clip_id", F.when(take, "accept").otherwise("reject").alias("split"), "decided_by")


def label_agreement(curated: DataFrame, labels: DataFrame) -> tuple[DataFrame, DataFrame]:
    """(confusion counts of split and quality, area under the curve of the composite by rank sums).

    Ranks come from counts of equal scores in distributed partial sums, not from a global window.
    """
    j = curated.select(F.col("clip_id").alias("doc_id"), "split", F.round("s_comp", 9).alias("s")).join(labels, "doc_id")
    confusion = j.groupBy("split", "quality").agg(F.count("*").alias("n"))
    v = j.where("s is not null").groupBy("s").agg(F.count_if(F.col("quality") == 1).alias("pos"), F.count_if(F.col("quality") == 0).alias("neg"))
    return confusion, v


def auc(counts: DataFrame, buckets: int = 1000) -> DataFrame:
    """Area under the curve from (s, pos, neg): scores are cut into equal buckets, ranked within each, and added up."""
    from pyspark.sql import Window

    b = counts.withColumn("b", F.least(F.lit(buckets - 1), F.floor(F.col("s") * buckets)))
    w = Window.partitionBy("b").orderBy("s").rowsBetween(Window.unboundedPreceding, -1)
    inner = b.withColumn("below", F.coalesce(F.sum("neg").over(w), F.lit(0)))
    per = inner.groupBy("b").agg(F.sum(F.col("pos") * (F.col("below") + F.col("neg") / 2)).alias("u"), F.sum("pos").alias("pos"), F.sum("neg").alias("neg"))
    base = Window.orderBy("b").rowsBetween(Window.unboundedPreceding, -1)  # at most ``buckets`` rows
    u = per.withColumn("before", F.coalesce(F.sum("neg").over(base), F.lit(0)))
    return u.agg((F.sum(F.col("u") + F.col("pos") * F.col("before")) / (F.sum("pos") * F.sum("neg"))).alias("auc"))
