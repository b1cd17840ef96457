"""Splits, difficulty ranks, schedules of training and their accounting."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from avcurate.sources.fixtures import bucket100


def md5_key(col: str):
    return F.md5(F.col(col).cast("string").cast("binary"))


def split_dataset(df: DataFrame, method: str = "hash", frac: float = 0.8, key: str = "clip_id", by: str = "speaker") -> DataFrame:
    """part train or test. hash is narrow; exact gives floor(frac * n) rows; stratified does so for each ``by``.

    exact and stratified find their cuts without a window over all rows: ids are counted by the
    first three hexadecimal digits of their hashes (4096 rows, for each ``by``), whole prefixes
    before the cut are train, and only within prefixes rows are ranked.
    """
    if method == "hash":
        return df.withColumn("part", F.when(bucket100(F.col(key)) < round(100 * frac), "train").otherwise("test"))
    if method == "stratified":
        x = df.withColumns({"pre": F.substring(md5_key(key), 1, 3), "of": F.struct(by)})
        counts = x.groupBy("of", "pre").agg(F.count("*").alias("c"))
        upto = Window.partitionBy("of").orderBy("pre").rowsBetween(Window.unboundedPreceding, -1)
        want = F.floor(frac * F.sum("c").over(Window.partitionBy("of")))
        cut = counts.select("of", "pre", (want - F.coalesce(F.sum("c").over(upto), F.lit(0))).alias("room"))
        rank = F.row_number().over(Window.partitionBy("of", "pre").orderBy(md5_key(key), key))
        return x.withColumn("rank", rank).join(cut, ["of", "pre"]).withColumn("part", F.when(F.col("rank") <= F.col("room"), "train").otherwise("test")).drop("of", "pre", "rank", "room")
    x = df.withColumn("pre", F.substring(md5_key(key), 1, 3))
    upto = Window.orderBy("pre").rowsBetween(Window.unboundedPreceding, -1)  # at most 4096 rows
    counts = x.groupBy("pre").agg(F.count("*").alias("c"))
    total = counts.agg(F.floor(frac * F.sum("c")).alias("want"))
    cut = counts.withColumn("before", F.coalesce(F.sum("c").over(upto), F.lit(0))).crossJoin(F.broadcast(total)).select("pre", (F.col("want") - F.col("before")).alias("room"))
    rank = F.row_number().over(Window.partitionBy("pre").orderBy(md5_key(key), key))
    return x.withColumn("rank", rank).join(F.broadcast(cut), "pre").withColumn("part", F.when(F.col("rank") <= F.col("room"), "train").otherwise("test")).drop("pre", "rank", "room")


def rank_difficulty(df: DataFrame, score: str = "s_comp", buckets: int = 8, key: str = "clip_id") -> DataFrame:
    """Easiest (highest score) first: rank, pct, bucket; ties by key, null scores last.

    The global order comes from counts: rows are counted by range of the score, score and range of
    the (numeric) key, counts are added up within ranges of the score and over them, and only rows
    of one score and one range of keys are numbered together. So no task sees all rows, nor all
    rows without a score.
    """
    keys = df.agg(F.min(key).alias("k0"), F.max(key).alias("k1"))
    x = df.crossJoin(F.broadcast(keys)).withColumn("o", F.coalesce(-F.round(score, 9), F.lit(float("inf"))))
    x = x.withColumn("cell", F.when(F.col("o") == float("inf"), F.lit(1 << 20)).otherwise(F.floor((F.col("o") + 1) * 4096)).cast("bigint"))
    x = x.withColumn("sub", F.floor((F.col(key) - F.col("k0")) / (F.col("k1") - F.col("k0") + 1) * 1024)).drop("k0", "k1")
    place = ["cell", "o", "sub"]
    counts = x.groupBy(*place).agg(F.count("*").alias("c"))
    before = F.coalesce(F.sum("c").over(Window.partitionBy("cell").orderBy("o", "sub").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0))
    cells = counts.groupBy("cell").agg(F.sum("c").alias("c"))
    w = Window.orderBy("cell").rowsBetween(Window.unboundedPreceding, -1)  # some thousand rows at most for scores in 0..1
    base = cells.select("cell", F.coalesce(F.sum("c").over(w), F.lit(0)).alias("base")).crossJoin(F.broadcast(cells.agg(F.sum("c").alias("n"))))
    found = counts.withColumn("before", before).join(F.broadcast(base), "cell").select(*place, (F.col("before") + F.col("base")).alias("base"), "n")
    inner = F.row_number().over(Window.partitionBy(*place).orderBy(key))
    r = x.withColumn("inner", inner).join(found, place).withColumn("rank", (F.col("base") + F.col("inner")).cast("bigint"))
    r = r.withColumn("pct", F.when(F.col("n") > 1, (F.col("rank") - 1) / (F.col("n") - 1)).otherwise(0.0))
    big, small = F.floor(F.col("n") / buckets), F.col("n") % buckets
    border = small * (big + 1)
    bucket = F.when(F.col("rank") <= border, F.floor((F.col("rank") - 1) / (big + 1)) + 1).otherwise(small + F.floor(F.try_divide(F.col("rank") - 1 - border, big)) + 1)
    return r.withColumn("bucket", bucket.cast("int")).drop("o", "cell", "sub", "inner", "base", "n")


#: phases as (phase, splits that it reads, epochs) for modes that the split alone decides.
MODES = {
    "two_phase": lambda e, h: [(1, ("accept",), e), (2, ("reject",), h)],
    "cumulative": lambda e, h: [(1, ("accept",), e), (2, ("accept", "reject"), h)],
    "none": lambda e, h: [(1, ("accept", "reject"), e + h)],
    "reverse": lambda e, h: [(1, ("reject",), h), (2, ("accept",), e)],
    "easy_only": lambda e, h: [(1, ("accept",), e + h)],
}


def curriculum_schedule(curated: DataFrame, mode: str = "two_phase", easy_epochs: int = 3, hard_epochs: int = 5, buckets: int = 8, shuffled: bool = True) -> DataFrame:
    """phase, epoch, clip_id, split and order: the md5 by which an epoch's rows are shuffled anew.

    ranked adds one bucket of difficulty an epoch and needs the column ``bucket``.
    """
    if mode == "ranked":
        x = curated.withColumn("epoch", F.explode(F.sequence(F.col("bucket"), F.lit(max(buckets, easy_epochs + hard_epochs))))).withColumn("phase", F.lit(1))
    else:
        phases = MODES[mode](easy_epochs, hard_epochs)
        mine = F.filter(
            F.array(*[F.struct(F.lit(p).alias("phase"), F.lit(n).alias("epochs"), F.array(*[F.lit(s) for s in splits]).alias("splits")) for p, splits, n in phases]),
            lambda p: F.array_contains(p["splits"], F.col("split")),
        )
        x = curated.withColumn("p", F.explode(mine)).withColumn("phase", F.col("p.phase")).withColumn("epoch", F.explode(F.sequence(F.lit(1), F.col("p.epochs"))))
    out = x.select("phase", "epoch", "clip_id", "split")
    return out.withColumn("order", F.md5(F.concat_ws(":", "phase", "epoch", "clip_id").cast("binary"))) if shuffled else out


def exposure_report(curated: DataFrame, mode: str = "two_phase", **epochs) -> DataFrame:
    """split, samples, exposures, share of all exposures, of a schedule of ``curated``.

    Rows are counted first, and the schedule is made of the counts, so no row is multiplied by its epochs.
    """
    own = ["bucket"] if mode == "ranked" else []
    counted = curated.groupBy("split", *own).agg(F.count("*").alias("c")).withColumn("clip_id", F.struct(*own, "c"))
    made = curriculum_schedule(counted, mode, shuffled=False, **epochs).groupBy("split", "clip_id").agg(F.count("*").alias("epochs"))
    g = made.groupBy("split").agg(F.sum("clip_id.c").alias("samples"), F.sum(F.col("epochs") * F.col("clip_id.c")).alias("exposures"))
    return g.crossJoin(F.broadcast(g.agg(F.sum("exposures").alias("all")))).select("split", "samples", "exposures", (F.col("exposures") / F.col("all")).alias("share"))


def expected_ce(df: DataFrame, prob: str = "p", y: str = "y", by: tuple[str, ...] = ("phase",)) -> DataFrame:
    """Mean cross-entropy of given class probabilities; zeros are floored at 1e-12."""
    p = F.greatest(F.element_at(prob, F.col(y) + 1), F.lit(1e-12))
    return df.groupBy(*by).agg(F.count("*").alias("n"), F.avg(-F.ln(p)).alias("loss"))
