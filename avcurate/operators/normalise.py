"""Min-max normalisation over a dataset: statistics are a one-row aggregate, never a global window."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F


def fit_minmax(df: DataFrame, col: str, by: list[str] | None = None) -> DataFrame:
    """lo, hi of the finite values; one row, or one for each group."""
    g = df.groupBy(*by) if by else df.groupBy()
    return g.agg(F.min(col).alias("lo"), F.max(col).alias("hi"))


def exact_quantile(df: DataFrame, col: str, q: float, out: str, buckets: int = 1024) -> DataFrame:
    """One row: the q-quantile of the values that are there, with linear interpolation, exactly.

    Values are counted in equal ranges of the span, which tells the ranges that hold the two ranks
    wanted; only these ranges' values are counted one by one. No task holds all distinct values.
    """
    x = df.where(F.col(col).isNotNull()).select(F.col(col).cast("double").alias("v"))
    span = x.agg(F.min("v").alias("lo"), F.max("v").alias("hi"), F.count("*").alias("n"))
    place = F.when(F.col("hi") > F.col("lo"), F.least(F.lit(buckets - 1), F.floor((F.col("v") - F.col("lo")) / (F.col("hi") - F.col("lo")) * buckets))).otherwise(0)
    placed = x.crossJoin(F.broadcast(span)).select("v", place.alias("b"))
    ranges = placed.groupBy("b").agg(F.count("*").alias("c")).agg(F.sort_array(F.collect_list(F.struct("b", "c"))).alias("r"))  # at most ``buckets``
    below = F.aggregate(F.slice("r", F.lit(1), F.col("i")), F.lit(0).cast("bigint"), lambda s, x: s + x["c"])
    counts = ranges.select("r", F.posexplode("r").alias("i", "x")).select(F.col("x.b").alias("b"), F.col("x.c").alias("c"), below.alias("before")).withColumn("upto", F.col("before") + F.col("c"))
    at = span.select((F.lit(q) * (F.col("n") - 1)).alias("at"))
    wanted = counts.crossJoin(F.broadcast(at)).where((F.col("before") <= F.ceil("at")) & (F.col("upto") > F.floor("at"))).select("b", "before", "at")
    values = placed.join(F.broadcast(wanted), "b").groupBy("b", "before", "at", "v").agg(F.count("*").alias("c"))
    inner = Window.partitionBy("b").orderBy("v").rowsBetween(Window.unboundedPreceding, 0)
    ranked = values.withColumn("end", F.col("before") + F.sum("c").over(inner))  # ranks end - c to end - 1 have this value
    has = lambda rank: (F.col("end") - F.col("c") <= rank) & (F.col("end") > rank)
    low, high = F.floor("at"), F.ceil("at")
    ends = ranked.agg(F.max(F.when(has(low), F.col("v"))).alias("a"), F.max(F.when(has(high), F.col("v"))).alias("z"), F.max("at").alias("at"))
    return ends.select((F.col("a") + (F.col("z") - F.col("a")) * (F.col("at") - F.floor("at"))).alias(out))


def scaled(value: Column, lo: Column, hi: Column, constant: float | None = 0.0) -> Column:
    """(value - lo) / (hi - lo), held in 0..1 for values the statistics haven't seen; a constant column gives ``constant``."""
    s = F.greatest(F.lit(0.0), F.least(F.lit(1.0), (value - lo) / F.nullif(hi - lo, F.lit(0.0))))
    return F.when(value.isNotNull() & (hi == lo), F.lit(constant).cast("double")).when(value.isNotNull() & (hi > lo), s)


def apply_minmax(df: DataFrame, stats: DataFrame, col: str, out: str, kind: str | None = None, inf_policy: str = "cap", by: list[str] | None = None, constant: float | None = 0.0) -> DataFrame:
    """inf_policy for ``kind`` pos_inf and neg_inf: cap (1 and 0), null, or drop (the rows go)."""
    j = df.join(stats, by, "left") if by else df.crossJoin(F.broadcast(stats))
    v = scaled(F.col(col), F.col("lo"), F.col("hi"), constant)
    if kind and inf_policy == "cap":
        v = F.when(F.col(kind) == "pos_inf", 1.0).when(F.col(kind) == "neg_inf", 0.0).otherwise(v)
    if kind and inf_policy == "drop":
        j = j.where(~F.col(kind).isin("pos_inf", "neg_inf"))
    return j.withColumn(out, v).drop("lo", "hi")
