"""Joins that Spark lacks an operator for, rewritten so that they meet by equality first."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F


def interval_join(left: DataFrame, right: DataFrame, key: str, left_t: str, right_t: str, seconds: float) -> DataFrame:
    """Rows of the same key with 0 <= right_t - left_t <= seconds; times in seconds (double).

    Time is cut into buckets of ``seconds``. A left row goes to its own bucket and the next, so a
    match is found by equality of key and bucket, and then checked exactly.
    """
    b = F.floor(F.col(left_t) / seconds)
    le = left.withColumn("_b", F.explode(F.array(b, b + 1)))
    ri = right.withColumn("_b", F.floor(F.col(right_t) / seconds))
    gap = F.col(right_t) - F.col(left_t)
    return le.join(ri, [key, "_b"]).where((gap >= 0) & (gap <= seconds)).drop("_b")


def asof_join(left: DataFrame, right: DataFrame, key: str, t: str, value: str) -> DataFrame:
    """left with the last value of right before or at t, for each key: one sort of the union, no pairs."""
    both = left.withColumns({"_side": F.lit(1), "_v": F.lit(None).cast(right.schema[value].dataType)}).select(*left.columns, "_side", "_v")
    pad = [F.col(key), F.col(t)] + [F.lit(None).cast(left.schema[c].dataType).alias(c) for c in left.columns if c not in (key, t)]
    other = right.select(*pad, F.lit(0).alias("_side"), F.col(value).alias("_v")).select(*left.columns, "_side", "_v")
    w = Window.partitionBy(key).orderBy(t, "_side").rowsBetween(Window.unboundedPreceding, 0)
    return both.unionByName(other).withColumn(f"last_{value}", F.last("_v", ignorenulls=True).over(w)).where("_side = 1").drop("_side", "_v")


def sessions(events: DataFrame, key: str, t: str, gap: float) -> DataFrame:
    """Sessions of a key: a gap of more than ``gap`` seconds begins a new one."""
    w = Window.partitionBy(key).orderBy(t)
    new = F.when(F.col(t) - F.lag(t).over(w) <= gap, 0).otherwise(1)
    numbered = events.withColumn("_new", new).withColumn("session", F.sum("_new").over(w.rowsBetween(Window.unboundedPreceding, 0)))
    return numbered.groupBy(key, "session").agg(F.count("*").alias("n"), F.min(t).alias("first_t"), F.max(t).alias("last_t"))
