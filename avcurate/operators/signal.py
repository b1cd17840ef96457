"""Signal-to-noise ratio of clean and noisy samples."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from avcurate.functions.vectors import dot, total


def ratio_db(signal: Column, residual: Column) -> tuple[Column, Column]:
    """(snr_db, snr_kind): null unless both energies are above zero; kinds finite, pos_inf, neg_inf and none."""
    kind = F.when(signal.isNull() | residual.isNull(), "none").when((residual == 0) & (signal == 0), "none").when(residual == 0, "pos_inf").when(signal == 0, "neg_inf").otherwise("finite")
    return F.when((signal > 0) & (residual > 0), 10 * F.log10(signal / residual)), kind


def snr_db(samples: DataFrame, key: str = "clip_id", clean: str = "clean", noisy: str = "noisy") -> DataFrame:
    """One shuffle of two partial sums for each clip and task."""
    s, r = F.col(clean), F.col(clean) - F.col(noisy)
    sums = samples.groupBy(key).agg(F.count("*").alias("n"), F.sum(s * s).alias("signal"), F.sum(r * r).alias("residual"))
    db, kind = ratio_db(F.col("signal"), F.col("residual"))
    return sums.withColumns({"snr_db": db, "snr_kind": kind})


def snr_db_arrays(clean: Column | str, noisy: Column | str) -> tuple[Column, Column]:
    """The same for packed arrays, without a shuffle."""
    c = (F.col(clean) if isinstance(clean, str) else clean).cast("array<double>")
    d = (F.col(noisy) if isinstance(noisy, str) else noisy).cast("array<double>")
    return ratio_db(dot(c, c), total(F.zip_with(c, d, lambda x, y: (x - y) * (x - y))))
