"""Vector algebra on array columns."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F


def _c(x: Column | str) -> Column:
    return (F.col(x) if isinstance(x, str) else x).cast("array<double>")


def total(x: Column) -> Column:
    return F.aggregate(x, F.lit(0.0), lambda a, v: a + v)


def dot(a: Column | str, b: Column | str) -> Column:
    return total(F.zip_with(_c(a), _c(b), lambda x, y: x * y))


def norm(a: Column | str) -> Column:
    return F.sqrt(dot(a, a))


def cosine(a: Column | str, b: Column | str) -> Column:
    """Null where a vector is zero or null; vectors of unlike lengths are an error."""
    x, y = _c(a), _c(b)
    n = norm(a) * norm(b)
    same = F.when(F.size(x) == F.size(y), dot(a, b)).when(x.isNotNull() & y.isNotNull(), F.raise_error(F.lit("vectors of unlike lengths")).cast("double"))
    return F.when(n > 0, same / n)


def mean_difference(a: Column | str, b: Column | str, kind: str = "l1") -> Column:
    """Mean difference of two arrays: absolute (l1), root of squares (l2) or signed."""
    f = {"l1": lambda x, y: F.abs(y - x), "l2": lambda x, y: (y - x) * (y - x), "signed": lambda x, y: y - x}[kind]
    m = F.try_divide(total(F.zip_with(_c(a), _c(b), f)), F.size(_c(a)))
    return F.sqrt(m) if kind == "l2" else m
