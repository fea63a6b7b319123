"""Distances between array columns as plain expressions, summed from left to right in double precision."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F


def _c(x: Column | str) -> Column:
    return F.col(x) if isinstance(x, str) else x


def _sum(a: Column | str, b: Column | str, f) -> Column:
    return F.aggregate(F.zip_with(_c(a), _c(b), lambda x, y: f(x.cast("double"), y.cast("double"))), F.lit(0.0), lambda s, v: s + v)


def l2sq(a, b) -> Column:
    return _sum(a, b, lambda x, y: (x - y) * (x - y))


def l2(a, b) -> Column:
    return F.sqrt(l2sq(a, b))


def dot(a, b) -> Column:
    return _sum(a, b, lambda x, y: x * y)


def cosine(a, b) -> Column:
    """Null where a norm is zero."""
    n = F.sqrt(dot(a, a)) * F.sqrt(dot(b, b))
    return F.when(n > 0, dot(a, b) / n)


def distance(metric: str, a, b) -> Column:
    """Smaller is nearer: squared L2, negated inner product, or one minus cosine."""
    if metric == "l2":
        return l2sq(a, b)
    if metric == "ip":
        return -dot(a, b)
    if metric == "cosine":
        return F.lit(1.0) - cosine(a, b)
    raise ValueError(f"unknown metric {metric}")
