"""Vector expressions: unrolled over columns for few dimensions, over arrays otherwise."""

from __future__ import annotations

from functools import reduce

from pyspark.sql import Column
from pyspark.sql import functions as F


def dot(xs: list[Column], ws: list[Column]) -> Column:
    return reduce(lambda a, b: a + b, (x * w for x, w in zip(xs, ws, strict=True)))


def array_dot(x: Column, w: Column) -> Column:
    return F.aggregate(F.zip_with(x, w, lambda a, b: a * b), F.lit(0.0), lambda s, v: s + v)


def soft_threshold(v: Column, tau: Column | float) -> Column:
    """Each value moved towards 0 by tau, and to 0 within it; the sign of 0 is 0."""
    return F.signum(v) * F.greatest(F.abs(v) - tau, F.lit(0.0))


def limit_deviation(wi: Column, wj: Column) -> Column:
    """The pair deviation when its penalty grows without bound: half the difference of the two sources' vectors."""
    return F.zip_with(wi, wj, lambda a, b: (b - a) / 2)


def norm(v: Column, kind: str = "l2") -> Column:
    if kind == "l1":
        return F.aggregate(v, F.lit(0.0), lambda s, x: s + F.abs(x))
    if kind == "max":
        return F.aggregate(v, F.lit(0.0), lambda s, x: F.greatest(s, F.abs(x)))
    return F.sqrt(F.aggregate(v, F.lit(0.0), lambda s, x: s + x * x))


def contributions(names: list[str], xs: list[Column], ws: list[Column]) -> Column:
    """A map from feature to its share of a score."""
    return F.map_from_arrays(F.array(*map(F.lit, names)), F.array(*(x * w for x, w in zip(xs, ws, strict=True))))
