"""Attribute similarities of two records."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import Column
from pyspark.sql import functions as F


def jaccard(a: Column, b: Column) -> Column:
    """Shared over all distinct elements; 0 if both are empty; null if either is null."""
    union = F.size(F.array_union(a, b))
    return F.when(union > 0, F.size(F.array_intersect(a, b)) / union).when(union == 0, F.lit(0.0))


def edit_distance(a: Column, b: Column, normalise: bool = False) -> Column:
    d = F.levenshtein(a, b)
    return d / F.greatest(F.length(a), F.length(b), F.lit(1)) if normalise else d


def abs_diff(a: Column, b: Column) -> Column:
    return F.abs(a - b)


def attr_diff(a: Column, b: Column, mode: str = "abs") -> Column:
    """Differences of two arrays.  Signed ones are alike for matches and others, so no linear scorer separates them."""
    how = {"abs": lambda x, y: F.abs(x - y), "signed": lambda x, y: x - y, "sq": lambda x, y: (x - y) * (x - y)}[mode]
    return F.zip_with(a, b, how)


def best_over(a: Column, b: Column, similarity: Callable[[Column, Column], Column]) -> Column:
    """The best similarity over two lists of alternatives; null if either is empty."""
    return F.array_max(F.transform(a, lambda x: F.array_max(F.transform(b, lambda y: similarity(x, y)))))


def fill_missing(features: dict[str, Column], how: str = "mean", worst: dict[str, float] | None = None) -> dict[str, Column]:
    """Features without nulls: 0 (the mean, once standardised), the worst value, or 0 beside an indicator feature."""
    out: dict[str, Column] = {}
    for name, c in features.items():
        out[name] = F.coalesce(c, F.lit((worst or {}).get(name, 0.0) if how == "worst" else 0.0))
        if how == "indicator":
            out[f"{name}_missing"] = c.isNull().cast("double")
    return out
