"""Labels at a budget, splits and folds: by hash order, so the same rows whatever the partitions."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F


def sample_labels(pairs: DataFrame, order: Column, k: int, per: str = "pair", extra: list[str] | None = None, max_labels: int | None = None) -> DataFrame:
    """The first k rows in the order of each source pair, of each source, or of all.

    Per source, each source takes the first k rows that it is on either side of, and a row may serve both its sources.
    With max_labels, a sample of more rows is refused.
    """
    extra = extra or []
    if per == "total" and not extra:
        out = pairs.orderBy(order).limit(k)
    elif per == "source":
        first = lambda side: F.row_number().over(Window.partitionBy(*extra, side).orderBy("order_"))
        marked = pairs.withColumn("order_", order)
        sides = marked.withColumn("side_", F.explode(F.array("s1", "s2")))
        taken = sides.withColumn("rank_", first("side_")).where(F.col("rank_") <= k)
        # A row that serves both sources comes twice; its lesser side stands for it.
        out = taken.withColumn("both_", F.min("side_").over(Window.partitionBy(*extra, "s1", "s2", "order_"))).where("side_ = both_").drop("order_", "side_", "rank_", "both_")
    else:
        w = Window.partitionBy(*extra, *{"pair": ["s1", "s2"], "total": []}[per]).orderBy(order)
        out = pairs.withColumn("rank_", F.row_number().over(w)).where(F.col("rank_") <= k).drop("rank_")
    if max_labels is not None and out.limit(max_labels + 1).count() > max_labels:
        raise ValueError("the budget exceeds the labels that may be asked for")
    return out


def split(pairs: DataFrame, key: Column, test_hundredths: int = 30) -> DataFrame:
    """A column role: test for so many hundredths of the keys."""
    return pairs.withColumn("role", F.when(key % 100 < test_hundredths, "test").otherwise("train"))


def with_folds(pairs: DataFrame, key: Column, folds: int) -> DataFrame:
    return pairs.withColumn("fold", (key % folds).cast("int"))


def select_for_labelling(scored: DataFrame, budget: int, per: str = "pair") -> DataFrame:
    """The pairs with the least sure scores, within each source pair, each source, or all."""
    return sample_labels(scored.where(F.col("score").isNotNull()), F.struct(F.abs("score"), "d1", "d2"), budget, per)
