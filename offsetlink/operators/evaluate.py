"""Measures on scored pairs: confusion, error, curves, bands, label cost, convergence."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from offsetlink.plans import relational

# Two-sided 95 % points of Student's t for 1 to 30 degrees of freedom; beyond, the normal one.
T95 = [12.706, 4.303, 3.182, 2.776, 2.571, 2.447, 2.365, 2.306, 2.262, 2.228, 2.201, 2.179, 2.160, 2.145, 2.131, 2.120, 2.110, 2.101, 2.093, 2.086, 2.080, 2.074, 2.069, 2.064, 2.060, 2.056, 2.052, 2.048, 2.045, 2.042]


def confusion(scored: DataFrame, tau: float = 0.0, by: list[str] | None = None) -> DataFrame:
    """tp, fp, fn, tn over pairs with a score."""
    hit, true = F.col("score") >= tau, F.col("y") > 0
    count = lambda c, n: F.sum(F.when(c, 1).otherwise(0)).cast("long").alias(n)
    some = scored.where(F.col("score").isNotNull())
    return some.groupBy(*(by or [])).agg(count(hit & true, "tp"), count(hit & ~true, "fp"), count(~hit & true, "fn"), count(~hit & ~true, "tn"))


def precision_recall(scored: DataFrame, tau: float = 0.0, by: list[str] | None = None) -> DataFrame:
    """Null precision where nothing is predicted, null recall where nothing is true."""
    c = confusion(scored, tau, by)
    return c.withColumns({"precision": F.try_divide(F.col("tp"), F.col("tp") + F.col("fp")), "recall": F.try_divide(F.col("tp"), F.col("tp") + F.col("fn"))})


def test_error(scored: DataFrame, tau: float = 0.0, by: list[str] | None = None) -> DataFrame:
    wrong = (F.col("score") >= tau) != (F.col("y") > 0)
    return scored.where(F.col("score").isNotNull()).groupBy(*(by or [])).agg(F.avg(wrong.cast("double")).alias("test_error"), F.count("*").alias("n_test"))


def macro_error(scored: DataFrame, tau: float = 0.0, by: list[str] | None = None) -> DataFrame:
    """The mean over source pairs of their errors."""
    return test_error(scored, tau, [*(by or []), "s1", "s2"]).groupBy(*(by or [])).agg(F.avg("test_error").alias("macro_error"), F.count("*").alias("n_pairs"))


def pr_curve(scored: DataFrame, by: list[str] | None = None, bins: int | None = None, low: float = -2.0, high: float = 2.0) -> DataFrame:
    """tau, tp, fp, fn, precision, recall for every threshold: each distinct score, or the lower ends of bins.

    Scores are counted by threshold first, partially before the shuffle; only the counts meet in the running sums.
    """
    keys = by or []
    tau = F.col("score") if bins is None else low + F.greatest(F.lit(0), F.least(F.lit(bins - 1), F.floor((F.col("score") - low) / ((high - low) / bins)))) * ((high - low) / bins)
    true = (F.col("y") > 0).cast("long")
    counts = scored.where(F.col("score").isNotNull()).groupBy(*keys, tau.alias("tau")).agg(F.sum(true).alias("pos"), F.sum(1 - true).alias("neg"))
    if bins is None:
        # Thresholds are as many as scores: running sums go by ranges of thresholds, and ranges by their totals.
        counts = counts.withColumn("range_", relational.range_bins(counts, "tau"))
        totals = counts.groupBy(*keys, "range_").agg(F.sum("pos").alias("pos_"), F.sum("neg").alias("neg_"))
        above = Window.partitionBy(*(keys or [F.lit(0)])).orderBy(F.desc("range_")).rowsBetween(Window.unboundedPreceding, -1)
        starts = totals.select(*(F.col(k).alias(f"{k}_") for k in keys), F.col("range_").alias("its_"), *(F.coalesce(F.sum(f"{c}_").over(above), F.lit(0)).alias(f"{c}_above") for c in ("pos", "neg")))
        inside = Window.partitionBy(*keys, "range_").orderBy(F.desc("tau")).rowsBetween(Window.unboundedPreceding, 0)
        same = F.col("range_") == F.col("its_")
        for k in keys:
            same = same & F.col(k).eqNullSafe(F.col(f"{k}_"))
        c = counts.withColumns({"tp": F.sum("pos").over(inside), "fp": F.sum("neg").over(inside)}).join(starts, same)
        every = totals.groupBy(*keys).agg(F.sum("pos_").alias("all_pos"))
        c = c.select(*keys, "tau", (F.col("tp") + F.col("pos_above")).alias("tp"), (F.col("fp") + F.col("neg_above")).alias("fp"))
        named = every.select(*(F.col(k).alias(f"{k}_") for k in keys), "all_pos")
        match = F.lit(True)
        for k in keys:
            match = match & F.col(k).eqNullSafe(F.col(f"{k}_"))
        c = c.join(named, match) if keys else c.crossJoin(F.broadcast(named))
    else:
        down = Window.partitionBy(*(keys or [F.lit(0)])).orderBy(F.desc("tau")).rowsBetween(Window.unboundedPreceding, 0)
        whole = Window.partitionBy(*(keys or [F.lit(0)]))
        c = counts.select(*keys, "tau", F.sum("pos").over(down).alias("tp"), F.sum("neg").over(down).alias("fp"), F.sum("pos").over(whole).alias("all_pos"))
    return c.select(*keys, "tau", "tp", "fp", (F.col("all_pos") - F.col("tp")).alias("fn"), (F.col("tp") / (F.col("tp") + F.col("fp"))).alias("precision"), F.try_divide("tp", "all_pos").alias("recall"))


def precision_at_recall(curve: DataFrame, recall: float = 0.85, by: list[str] | None = None) -> DataFrame:
    """The precision at the largest threshold whose recall is at least that."""
    return curve.where(F.col("recall") >= recall).groupBy(*(by or [])).agg(F.max("tau").alias("tau"), F.max_by("precision", "tau").alias("precision"), F.max_by("recall", "tau").alias("recall"))


def band(values: DataFrame, value: str, by: list[str], method: str = "t") -> DataFrame:
    """Mean and pointwise 95 % band over the rows (trials) of each group."""
    if method == "percentile":
        q = lambda p: F.percentile(value, F.lit(p))
        out = values.groupBy(*by).agg(F.count(value).alias("trials"), F.avg(value).alias("mean"), q(0.025).alias("low"), q(0.975).alias("high"))
    else:
        t = F.element_at(F.array(*map(F.lit, T95)), F.greatest(F.least(F.col("trials") - 1, F.lit(30)), F.lit(1)).cast("int"))
        half = F.when(F.col("trials") > 31, F.lit(1.96)).otherwise(t) * F.col("sd") / F.sqrt("trials")
        stats = values.groupBy(*by).agg(F.count(value).alias("trials"), F.avg(value).alias("mean"), F.stddev_samp(value).alias("sd"))
        out = stats.select(*by, "trials", "mean", (F.col("mean") - half).alias("low"), (F.col("mean") + half).alias("high"))
    return out.withColumn("width", F.col("high") - F.col("low"))


def label_ledger(train: DataFrame, by: list[str] | None = None) -> DataFrame:
    """Labels used per source pair, per source and in total, by grouping sets."""
    sides = train.select(*(by or []), "s1", "s2", F.explode(F.array("s1", "s2")).alias("source"))
    keys = by or []
    per_pair = train.groupBy(*keys, "s1", "s2").count().select(*keys, F.lit("pair").alias("level"), "s1", "s2", F.col("count").alias("labels"))
    per_source = sides.groupBy(*keys, "source").count().select(*keys, F.lit("source").alias("level"), F.col("source").alias("s1"), F.lit(None).cast("int").alias("s2"), F.col("count").alias("labels"))
    total = train.groupBy(*keys).agg(F.count("*").alias("labels")).select(*keys, F.lit("total").alias("level"), F.lit(None).cast("int").alias("s1"), F.lit(None).cast("int").alias("s2"), "labels")
    return per_pair.unionByName(per_source).unionByName(total)


def labels_to_target(errors: DataFrame, target: float, by: list[str], labels: str = "labels", error: str = "test_error") -> DataFrame:
    """The fewest labels that reach an error."""
    return errors.where(F.col(error) <= target).groupBy(*by).agg(F.min(labels).alias("labels"))


def growth_exponent(costs: DataFrame, size: str = "sources", labels: str = "labels", by: list[str] | None = None) -> DataFrame:
    """The slope of log labels against log size: about 1 for linear, 2 for quadratic growth."""
    return costs.groupBy(*(by or [])).agg(F.regr_slope(F.log(labels), F.log(size)).alias("exponent"), F.count("*").alias("points"))


def dominance(curves: DataFrame, method: str = "method", grid: int = 20) -> DataFrame:
    """The leading method at each recall of a grid."""
    points = curves.select(method, "precision", F.floor(F.col("recall") * grid).cast("int").alias("step"))
    best = points.groupBy(method, "step").agg(F.max("precision").alias("precision"))
    return best.groupBy("step").agg(F.max_by(method, "precision").alias("leader"), F.max("precision").alias("precision")).select((F.col("step") / grid).alias("recall"), "leader", "precision")


def convergence_rate(trace: DataFrame, optimum: float, by: list[str] | None = None) -> DataFrame:
    """Ratios of successive gaps to the optimum; below 1, and about constant, if convergence is geometric."""
    gap = F.col("objective") - F.lit(optimum)
    before = F.lag(gap).over(Window.partitionBy(*(by or [F.lit(0)])).orderBy("iter"))
    return trace.select(*(by or []), "iter", gap.alias("gap"), F.try_divide(gap, before).alias("ratio"))


def blocking_quality(candidates: DataFrame, truth: DataFrame, all_pairs: int, keys: tuple[str, str] = ("d1", "d2")) -> DataFrame:
    """Share of true pairs that are candidates, and share of all pairs that are not."""
    kept = truth.select(*keys).distinct().join(candidates.select(*keys, F.lit(1).alias("kept")).distinct(), list(keys), "left")
    n = candidates.select(*keys).distinct().agg(F.count("*").alias("candidates"))
    t = kept.agg(F.count("*").alias("true_pairs"), F.count("kept").alias("kept_pairs"))
    return t.crossJoin(n).select("true_pairs", "kept_pairs", "candidates", F.try_divide("kept_pairs", "true_pairs").alias("completeness"), (1 - F.col("candidates") / F.lit(float(max(all_pairs, 1)))).alias("reduction"))

