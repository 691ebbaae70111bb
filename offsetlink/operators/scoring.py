"""Scores of pairs under one or many models: broadcast joins on source ids and an unrolled sum of products."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from offsetlink.functions.vectors import dot
from offsetlink.operators.learners import OffsetModel

#: Each of the tables of shared vectors, offsets and weights of pairs is broadcast up to so many numbers, and shuffled beyond.
BROADCAST_NUMBERS = 10_000_000


def models_frame(spark: SparkSession, models: list[tuple[dict, OffsetModel]], d: int) -> tuple[DataFrame, DataFrame, DataFrame]:
    """Tables of shared vectors, offsets and pair weights for models told apart by the values in their dicts."""
    keys = list(models[0][0])
    kind = lambda v: "string" if isinstance(v, str) else "double" if isinstance(v, float) else "long"
    head = ", ".join(f"{k} {kind(v)}" for k, v in models[0][0].items())
    ws = ", ".join(f"{{0}}{a} double" for a in range(d + 1))
    shared, offsets, pairs = [], [], []
    for at, m in models:
        label = tuple(at[k] for k in keys)
        base = [None] * (d + 1) if m.pairs_only else [float(v) for v in m.w0]
        shared.append((*label, float(m.share), *base))
        offsets += [(*label, int(s), *map(float, w)) for s, w in m.offsets.items()]
        pairs += [(*label, int(i), int(j), *map(float, w)) for (i, j), w in m.pairs.items()]
    return (
        spark.createDataFrame(shared, f"{head}, share double, {ws.format('w')}"),
        spark.createDataFrame(offsets, f"{head}, source int, {ws.format('o')}"),
        spark.createDataFrame(pairs, f"{head}, s1 int, s2 int, {ws.format('p')}"),
    )


def score(pairs: DataFrame, models: list[tuple[dict, OffsetModel]], features: list[str], scale: float = 1.0, match: tuple[str, ...] = ()) -> DataFrame:
    """Each pair under each model, with a column score; null where a model has no weights for the pair.

    match names keys of the models that must equal columns of the pairs (such as trial).  Sources without an offset
    count as nominal.  Models are broadcast, and nothing is shuffled, up to BROADCAST_NUMBERS; beyond, Spark joins them.
    """
    spark, d = pairs.sparkSession, len(features)
    keys = list(models[0][0])
    shared, offsets, own = models_frame(spark, models, d)
    small = lambda table, rows: F.broadcast(table) if rows * (d + 1) <= BROADCAST_NUMBERS else table
    if not match and len(models) * (d + 1) > BROADCAST_NUMBERS:
        raise ValueError("too many models to score every pair under each; name the columns that they match")
    out = pairs.join(small(shared, len(models)), list(match)) if match else pairs.crossJoin(F.broadcast(shared))
    n_offsets = sum(len(m.offsets) for _, m in models)
    for side in ("s1", "s2"):
        named = offsets.select(*keys, F.col("source").alias(side), *(F.col(f"o{a}").alias(f"{side}_{a}") for a in range(d + 1)))
        out = out.join(small(named, n_offsets), [*keys, side], "left")
    out = out.join(small(own, sum(len(m.pairs) for _, m in models)), [*keys, "s1", "s2"], "left")
    xs: list[Column] = [F.lit(1.0), *(F.col(f) / scale if scale != 1 else F.col(f) for f in features)]
    weight = lambda a: F.coalesce(F.col(f"p{a}"), F.col(f"w{a}") + F.col("share") * (F.coalesce(F.col(f"s1_{a}"), F.lit(0.0)) + F.coalesce(F.col(f"s2_{a}"), F.lit(0.0))))
    return out.select(*(c for c in pairs.columns), *(k for k in keys if k not in pairs.columns), dot(xs, [weight(a) for a in range(d + 1)]).alias("score"))


def score_fixed(pairs: DataFrame, weights: list[float], features: list[str], scale: float = 1.0) -> DataFrame:
    """Scores under literal weights, the constant's first."""
    xs = [F.lit(1.0), *(F.col(f) / scale for f in features)]
    return pairs.withColumn("score", dot(xs, [F.lit(float(w)) for w in weights]))


def decide(scored: DataFrame, tau: float = 0.0, strict: bool = False) -> DataFrame:
    """predicted (1 or -1) and confidence.  A score equal to tau is a match, unless strict."""
    hit = F.col("score") > tau if strict else F.col("score") >= tau
    return scored.withColumns({"predicted": F.when(hit, 1).when(F.col("score").isNotNull(), -1), "confidence": F.abs("score")})
