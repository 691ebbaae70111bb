"""Many small experiments at once: each cell (budget, trial, number of sources, ..) is one group of labelled pairs.

A group holds the labels of one experiment, which its design bounds, and one task fits all methods on it and scores the
test pairs of that cell.  Test pairs are few by design and are sent to the tasks, behind a check of their number.
"""

from __future__ import annotations

from collections.abc import Callable

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from offsetlink.operators import learners, moments, solver, svm, tuning

TEST_ROWS, CELL_ROWS = 200_000, 100_000
LINEAR = ("pooled", "pairwise", "offset")


def block_of_rows(frame: pd.DataFrame, features: list[str], scale: float = 1.0) -> moments.Block:
    """Moments by source pair of rows in memory; features as they are, divided by scale."""
    x = np.column_stack([np.ones(len(frame)), frame[features].to_numpy(float) / scale])
    y = frame["y"].to_numpy(float)
    pairs, at = np.unique(frame[["s1", "s2"]].to_numpy(), axis=0, return_inverse=True)
    at = at.ravel()
    order = np.argsort(at, kind="stable")
    x, y, at = x[order], y[order], at[order]
    first = np.searchsorted(at, np.arange(len(pairs)))
    total = lambda v: np.add.reduceat(v, first, axis=0)
    return moments.Block(pairs[:, 0], pairs[:, 1], np.diff([*first, len(at)]), total(x[:, :, None] * x[:, None, :]), total(x * y[:, None]), total(y * y))


def fit_linear(frame: pd.DataFrame, features: list[str], scale: float, folds: int | None) -> list[learners.OffsetModel]:
    """Pooled, pairwise and offset learners; the offsets' penalty by cross-validation, or a fixed share of the largest."""
    block = block_of_rows(frame, features, scale)
    t = moments.scaler(block)
    b = block.transformed(t)
    learner = learners.SourceOffsetLearner(0.0, max_iter=3000, tol=1e-6)
    if folds:
        fold = frame["fold"].to_numpy() % folds
        held = {k: block_of_rows(frame[fold == k], features, scale).transformed(t) for k in np.unique(fold).tolist()}
        learner.lam = tuning.tune(learner, b, held, tuning.grid(learner, b, 6))
    else:
        learner.lam = solver.lambda_max(learner.problem(b)) / 50
    return [m.fit(b).untransformed(t) for m in (learners.PooledLearner(), learners.PairwiseLearner(), learner)]


def linear_scores(model: learners.OffsetModel, frame: pd.DataFrame, features: list[str], scale: float) -> np.ndarray:
    """Scores of rows in memory; missing where the model has no weights for a pair."""
    x = np.column_stack([np.ones(len(frame)), frame[features].to_numpy(float) / scale])
    out = np.full(len(frame), np.nan)
    pairs, at = np.unique(frame[["s1", "s2"]].to_numpy(), axis=0, return_inverse=True)
    for k, (i, j) in enumerate(pairs.tolist()):
        w = model.weights(i, j)
        if w is not None:
            rows = at.ravel() == k
            out[rows] = x[rows] @ w
    return out


def run(labels: DataFrame, keys: list[str], test: DataFrame, features: list[str], scale: float = 1.0, folds: int | None = None, among: Callable | None = None, svm_grid: tuple | None = None, sources: int = 0) -> DataFrame:
    """method, s1, s2, y and score of every test pair under every method, for each cell of labels; with n_labels of the cell.

    labels has the keys, s1, s2, y, the features, and fold if folds are asked for.  among(key, test rows) picks a cell's
    test pairs.  svm_grid is (values of c, values of sigma, folds); then the kernel baseline is tuned and fitted too.
    """
    spark = labels.sparkSession
    rows = test.select("s1", "s2", "r", "y", *features).limit(TEST_ROWS + 1).toPandas()
    if len(rows) > TEST_ROWS:
        raise ValueError("too many test pairs to send to every task")
    rows = rows.sort_values(["s1", "s2", "r"], kind="stable").reset_index(drop=True)
    sent = spark.sparkContext.broadcast(rows)

    def cell(key, frame: pd.DataFrame) -> pd.DataFrame:
        if len(frame) > CELL_ROWS:
            raise ValueError("a cell has more labels than one task should hold; fit it on moments")
        frame = frame.sort_values(["s1", "s2", "r"], kind="stable")
        mine = sent.value if among is None else sent.value[among(key, sent.value)]
        scores = {m.method: linear_scores(m, mine, features, scale) for m in fit_linear(frame, features, scale, folds)}
        if svm_grid:
            scores["rbf_svm"] = svm.tuned(frame, features, sources, *svm_grid, scale).score(svm.inputs(mine, features, sources, scale))
        out = pd.concat([mine[["s1", "s2", "y"]].assign(method=m, score=s) for m, s in scores.items()])
        return out.assign(n_labels=len(frame), **dict(zip(keys, key, strict=True)))[[*keys, "n_labels", "method", "s1", "s2", "y", "score"]]

    kinds = ", ".join(f"{k} {labels.schema[k].dataType.simpleString()}" for k in keys)
    columns = [*keys, "s1", "s2", "r", "y", *features, *(["fold"] if folds or svm_grid else [])]
    scored = labels.select(*columns).groupBy(*keys).applyInPandas(cell, f"{kinds}, n_labels long, method string, s1 int, s2 int, y int, score double")
    return scored.withColumn("score", F.when(~F.isnan("score"), F.col("score")))
