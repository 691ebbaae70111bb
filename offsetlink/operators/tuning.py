"""Penalty selection by hold-out or cross-validation on moments of folds: one pass over the labels, all fits on moments."""

from __future__ import annotations

import numpy as np

from offsetlink.operators import solver
from offsetlink.operators.learners import SourceOffsetLearner
from offsetlink.operators.moments import Block


def grid(learner: SourceOffsetLearner, block: Block, points: int = 10, span: float = 1e3) -> list[float]:
    """Penalties from the least that makes all offsets 0 downwards."""
    top = solver.lambda_max(learner.problem(block))
    return [float(v) for v in np.geomspace(max(top, 1e-9), max(top, 1e-9) / span, points)]


def squared_error(model, block: Block) -> float:
    """Sum of squared errors of a model on a block's rows, from moments alone."""
    u = np.array([model.weights(i, j) for i, j in zip(block.s1.tolist(), block.s2.tolist(), strict=True)])
    return float((block.yy - 2 * (u * block.cross).sum(1) + np.einsum("pa,pab,pb->p", u, block.gram, u)).sum())


def cross_validate(learner: SourceOffsetLearner, total: Block, folds: dict[int, Block], lams: list[float]) -> list[dict]:
    """Mean held-out squared error of each penalty.  A fold's training moments are the total's less its own, and the
    penalty, which belongs to sums, shrinks with the number of rows."""
    import dataclasses

    out, n = [], total.n.sum()
    for lam in lams:
        sse = rows = 0.0
        for held in folds.values():
            rest = total.minus(held)
            fit = dataclasses.replace(learner, lam=lam * rest.n.sum() / n).fit(rest)
            sse += squared_error(fit, held)
            rows += held.n.sum()
        out.append({"lam": lam, "mse": sse / rows})
    return out


def tune(learner: SourceOffsetLearner, total: Block, folds: dict[int, Block], lams: list[float] | None = None, holdout: bool = False) -> float:
    """The penalty with the least error over all folds, or over the first one."""
    lams = lams or grid(learner, total)
    some = dict(list(folds.items())[:1]) if holdout else folds
    return min(cross_validate(learner, total, some, lams), key=lambda r: r["mse"])["lam"]
