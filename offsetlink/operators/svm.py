"""The Gaussian-kernel baseline: source identity enters as features; labelled pairs are few, so duals are solved exactly."""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

#: The dual needs memory quadratic in labels; more labels need solver="rff".
DUAL_ROWS = 6000


def encode_sources(s1: Column, s2: Column, sources: int) -> Column:
    """One 1 for each of the two sources, whatever their order."""
    return F.transform(F.sequence(F.lit(1), F.lit(sources)), lambda k: ((k == s1) | (k == s2)).cast("double"))


def inputs(frame: pd.DataFrame, features: list[str], sources: int, scale: float = 1.0) -> np.ndarray:
    x = frame[features].to_numpy(float) / scale
    hot = np.zeros((len(frame), sources))
    rows = np.arange(len(frame))
    hot[rows, frame["s1"].to_numpy() - 1] = 1
    hot[rows, frame["s2"].to_numpy() - 1] = 1
    return np.concatenate([x, hot], 1)


def kernel(a: np.ndarray, b: np.ndarray, sigma: float) -> np.ndarray:
    square = (a * a).sum(1)[:, None] + (b * b).sum(1)[None, :] - 2 * a @ b.T
    return np.exp(-np.maximum(square, 0) / (2 * sigma * sigma))


def fit_dual(k: np.ndarray, y: np.ndarray, c: float, passes: int = 20_000, tol: float = 1e-3) -> np.ndarray:
    """Signed multipliers of the soft-margin dual; the bias is part of the kernel (k + 1).

    Projected gradient steps with momentum; now and then the multipliers between their bounds solve their own quadratic
    problem, which ends the fit once the right ones are between.  Ends when no multiplier's margin misses its condition by
    more than tol, and raises where that isn't reached.
    """
    q = (k + 1) * np.outer(y, y)
    v = np.ones(len(y))
    for _ in range(20):
        u = q @ v
        top = float(np.linalg.norm(u)) or 1.0
        v = u / top
    single, rate = q.astype(np.float32), np.float32(1 / (1.05 * top))

    def missed(alpha, gradient):
        held = (alpha <= 0) & (gradient > 0) | (alpha >= c) & (gradient < 0)
        return np.abs(gradient[~held]).max(initial=0)

    alpha = ahead = np.zeros(len(y), np.float32)
    t = 1.0
    for step in range(1, passes + 1):
        new = np.clip(ahead - rate * (single @ ahead - 1), 0, np.float32(c))
        t = 1.0 if float((ahead - new) @ (new - alpha)) > 0 else t
        t2 = (1 + np.sqrt(1 + 4 * t * t)) / 2
        alpha, ahead, t = new, new + np.float32((t - 1) / t2) * (new - alpha), t2
        if step % 50 == 0:
            exact = alpha.astype(float)
            gradient = q @ exact - 1
            between = np.flatnonzero((exact > 0) & (exact < c))
            if len(between):
                moved = exact[between] - np.linalg.solve(q[np.ix_(between, between)] + 1e-8 * np.eye(len(between)), gradient[between])
                tried = exact.copy()
                tried[between] = np.clip(moved, 0, c)
                after = q @ tried - 1
                if missed(tried, after) < missed(exact, gradient):
                    exact, gradient = tried, after
                    alpha = ahead = tried.astype(np.float32)
                    t = 1.0
            if missed(exact, gradient) <= tol:
                return exact * y
    raise RuntimeError("the dual has not converged")


class RbfSvm:
    def __init__(self, c: float = 1.0, sigma: float = 1.0, solver: str = "dual", dims: int = 512, tol: float = 1e-3) -> None:
        self.c, self.sigma, self.solver, self.dims, self.tol = c, sigma, solver, dims, tol

    def fit(self, x: np.ndarray, y: np.ndarray) -> RbfSvm:
        self.mean, self.scale = x.mean(0), np.where(x.std(0) > 1e-12, x.std(0), 1.0)
        z = (x - self.mean) / self.scale
        if self.solver == "rff":
            rng = np.random.default_rng(11)
            self.w, self.b = rng.normal(0, 1 / self.sigma, (z.shape[1], self.dims)), rng.uniform(0, 2 * np.pi, self.dims)
            f = self._lift(z)
            self.beta = np.zeros(f.shape[1])
            for step in range(1, 600):  # squared hinge by gradient steps
                slack = np.maximum(0, 1 - y * (f @ self.beta))
                self.beta -= 0.5 / step**0.5 * (self.beta / (self.c * len(y)) - f.T @ (slack * y) * 2 / len(y))
            return self
        if len(y) > DUAL_ROWS:
            raise ValueError("too many labels for the dual; use solver='rff'")
        signed = fit_dual(kernel(z, z, self.sigma), y, self.c, tol=self.tol)
        keep = signed != 0
        self.vectors, self.signed = z[keep], signed[keep]
        return self

    def _lift(self, z: np.ndarray) -> np.ndarray:
        return np.concatenate([np.sqrt(2 / self.dims) * np.cos(z @ self.w + self.b), np.ones((len(z), 1))], 1)

    def score(self, x: np.ndarray) -> np.ndarray:
        z = (x - self.mean) / self.scale
        if self.solver == "rff":
            return self._lift(z) @ self.beta
        return (kernel(z, self.vectors, self.sigma) + 1) @ self.signed if len(self.signed) else np.zeros(len(z))


def tune(train: DataFrame, features: list[str], sources: int, cs: list[float], sigmas: list[float], folds: int = 10, scale: float = 1.0) -> DataFrame:
    """Held-out error for each (c, sigma), from one task for each of them and each fold."""
    spark = train.sparkSession
    cells = spark.createDataFrame([(float(c), float(s), k) for c in cs for s in sigmas for k in range(folds)], "c double, sigma double, held int")
    rows = train.select("s1", "s2", "y", *features, "fold")
    if rows.limit(DUAL_ROWS + 1).count() > DUAL_ROWS:
        raise ValueError("too many labels for the dual; use solver='rff'")

    def error(key, frame: pd.DataFrame) -> pd.DataFrame:
        c, sigma, held = key
        rest, out = frame[frame.fold != held], frame[frame.fold == held]
        if rest.empty or out.empty:
            return pd.DataFrame({"c": [c], "sigma": [sigma], "held": [held], "wrong": [0], "n": [0]})
        model = RbfSvm(c, sigma).fit(inputs(rest, features, sources, scale), rest.y.to_numpy(float))
        wrong = int(((model.score(inputs(out, features, sources, scale)) >= 0) != (out.y.to_numpy() > 0)).sum())
        return pd.DataFrame({"c": [c], "sigma": [sigma], "held": [held], "wrong": [wrong], "n": [len(out)]})

    each = rows.crossJoin(F.broadcast(cells)).groupBy("c", "sigma", "held").applyInPandas(error, "c double, sigma double, held int, wrong long, n long")
    return each.groupBy("c", "sigma").agg((F.sum("wrong") / F.sum("n")).alias("error"))


def tuned(frame: pd.DataFrame, features: list[str], sources: int, cs: tuple, sigmas: tuple, folds: int, scale: float = 1.0) -> RbfSvm:
    """The machine with the least held-out error over the folds of rows in memory; ties go to the first of the grid."""
    x, y, fold = inputs(frame, features, sources, scale), frame["y"].to_numpy(float), frame["fold"].to_numpy() % folds
    wrong = {}
    for sigma in sigmas:
        for c in cs:
            wrong[c, sigma] = 0
            for k in np.unique(fold):
                held = fold == k
                if len(np.unique(y[~held])) == 2:
                    wrong[c, sigma] += int(((RbfSvm(c, sigma, tol=5e-2).fit(x[~held], y[~held]).score(x[held]) >= 0) != (y[held] > 0)).sum())
    return RbfSvm(*min(wrong, key=wrong.get)).fit(x, y)


def predict(pairs: DataFrame, model: RbfSvm, features: list[str], sources: int, scale: float = 1.0) -> DataFrame:
    """Pairs with a column score; the support vectors travel with the function."""
    names = [f for f in pairs.columns if f != "score"]
    schema = ", ".join(f"`{f.name}` {f.dataType.simpleString()}" for f in pairs.schema if f.name != "score") + ", score double"

    def scored(frames):
        for f in frames:
            step, out = max(1, 4_000_000 // max(len(getattr(model, "signed", [])), 1)), []
            for at in range(0, len(f), step):
                out.append(model.score(inputs(f.iloc[at : at + step], features, sources, scale)))
            yield f.assign(score=np.concatenate(out) if out else np.zeros(0))

    return pairs.select(*names).mapInPandas(scored, schema)
