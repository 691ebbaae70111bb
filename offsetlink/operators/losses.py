"""Other losses with the same offsets, and the squared loss for more source pairs than a driver holds.

A step for another loss takes one pass over the labels, which sums the loss's local quadratic model by source pair: these
are moments with curvatures as weights, so the solver for moments takes the step.  Few such steps converge.  For the
squared loss on the cluster, an iteration is one pass over moments; only weights meet on the driver.
"""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import dataclass

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from offsetlink.operators import moments, scoring, solver
from offsetlink.operators.learners import OffsetModel
from offsetlink.operators.solver import PENALTIES, VALUES


def _squared(m, y):
    return (m - y) ** 2 / 2, m - y


def _logistic(m, y):
    z = -y * m
    return np.logaddexp(0, z), -y / (1 + np.exp(-z))


def _squared_hinge(m, y):
    slack = np.maximum(0, 1 - y * m)
    return slack**2 / 2, -y * slack


#: Source pairs for each task of an iteration on the cluster, and tasks whose sums the driver adds up itself.
PAIRS_A_TASK, FEW_TASKS = 2000, 16
#: Value and derivative by margin, and a bound of the second derivative.
LOSSES: dict[str, tuple[Callable, float]] = {"squared": (_squared, 1.0), "logistic": (_logistic, 0.25), "squared_hinge": (_squared_hinge, 1.0)}


#: Second derivative by margin.
CURVES: dict[str, Callable] = {
    "squared": lambda m, y: np.ones_like(m),
    "logistic": lambda m, y: 1 / (2 + np.exp(y * m) + np.exp(-y * m)),
    "squared_hinge": lambda m, y: (y * m < 1).astype(float),
}


def gradient(pairs: DataFrame, features: list[str], w0: np.ndarray, w: np.ndarray, sources: list[int], loss: str = "logistic", scale: float = 1.0) -> tuple[float, np.ndarray, np.ndarray]:
    """Loss and gradients of the shared vector and the offsets, over all rows, in one pass."""
    at, d = {s: i for i, s in enumerate(sources)}, len(features) + 1

    def partial(batches):
        value, total = 0.0, np.zeros((len(sources) + 1, d))
        for b in batches:
            x = np.column_stack([np.ones(len(b)), *(b.column(f).to_numpy(zero_copy_only=False) / scale for f in features)])
            y = b.column("y").to_numpy(zero_copy_only=False).astype(float)
            i, j = (np.array([at[s] for s in b.column(c).to_pylist()], int) for c in ("s1", "s2"))
            v, slope = LOSSES[loss][0]((x * (w0 + (w[i] + w[j]) / 2)).sum(1), y)
            part = slope[:, None] * x
            value += v.sum()
            total[0] += part.sum(0)
            np.add.at(total, i + 1, part / 2)
            np.add.at(total, j + 1, part / 2)
        n = total.size + 1
        yield pa.RecordBatch.from_arrays([pa.array(range(n), pa.int32()), pa.array(np.concatenate([[value], total.ravel()]))], names=["k", "v"])

    parts = pairs.select("s1", "s2", "y", *(F.col(f).cast("double").alias(f) for f in features)).mapInArrow(partial, "k int, v double")
    out = np.zeros((len(sources) + 1) * d + 1)
    for r in parts.groupBy("k").agg(F.sum("v").alias("v")).collect():
        out[r.k] = r.v
    g = out[1:].reshape(-1, d)
    return float(out[0]), g[0], g[1:]


def local_terms(loss: str, m: Column, y: Column) -> tuple[Column, Column, Column]:
    """Value, derivative and second derivative of a loss at margin m of a label y."""
    if loss == "squared":
        return (m - y) ** 2 / 2, m - y, F.lit(1.0)
    if loss == "logistic":
        p = 1 / (1 + F.exp(y * m))
        return F.greatest(-y * m, F.lit(0.0)) + F.log1p(F.exp(-F.abs(y * m))), -y * p, p * (1 - p)
    if loss == "squared_hinge":
        slack = F.greatest(1 - y * m, F.lit(0.0))
        return slack**2 / 2, -y * slack, (slack > 0).cast("double")
    raise ValueError(f"no loss {loss}")


def local_moments(pairs: DataFrame, features: list[str], model: OffsetModel, loss: str, scale: float = 1.0) -> moments.Block:
    """The loss's quadratic model at a model's weights, by source pair: curvatures as gram, slopes as cross, values as yy."""
    scored = scoring.score(moments.canonical(pairs), [({"model": 0}, model)], features, scale)
    value, slope, curve = local_terms(loss, F.col("score"), F.col("y").cast("double"))
    xs = [F.lit(1.0), *(F.col(f) / scale for f in features)]
    d = len(features)
    gram = [F.sum(curve * xs[a] * xs[b]).alias(f"g{a}_{b}") for a in range(d + 1) for b in range(a, d + 1)]
    cross = [F.sum(slope * xs[a]).alias(f"c{a}") for a in range(d + 1)]
    return moments.to_driver(scored.groupBy("s1", "s2").agg(F.count("*").alias("n"), *gram, *cross, F.sum(value).alias("yy")), d)[()]


@dataclass
class LossLearner:
    """Source offsets under a loss of choice, by steps that solve the loss's quadratic model; rows should be cached.

    A step is halved until the objective falls.  Ends when the optimality conditions hold to tol, relative to the number
    of labels, and raises where that isn't reached, as on separable labels under a logistic loss without penalty.
    """

    lam: float
    loss: str = "logistic"
    penalty: str = "l1"
    max_iter: int = 60
    tol: float = 1e-7
    pooled: bool = False  # one weight vector for all pairs of sources

    def fit(self, pairs: DataFrame, features: list[str], scale: float = 1.0) -> OffsetModel:
        d = len(features) + 1
        name = f"{'pooled' if self.pooled else 'offset'}_{self.loss}"
        lam = 0.0 if self.pooled else self.lam
        at = OffsetModel(name, np.zeros(d))
        block = local_moments(pairs, features, at, self.loss, scale)
        sources = block.sources
        w0, w = np.zeros(d), np.zeros((len(sources), d))
        cost = block.yy.sum()
        for steps in range(self.max_iter):
            problem = solver.Problem.of(block)
            u = problem.pair_weights(w0, w)
            model = moments.Block(block.s1, block.s2, block.n, block.gram, np.einsum("pab,pb->pa", block.gram, u) - block.cross, np.zeros(len(block.n)))
            local = solver.Problem.of(model)
            if optimality(local, w0, w, lam, self.penalty, self.pooled) <= self.tol * block.n.sum():
                return OffsetModel(name, w0, {int(s): w[i] for i, s in enumerate(sources) if np.any(w[i])}, info={"loss": float(block.yy.sum()), "objective": float(cost), "steps": steps})
            start = solver.Solution(w0, w, sources, 0, 0.0)
            to = solver.solve(local, lam, self.penalty, max_iter=20000, tol=1e-11, start=start, freeze_offsets=self.pooled)
            share, before = 1.0, cost
            while True:
                n0, n = w0 + share * (to.w0 - w0), w + share * (to.w - w)
                tried = local_moments(pairs, features, OffsetModel(name, n0, {int(s): n[i] for i, s in enumerate(sources)}), self.loss, scale)
                cost = tried.yy.sum() + lam * VALUES[self.penalty](n)
                if cost <= before + 1e-12 * abs(before) or share < 1e-8:
                    break
                share /= 2
            w0, w, block = n0, n, tried
        raise RuntimeError(f"{name} has not converged in {self.max_iter} steps")


def optimality(problem: solver.Problem, w0: np.ndarray, w: np.ndarray, lam: float, penalty: str = "l1", pooled: bool = False) -> float:
    """How far a step of unit length moves: 0 at an optimum of the loss and its penalty."""
    g0, g = problem.gradient(w0, w)
    moved = 0.0 if pooled else float(np.abs(w - PENALTIES[penalty](w - g, lam)).max(initial=0))
    return max(float(np.abs(g0).max(initial=0)), moved)


def fit_pairwise_loss(pairs: DataFrame, features: list[str], loss: str = "logistic", scale: float = 1.0, ridge: float = 1e-3, rounds: int = 200) -> OffsetModel:
    """An unrelated weight vector per source pair under a loss, one task for each pair's labels."""
    bound = LOSSES[loss][1]

    def fit(key, frame: pd.DataFrame) -> pd.DataFrame:
        x = np.column_stack([np.ones(len(frame)), frame[features].to_numpy(float) / scale])
        y, w = frame["y"].to_numpy(float), np.zeros(len(features) + 1)
        curve = CURVES[loss]
        cost = lambda w: LOSSES[loss][0](x @ w, y)[0].sum() + ridge / 2 * (w @ w)
        for _ in range(rounds):
            m = x @ w
            g = x.T @ LOSSES[loss][0](m, y)[1] + ridge * w
            if np.abs(g).max() <= 1e-9 * len(y):
                return pd.DataFrame({"s1": [key[0]], "s2": [key[1]], "w": [w.tolist()]})
            step, share = np.linalg.solve((x * curve(m, y)[:, None]).T @ x + ridge * np.eye(len(w)), g), 1.0
            while cost(w - share * step) > cost(w) and share > 1e-10:
                share /= 2
            w = w - share * step
        raise RuntimeError(f"pair {key} has not converged")

    rows = pairs.select("s1", "s2", "y", *features).groupBy("s1", "s2").applyInPandas(fit, "s1 int, s2 int, w array<double>").collect()
    return OffsetModel(f"pairwise_{loss}", np.zeros(len(features) + 1), pairs={(r.s1, r.s2): np.array(r.w) for r in rows}, pairs_only=True)


def gradient_from_moments(moments: DataFrame, d: int, w0: np.ndarray, w: dict[int, np.ndarray], scale: float = 1.0, tasks: int | None = None) -> tuple[np.ndarray, dict[int, np.ndarray]]:
    """The squared loss's gradients with the moments left on the cluster: a map and one sum per source.

    A task sums its pairs by source.  The sums of so few tasks as FEW_TASKS meet on the driver, those of more in a shuffle.
    """
    upper = np.triu_indices(d + 1)
    names = [f"g{a}_{b}" for a, b in zip(*upper, strict=True)], [f"c{a}" for a in range(d + 1)]
    unit, none = np.concatenate([[1.0], np.full(d, 1 / scale)]), np.zeros(d + 1)

    def partial(frames):
        total: dict[int, np.ndarray] = {}
        for f in frames:
            gram = np.zeros((len(f), d + 1, d + 1))
            gram[:, upper[0], upper[1]] = f[names[0]].to_numpy()
            gram = (gram + np.transpose(np.triu(gram, 1), (0, 2, 1))) * unit[:, None] * unit[None, :]
            u = np.array([w0 + (w.get(i, none) + w.get(j, none)) / 2 for i, j in zip(f.s1, f.s2, strict=True)])
            r = np.einsum("pab,pb->pa", gram, u) - f[names[1]].to_numpy() * unit
            for ends in (f.s1.to_numpy(), f.s2.to_numpy()):
                sources, at = np.unique(ends, return_inverse=True)
                sums = np.stack([np.bincount(at, c, len(sources)) for c in r.T / 2], 1)
                for s, v in zip(sources.tolist(), sums, strict=True):
                    total[s] = total.get(s, 0) + v
        if total:
            yield pd.DataFrame({"source": list(total), "r": [v.tolist() for v in total.values()]})

    doubles = [moments[c].cast("double").alias(c) for c in (*names[0], *names[1])]
    parts = moments.select("s1", "s2", *doubles).mapInPandas(partial, "source int, r array<double>")
    each: dict[int, np.ndarray] = {}
    if tasks is not None and tasks <= FEW_TASKS:
        for r in parts.collect():
            each[r.source] = each.get(r.source, 0) + np.array(r.r)
    else:
        for r in parts.groupBy("source").agg(*(F.sum(F.col("r")[a]).alias(f"r{a}") for a in range(d + 1))).collect():
            each[r.source] = np.array([r[f"r{a}"] for a in range(d + 1)])
    return sum(each.values()), each  # every pair's residual counts half for each of its two sources


def _standardised(moments_: DataFrame, d: int, scale: float) -> np.ndarray:
    """T of features of mean 0 and variance 1, from the sums of all source pairs."""
    total = moments_.agg(*(F.sum(F.col(c).cast("double")).alias(c) for c in (*(f"g0_{a}" for a in range(d + 1)), *(f"g{a}_{a}" for a in range(1, d + 1))))).first()
    unit = np.concatenate([[1.0], np.full(d, 1 / scale)])
    first = np.array([total[f"g0_{a}"] for a in range(d + 1)]) * unit
    square = np.array([total[f"g{a}_{a}"] for a in range(d + 1)]) * unit**2
    gram = np.zeros((1, d + 1, d + 1))
    gram[0, 0], gram[0, :, 0] = first, first
    gram[0][np.diag_indices(d + 1)] = square
    none = np.zeros((1, d + 1))
    return moments.scaler(moments.Block(np.zeros(1), np.ones(1), first[:1], gram, none, none[0]))


def solve_on_cluster(moments_: DataFrame, d: int, lam: float, scale: float = 1.0, max_iter: int = 3000, penalty: str = "l1", tol: float = 1e-6, standardise: bool = True) -> OffsetModel:
    """Proximal gradient where each iteration is one job over cached moments; only weights meet on the driver.

    The penalty is on offsets of standardised features, unless standardise is False.  Steps are as long as each source's
    own moments allow; momentum is dropped where it overshoots.  Ends when the optimality conditions hold to tol, relative
    to the number of labels, and raises where that isn't reached.
    """
    doubles = moments_.select("s1", "s2", *(F.col(c).cast("double").alias(c) for c in moments_.columns if c[0] in "gc" and c[1].isdigit())).cache()
    # Few source pairs in many partitions would make each iteration many tiny tasks.
    tasks = -(-doubles.count() // PAIRS_A_TASK) or 1
    fewer = doubles.coalesce(tasks).cache()
    try:
        t = _standardised(fewer, d, scale) if standardise else np.eye(d + 1)
        w0, w, steps = _cluster_steps(fewer, d, lam, scale, max_iter, penalty, tol, t, tasks)
    finally:
        fewer.unpersist()
        doubles.unpersist()
    return OffsetModel("offset", w0, {s: x for s, x in w.items() if np.any(x)}, info={"steps": steps}).untransformed(t)


def _cluster_steps(doubles: DataFrame, d: int, lam: float, scale: float, max_iter: int, penalty: str, tol: float, t: np.ndarray, tasks: int):
    none = np.zeros(d + 1)

    def gradients(v0, v):
        # Weights of standardised features act on the others through T; gradients come back through it.
        g0, g = gradient_from_moments(doubles, d, t.T @ v0, {s: t.T @ x for s, x in v.items()}, scale, tasks)
        return t @ g0, {s: t @ x for s, x in g.items()}

    sides = doubles.select("s1", F.explode(F.array("s1", "s2")).alias("source"), *(c for c in doubles.columns if c[0] == "g"))
    upper = list(zip(*np.triu_indices(d + 1), strict=True))
    unit = np.concatenate([[1.0], np.full(d, 1 / scale)])
    own = {}
    for r in sides.groupBy("source").agg(*(F.sum(f"g{a}_{b}").alias(f"g{a}_{b}") for a, b in upper)).collect():
        gram = np.zeros((d + 1, d + 1))
        for a, b in upper:
            gram[a, b] = gram[b, a] = r[f"g{a}_{b}"] * unit[a] * unit[b]
        own[r.source] = t @ gram @ t.T
    return bounded_steps(gradients, own, lam, max_iter, penalty, tol)


def bounded_steps(gradients: Callable, own: dict[int, np.ndarray], lam: float, max_iter: int, penalty: str, tol: float):
    """Minimise a squared loss of w0 + (w_i + w_j) / 2 from its gradients and each source's own moments.

    (a + b / 2 + c / 2)^2 is at most 3 a^2 + 3/4 b^2 + 3/4 c^2, so the sources' own moments bound the loss from above, for
    each source by itself; a step minimises that bound and the penalty, source by source.
    """
    names, prox = sorted(own), PENALTIES[penalty]
    each = np.array([own[s] for s in names])
    n, whole, bound = each[:, 0, 0].sum() / 2, 1.5 * each.sum(0), 0.75 * each
    if penalty == "group":  # its map joins all sources, so they need one rate
        bound = np.broadcast_to(np.eye(each.shape[1]) * np.linalg.eigvalsh(bound)[:, -1].max(), each.shape)
    diagonal = np.maximum(np.einsum("skk->sk", bound), 1e-12)

    def stepped(v, g):
        if penalty == "group":
            return prox(v - g / diagonal, lam / diagonal[0, 0])
        x = v.copy()
        for _ in range(200):
            before = x.copy()
            for k in range(x.shape[1]):
                slope = g[:, k] + np.einsum("sl,sl->s", bound[:, k], x - v)
                x[:, k] = prox(x[:, k] - slope / diagonal[:, k], lam / diagonal[:, k])
            if np.abs(x - before).max() <= 1e-13:
                break
        return x

    w0 = v0 = np.zeros(each.shape[1])
    w = v = np.zeros(each.shape[:2])
    inverse, k = np.linalg.pinv(whole, rcond=1e-12, hermitian=True), 1.0
    for step in range(1, max_iter + 1):
        g0, parts = gradients(v0, dict(zip(names, v, strict=True)))
        g = np.array([parts[s] for s in names])
        n0, new = v0 - inverse @ g0, stepped(v, g)
        # How far the step went, in units of the gradient: 0 at an optimum.
        back0, back = whole @ (v0 - n0), np.einsum("skl,sl->sk", bound, v - new)
        if max(np.abs(g0).max(), np.abs(back).max()) <= tol * n:
            return n0, dict(zip(names, new, strict=True)), step
        # Momentum that points against the step has overshot.
        k = 1.0 if back0 @ (n0 - w0) + (back * (new - w)).sum() > 0 else k
        k2 = (1 + np.sqrt(1 + 4 * k * k)) / 2
        v0, v = n0 + (k - 1) / k2 * (n0 - w0), new + (k - 1) / k2 * (new - w)
        w0, w, k = n0, new, k2
    raise RuntimeError(f"no optimum in {max_iter} steps")


def random_features(pairs: DataFrame, features: list[str], dim: int, gamma: float, scale: float = 1.0, seed: int = 5) -> DataFrame:
    """Pairs with z1..z_dim, random cosine features of a Gaussian kernel: linear learners on them are kernel learners."""
    rng = np.random.default_rng(seed)
    w, b = rng.normal(0, np.sqrt(2 * gamma), (len(features), dim)), rng.uniform(0, 2 * np.pi, dim)

    def lifted(batches):
        for batch in batches:
            x = np.column_stack([batch.column(f).to_numpy(zero_copy_only=False) / scale for f in features])
            z = np.sqrt(2 / dim) * np.cos(x @ w + b)
            yield pa.RecordBatch.from_arrays([*(batch.column(c) for c in ("s1", "s2", "y")), *(pa.array(c) for c in z.T)], names=["s1", "s2", "y", *(f"z{k + 1}" for k in range(dim))])

    ddl = "s1 int, s2 int, y int, " + ", ".join(f"z{k + 1} double" for k in range(dim))
    return pairs.select(F.col("s1").cast("int").alias("s1"), F.col("s2").cast("int").alias("s2"), F.col("y").cast("int").alias("y"), *(F.col(f).cast("double").alias(f) for f in features)).mapInArrow(lifted, ddl)
