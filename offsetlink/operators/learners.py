"""Learners of one linear scorer per source pair, on blocks of moments, and the models that they give."""

from __future__ import annotations

import json
from dataclasses import dataclass, field

import numpy as np
from pyspark.sql import DataFrame, SparkSession

from offsetlink import schema
from offsetlink.operators import solver
from offsetlink.operators.moments import Block
from offsetlink.operators.solver import Problem, Solution


@dataclass
class OffsetModel:
    """Shared vector, offsets by source, and, if any, weights of single pairs.  Feature 0 is the constant."""

    method: str
    w0: np.ndarray
    offsets: dict[int, np.ndarray] = field(default_factory=dict)
    pairs: dict[tuple[int, int], np.ndarray] = field(default_factory=dict)
    share: float = 0.5
    pairs_only: bool = False  # no weights but those of pairs: other pairs can't be scored
    info: dict = field(default_factory=dict)

    def weights(self, i: int, j: int) -> np.ndarray | None:
        """The weights of a pair of sources, in either order; sources without labels have no offset."""
        key = (min(i, j), max(i, j))
        if key in self.pairs:
            return self.pairs[key]
        if self.pairs_only:
            return None
        none = np.zeros_like(self.w0)
        return self.w0 + self.share * (self.offsets.get(i, none) + self.offsets.get(j, none))

    def untransformed(self, t: np.ndarray) -> OffsetModel:
        """The model for raw features, given that this one is for features T x."""
        back = lambda w: t.T @ w
        return OffsetModel(self.method, back(self.w0), {s: back(w) for s, w in self.offsets.items()}, {p: back(w) for p, w in self.pairs.items()}, self.share, self.pairs_only, self.info)

    def size(self) -> tuple[int, int]:
        """Parameters and those that aren't 0."""
        every = [] if self.pairs_only else [self.w0, *self.offsets.values()]
        every = np.concatenate([*every, *self.pairs.values()]) if every or self.pairs else np.zeros(0)
        return len(every), int((every != 0).sum())

    def rows(self) -> list[tuple]:
        out = [] if self.pairs_only else [(self.method, "shared", None, None, self.w0.tolist())]
        out += [(self.method, "source", int(s), None, w.tolist()) for s, w in sorted(self.offsets.items())]
        return out + [(self.method, "pair", int(i), int(j), w.tolist()) for (i, j), w in sorted(self.pairs.items())]

    def to_df(self, spark: SparkSession) -> DataFrame:
        return spark.createDataFrame(self.rows(), schema.WEIGHTS)

    def save(self, spark: SparkSession, path: str) -> None:
        self.to_df(spark).coalesce(1).write.mode("overwrite").parquet(f"{path}/weights")
        meta = [(json.dumps({"method": self.method, "share": self.share, "pairs_only": self.pairs_only, "dims": len(self.w0), "info": self.info}),)]
        spark.createDataFrame(meta, "meta string").coalesce(1).write.mode("overwrite").text(f"{path}/meta")

    @classmethod
    def load(cls, spark: SparkSession, path: str) -> OffsetModel:
        meta = json.loads(spark.read.text(f"{path}/meta").first().value)
        out = cls(meta["method"], np.zeros(meta["dims"]), share=meta["share"], pairs_only=meta["pairs_only"], info=meta["info"])
        for r in spark.read.schema(schema.WEIGHTS).parquet(f"{path}/weights").collect():
            w = np.array(r.w)
            if r.kind == "shared":
                out.w0 = w
            elif r.kind == "source":
                out.offsets[r.s1] = w
            else:
                out.pairs[(r.s1, r.s2)] = w
        return out


@dataclass
class SourceOffsetLearner:
    """The joint learner: a shared vector and sparse offsets of sources.

    pair_ridge keeps deviations of pairs with that ridge; without it they are half the difference of the offsets, which
    gives w0 + (w_i + w_j) / 2.  split_penalty adds what the literal program charges for differing offsets of a pair,
    which the working form leaves out; as the ridge grows the literal program becomes the pooled learner.
    """

    lam: float
    pair_ridge: float | None = None
    split_penalty: bool = False
    penalty: str = "l1"
    max_iter: int = 5000
    tol: float = 1e-9
    step: float | str = "exact"
    accelerate: bool = True
    offset_intercept: bool = True
    master: int | None = None
    name: str = "offset"

    def problem(self, block: Block) -> Problem:
        mu = self.pair_ridge
        return Problem.of(block if mu is None else solver.ridge_block(block, mu), self.master, self.offset_intercept, mu / 2 if mu and self.split_penalty else 0.0)

    def solution(self, block: Block, trace: bool = False, start: Solution | None = None) -> Solution:
        return solver.solve(self.problem(block), self.lam, self.penalty, self.max_iter, self.tol, self.step, self.accelerate, start, trace)

    def fit(self, block: Block, start: Solution | None = None) -> OffsetModel:
        return self.model(block, self.solution(block, start=start))

    def model(self, block: Block, s: Solution) -> OffsetModel:
        out = OffsetModel(self.name, s.w0, {int(k): w for k, w in zip(s.sources, s.w, strict=True) if np.any(w)}, share=1.0 if self.master is not None else 0.5, info={"steps": s.steps, "objective": s.objective, "converged": s.converged})
        if self.pair_ridge is not None:
            none = np.zeros_like(s.w0)
            for p, (i, j) in enumerate(zip(block.s1.tolist(), block.s2.tolist(), strict=True)):
                wi, wj = out.offsets.get(i, none), out.offsets.get(j, none)
                out.pairs[(i, j)] = s.w0 + wi + solver.pair_deviation(block.gram[p], block.cross[p], s.w0, wi, wj, self.pair_ridge)
        return out


def star_learner(master: int, lam: float, **how) -> SourceOffsetLearner:
    """All sources against one master: w0 + w_i, with no offset for the master."""
    return SourceOffsetLearner(lam, master=master, name="star", **how)


@dataclass
class PooledLearner:
    """One weight vector for all pairs of sources."""

    ridge: float = 0.0
    name: str = "pooled"

    def fit(self, block: Block) -> OffsetModel:
        gram = block.gram.sum(0) + self.ridge * np.eye(block.dims)
        return OffsetModel(self.name, np.linalg.lstsq(gram, block.cross.sum(0), rcond=None)[0])

    def solution(self, block: Block, trace: bool = False, max_iter: int = 5000) -> Solution:
        """The same by iterations, for error against time."""
        return solver.solve(Problem.of(block), 0.0, max_iter=max_iter, freeze_offsets=True, trace=trace)


@dataclass
class PairwiseLearner:
    """An unrelated weight vector for each pair of sources; the shortest one where labels don't decide."""

    ridge: float = 0.0
    name: str = "pairwise"

    def fit(self, block: Block) -> OffsetModel:
        gram = block.gram + self.ridge * np.eye(block.dims)
        w = np.einsum("pab,pb->pa", np.linalg.pinv(gram, rcond=1e-10, hermitian=True), block.cross)
        pairs = {(i, j): v for i, j, v in zip(block.s1.tolist(), block.s2.tolist(), w, strict=True)}
        return OffsetModel(self.name, np.zeros(block.dims), pairs=pairs, pairs_only=True)

    def trajectory(self, block: Block, max_iter: int = 300) -> list[dict]:
        """Iterates of plain gradient steps on each pair, for error against time."""
        import time

        w, began, out = np.zeros_like(block.cross), time.perf_counter(), []
        rate = 1 / np.maximum(np.linalg.eigvalsh(block.gram)[:, -1], 1e-12)[:, None]
        for i in range(max_iter + 1):
            fit = (block.yy - 2 * (w * block.cross).sum(1) + np.einsum("pa,pab,pb->p", w, block.gram, w)).sum() / 2
            out.append({"iter": i, "elapsed_ms": (time.perf_counter() - began) * 1e3, "objective": float(fit), "pairs": w.copy()})
            w = w - rate * (np.einsum("pab,pb->pa", block.gram, w) - block.cross)
        return out


def with_fallback(model: OffsetModel, other: OffsetModel) -> OffsetModel:
    """The model's weights for its own pairs, and the other's for pairs that it can't score."""
    return OffsetModel(f"{model.method}_or_{other.method}", other.w0, other.offsets, other.pairs | model.pairs, other.share, other.pairs_only)


def fit_pairwise_distributed(moments: DataFrame, d: int, scale: float = 1.0, ridge: float = 0.0) -> DataFrame:
    """Pairwise weights without the driver: batched small solves where the moments are."""
    upper = np.triu_indices(d + 1)
    names = [f"g{a}_{b}" for a, b in zip(*upper, strict=True)], [f"c{a}" for a in range(d + 1)]
    unit = np.concatenate([[1.0], np.full(d, 1 / scale)])

    def solved(frames):
        for f in frames:
            gram = np.zeros((len(f), d + 1, d + 1))
            gram[:, upper[0], upper[1]] = f[names[0]].astype(float).to_numpy()
            gram = (gram + np.transpose(np.triu(gram, 1), (0, 2, 1))) * unit[:, None] * unit[None, :] + ridge * np.eye(d + 1)
            w = np.einsum("pab,pb->pa", np.linalg.pinv(gram, rcond=1e-10, hermitian=True), f[names[1]].astype(float).to_numpy() * unit)
            yield f[["s1", "s2"]].assign(w=list(w))

    doubles = [moments[c].cast("double").alias(c) for c in (*names[0], *names[1])]
    return moments.select("s1", "s2", *doubles).mapInPandas(solved, "s1 int, s2 int, w array<double>")


def fit_new_source(model: OffsetModel, block: Block, source: int, lam: float) -> OffsetModel:
    """Add a source to a fitted model: all else stays as it is, and only its offset is learned from its pairs."""
    mine = block.where((block.s1 == source) | (block.s2 == source))
    none = np.zeros_like(model.w0)
    others = np.where(mine.s1 == source, mine.s2, mine.s1)
    known = np.array([model.w0 + model.share * model.offsets.get(int(o), none) for o in others])
    gram, cross = model.share**2 * mine.gram.sum(0), model.share * (mine.cross - np.einsum("pab,pb->pa", mine.gram, known)).sum(0)
    w, rate = none.copy(), 1 / max(np.linalg.eigvalsh(gram)[-1], 1e-12)
    for _ in range(20000):
        new = solver.soft_threshold(w - rate * (gram @ w - cross), rate * lam)
        if np.abs(new - w).max() < 1e-13:
            break
        w = new
    return OffsetModel(model.method, model.w0, model.offsets | {source: w}, model.pairs, model.share, model.pairs_only, model.info)


def symmetric(model: OffsetModel) -> bool:
    """Whether every pair has the same weights in both orders."""
    sources = sorted({*model.offsets, *(s for p in model.pairs for s in p)})
    same = lambda a, b: (a is None and b is None) or np.allclose(a, b)
    return all(same(model.weights(i, j), model.weights(j, i)) for i in sources for j in sources if i < j)
