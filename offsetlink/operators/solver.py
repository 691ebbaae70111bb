"""Proximal gradient on moments, for source offsets: u_p = w0 + c (w_i + w_j), with c a half, or one for stars."""

from __future__ import annotations

import time
from collections.abc import Callable
from dataclasses import dataclass, field

import numpy as np

from offsetlink.operators.moments import Block


def soft_threshold(v: np.ndarray, tau) -> np.ndarray:
    return np.sign(v) * np.maximum(np.abs(v) - tau, 0)


#: Proximal maps of the penalties on all offsets at once (sources x features), by name.
PENALTIES: dict[str, Callable[[np.ndarray, float], np.ndarray]] = {
    "l1": soft_threshold,
    "l2": lambda w, t: w / (1 + t),
    "elastic": lambda w, t: soft_threshold(w, t / 2) / (1 + t / 2),
    "none": lambda w, t: w,
    # One norm for each feature over all sources: sources share which features they change.
    "group": lambda w, t: w * np.maximum(1 - t / np.maximum(np.linalg.norm(w, axis=0), 1e-300), 0),
}
VALUES: dict[str, Callable[[np.ndarray], float]] = {
    "l1": lambda w: float(np.abs(w).sum()),
    "l2": lambda w: float((w * w).sum() / 2),
    "elastic": lambda w: float(np.abs(w).sum() / 2 + (w * w).sum() / 4),
    "none": lambda w: 0.0,
    "group": lambda w: float(np.linalg.norm(w, axis=0).sum()),
}


@dataclass
class Problem:
    """A block with its design: which offsets enter which pair, and with what weight."""

    block: Block
    sources: np.ndarray
    left: np.ndarray
    right: np.ndarray
    share: float = 0.5
    master: int | None = None
    offset_intercept: bool = True
    split: float = 0.0  # weight of half the squared distance between the two offsets of a pair

    @classmethod
    def of(cls, block: Block, master: int | None = None, offset_intercept: bool = True, split: float = 0.0) -> Problem:
        sources = block.sources
        at = {s: i for i, s in enumerate(sources.tolist())}
        ends = [np.array([at[s] for s in e.tolist()], int) for e in (block.s1, block.s2)]
        return cls(block, sources, *ends, 1.0 if master is not None else 0.5, master, offset_intercept, split)

    def pair_weights(self, w0: np.ndarray, w: np.ndarray) -> np.ndarray:
        return w0 + self.share * (w[self.left] + w[self.right])

    def clean(self, w: np.ndarray) -> np.ndarray:
        """Offsets that the design fixes are 0."""
        if self.master is not None:
            w[self.sources == self.master] = 0
        if not self.offset_intercept:
            w[:, 0] = 0
        return w

    def loss(self, w0: np.ndarray, w: np.ndarray) -> float:
        u = self.pair_weights(w0, w)
        b = self.block
        fit = (b.yy - 2 * (u * b.cross).sum(1) + np.einsum("pa,pab,pb->p", u, b.gram, u)).sum() / 2
        gap = w[self.left] - w[self.right]
        return float(fit + self.split / 2 * (gap * gap).sum())

    def gradient(self, w0: np.ndarray, w: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        r = np.einsum("pab,pb->pa", self.block.gram, self.pair_weights(w0, w)) - self.block.cross
        gap = self.split * (w[self.left] - w[self.right])
        return r.sum(0), self.clean(self._by_source(self.left, self.share * r + gap) + self._by_source(self.right, self.share * r - gap))

    def _by_source(self, ends: np.ndarray, rows: np.ndarray) -> np.ndarray:
        """Sums of the rows of each source."""
        return np.stack([np.bincount(ends, c, len(self.sources)) for c in rows.T], 1)

    def curvature(self, rounds: int = 60) -> float:
        """The largest eigenvalue of the Hessian, by power iteration, a little enlarged."""
        rng = np.random.default_rng(7)
        w0, w = rng.normal(size=self.block.dims), self.clean(rng.normal(size=(len(self.sources), self.block.dims)))
        zero = Block(self.block.s1, self.block.s2, self.block.n, self.block.gram, np.zeros_like(self.block.cross), self.block.yy)
        plain = Problem(zero, self.sources, self.left, self.right, self.share, self.master, self.offset_intercept, self.split)
        top = 1.0
        for _ in range(rounds):
            size = np.sqrt((w0 @ w0) + (w * w).sum())
            if size == 0:
                return 1.0
            w0, w = plain.gradient(w0 / size, w / size)
            top = np.sqrt((w0 @ w0) + (w * w).sum())
        return float(top) * 1.05 or 1.0

    def bound(self) -> float:
        """A safe curvature without iterations: (1 + 2 share^2) times the sum of the pairs' own."""
        return float((1 + 2 * self.share**2) * np.linalg.eigvalsh(self.block.gram)[:, -1].sum() + 2 * self.split * len(self.left)) or 1.0


@dataclass
class Solution:
    w0: np.ndarray
    w: np.ndarray
    sources: np.ndarray
    steps: int
    objective: float
    converged: bool = True
    trace: list[dict] = field(default_factory=list)


def solve(problem: Problem, lam: float, penalty: str = "l1", max_iter: int = 5000, tol: float = 1e-9, step: float | str = "exact", accelerate: bool = True, start: Solution | None = None, trace: bool = False, freeze_w0: bool = False, freeze_offsets: bool = False) -> Solution:
    """Minimise the loss and lam times the penalty of the offsets.

    Each step moves against the gradient; the offsets then pass the penalty's proximal map.  With accelerate, momentum is
    added and dropped whenever the objective rises.
    """
    prox, value = PENALTIES[penalty], VALUES[penalty]
    w0 = start.w0.copy() if start else np.zeros(problem.block.dims)
    w = problem.clean(start.w.copy() if start else np.zeros((len(problem.sources), problem.block.dims)))
    if np.isinf(lam):
        freeze_offsets, lam = True, 0.0
    if freeze_offsets:
        w[:] = 0
    search = step == "backtrack"
    rate = 100 / problem.bound() if search else 1 / (problem.curvature() if step == "exact" else problem.bound() if step == "bound" else 1 / float(step))

    def move(v0, v, rate):
        g0, g = problem.gradient(v0, v)
        n0 = v0 if freeze_w0 else v0 - rate * g0
        n = v if freeze_offsets else problem.clean(prox(v - rate * g, rate * lam))
        # Whether the step stays under its quadratic model, which a step of at most 1 / curvature always does.
        if not search:
            return n0, n, True
        d0, d = n0 - v0, n - v
        model = problem.loss(v0, v) + d0 @ g0 + (d * g).sum() + (d0 @ d0 + (d * d).sum()) / (2 * rate)
        return n0, n, problem.loss(n0, n) <= model + 1e-12 * abs(model)

    cost = lambda a, b: problem.loss(a, b) + lam * value(b)
    began, best = time.perf_counter(), cost(w0, w)
    v0, v, t, rows = w0, w, 1.0, []
    note = lambda i, c: rows.append({"iter": i, "elapsed_ms": (time.perf_counter() - began) * 1e3, "objective": c, "w0": w0.copy(), "w": w.copy()})
    if trace:
        note(0, best)
    i = 0
    for i in range(1, max_iter + 1):
        n0, n, fits = move(v0, v, rate)
        while not fits:
            rate /= 2
            n0, n, fits = move(v0, v, rate)
        now = cost(n0, n)
        if accelerate and now > best and t > 1:
            v0, v, t = w0, w, 1.0  # momentum overshot: once more without it
            continue
        moved = max(np.abs(n0 - w0).max(initial=0), np.abs(n - w).max(initial=0))
        if accelerate:
            t2 = (1 + np.sqrt(1 + 4 * t * t)) / 2
            v0, v, t = n0 + (t - 1) / t2 * (n0 - w0), n + (t - 1) / t2 * (n - w), t2
        else:
            v0, v = n0, n
        w0, w, best = n0, n, now
        if trace:
            note(i, now)
        if moved <= tol * (1 + np.abs(w0).max(initial=0)):
            return Solution(w0, w, problem.sources, i, best, True, rows)
    return Solution(w0, w, problem.sources, i, best, False, rows)


def kkt_residual(problem: Problem, s: Solution, lam: float) -> float:
    """How far the l1 problem is from optimal: 0 at an optimum."""
    g0, g = problem.gradient(s.w0, s.w)
    free = np.abs(g + lam * np.sign(s.w))
    held = np.maximum(np.abs(g) - lam, 0)
    out = np.where(s.w != 0, free, held)
    return float(max(np.abs(g0).max(initial=0), problem.clean(out).max(initial=0)) / (1 + np.abs(problem.block.cross).sum()))


def lambda_max(problem: Problem) -> float:
    """The least penalty at which all offsets are 0: the largest offset gradient at the pooled solution."""
    b = problem.block
    pooled = np.linalg.lstsq(b.gram.sum(0), b.cross.sum(0), rcond=None)[0]
    return float(np.abs(problem.gradient(pooled, np.zeros((len(problem.sources), b.dims)))[1]).max())


def solve_reference(problem: Problem, lam: float, rounds: int = 4000) -> Solution:
    """Coordinate descent on the stacked quadratic; slow, for small problems and tests."""
    s, d = len(problem.sources), problem.block.dims
    size = (s + 1) * d
    h, c = np.zeros((size, size)), np.zeros(size)
    for p, (i, j) in enumerate(zip(problem.left, problem.right, strict=True)):
        a = np.zeros((d, size))
        a[:, :d] = np.eye(d)
        for k in (i, j):
            if problem.master is None or problem.sources[k] != problem.master:
                a[:, (k + 1) * d : (k + 2) * d] += problem.share * np.eye(d)
        h += a.T @ problem.block.gram[p] @ a
        c += a.T @ problem.block.cross[p]
        gap = np.zeros((d, size))
        gap[:, (i + 1) * d : (i + 2) * d], gap[:, (j + 1) * d : (j + 2) * d] = np.eye(d), -np.eye(d)
        h += problem.split * gap.T @ gap
    x = np.zeros(size)
    fixed = np.zeros((s + 1, d), bool)
    if not problem.offset_intercept:
        fixed[1:, 0] = True
    for _ in range(rounds):
        before = x.copy()
        for k in range(size):
            if h[k, k] <= 0 or fixed.ravel()[k]:
                continue
            r = c[k] - h[k] @ x + h[k, k] * x[k]
            x[k] = r / h[k, k] if k < d else np.sign(r) * max(abs(r) - lam, 0) / h[k, k]
        if np.abs(x - before).max() < 1e-13:
            break
    w0, w = x[:d], x[d:].reshape(s, d)
    return Solution(w0, w, problem.sources, 0, problem.loss(w0, w) + lam * float(np.abs(w).sum()))


def pair_deviation(gram: np.ndarray, cross: np.ndarray, w0: np.ndarray, wi: np.ndarray, wj: np.ndarray, mu: float) -> np.ndarray:
    """The pair's deviation from w0 + w_i that minimises its loss and both deviations' ridge, by its normal equation."""
    total = np.linalg.solve(gram + 2 * mu * np.eye(len(cross)), cross - gram @ w0 + mu * (wi + wj))
    return total - wi


def ridge_block(block: Block, mu: float) -> Block:
    """Moments of the problem that is left once pair deviations with ridge mu are eliminated."""
    eye = np.eye(block.dims)
    inv = np.linalg.inv(block.gram + 2 * mu * eye)
    gram = 2 * mu * block.gram @ inv
    cross = 2 * mu * np.einsum("pab,pb->pa", inv, block.cross)
    return Block(block.s1, block.s2, block.n, (gram + np.transpose(gram, (0, 2, 1))) / 2, cross, block.yy)
