"""The learner on moments: worked examples, optimality, limits, invariances."""

import numpy as np
import pytest
from hypothesis import given, settings
from hypothesis import strategies as st

from offsetlink.operators import learners, losses, moments, solver, svm, tuning
from offsetlink.operators.moments import Block


def scalar(pairs):
    """A block of scalar moments: {(i, j): (X, g, yy)}."""
    keys = sorted(pairs)
    arr = lambda k: np.array([pairs[p][k] for p in keys], float)
    return Block(np.array([p[0] for p in keys]), np.array([p[1] for p in keys]), np.ones(len(keys), int), arr(0)[:, None, None], arr(1)[:, None], arr(2))


def random_block(sources=6, d=3, n=25, seed=0):
    rng = np.random.default_rng(seed)
    rows = []
    w0, w = rng.normal(size=d), rng.normal(size=(sources, d)) * (rng.random((sources, 1)) < 0.4)
    for i in range(sources):
        for j in range(i + 1, sources):
            x = np.column_stack([np.ones(n), rng.normal(size=(n, d - 1))])
            y = np.sign(x @ (w0 + (w[i] + w[j]) / 2) + 0.3 * rng.normal(size=n))
            rows.append((i, j, n, x.T @ x, x.T @ y, y @ y))
    return Block(*(np.array([r[k] for r in rows]) for k in range(6)))


def test_soft_threshold():
    assert solver.soft_threshold(np.array([3, -0.5, -2]), 1).tolist() == [2, 0, -1]


def test_pair_deviation_example_and_limit():
    one = lambda v: np.array([v])
    args = np.array([[1.0]]), one(1.0), one(0.0)
    vij = solver.pair_deviation(*args, one(0.2), one(0.4), 0.5)[0]
    vji = solver.pair_deviation(*args, one(0.4), one(0.2), 0.5)[0]
    assert (vij, vji) == (pytest.approx(0.45), pytest.approx(0.25)) and 0.2 + vij == pytest.approx(0.4 + vji)
    assert solver.pair_deviation(*args, one(0.2), one(0.4), 1e9)[0] == pytest.approx(0.1, abs=1e-6)


def test_printed_iterations():
    p = solver.Problem.of(scalar({(1, 2): (2, 2, 2)}))
    s = solver.solve(p, 0.9, max_iter=4, tol=-1, step=1 / 3, accelerate=False, trace=True)
    assert [round(r["objective"], 6) for r in s.trace] == [1, 0.15, 0.017778, 0.001975, 0.000219]
    assert [round(float(r["w0"][0]), 6) for r in s.trace] == [0, 0.666667, 0.866667, 0.955556, 0.985185]
    assert p.curvature() / 1.05 == pytest.approx(3) and p.bound() >= 3


def test_three_sources_example():
    b = scalar({(1, 2): (4, 4, 4), (1, 3): (4, 2, 4), (2, 3): (4, 0, 4)})
    p = solver.Problem.of(b)
    assert learners.PooledLearner().fit(b).w0[0] == pytest.approx(0.5)
    assert [learners.PairwiseLearner().fit(b).weights(*k)[0] for k in ((1, 2), (1, 3), (2, 3))] == pytest.approx([1, 0.5, 0])
    free = learners.SourceOffsetLearner(0.0, max_iter=20000, tol=1e-14).fit(b)
    assert [free.weights(*k)[0] for k in ((1, 2), (1, 3), (2, 3))] == pytest.approx([1, 0.5, 0], abs=1e-6)
    assert solver.lambda_max(p) == pytest.approx(1)
    assert not learners.SourceOffsetLearner(1.001).fit(b).offsets and learners.SourceOffsetLearner(0.9).fit(b).offsets


@pytest.mark.parametrize("lam", [0.5, 3.0, 20.0])
def test_optimal_and_as_the_reference(lam):
    for master, penalty_split in ((None, 0.0), (0, 0.0), (None, 0.7)):
        b = random_block()
        if master is not None:
            b = b.where(b.s1 == 0)
        p = solver.Problem.of(b, master, split=penalty_split)
        s, r = solver.solve(p, lam, tol=1e-12, max_iter=20000), solver.solve_reference(p, lam)
        assert s.objective == pytest.approx(r.objective, rel=1e-7)
        assert solver.kkt_residual(p, s, lam) < 1e-7


def test_objective_falls_and_accelerated_is_no_worse():
    p = solver.Problem.of(random_block())
    plain = solver.solve(p, 2.0, max_iter=60, tol=-1, accelerate=False, trace=True)
    values = [r["objective"] for r in plain.trace]
    assert all(a >= b - 1e-9 for a, b in zip(values, values[1:]))
    assert solver.solve(p, 2.0, max_iter=60, tol=-1).objective <= values[-1] + 1e-9


def test_limits_and_special_cases():
    b = random_block()
    pooled, pairwise, working = learners.PooledLearner().fit(b), learners.PairwiseLearner().fit(b), learners.SourceOffsetLearner(2.0, tol=1e-12, max_iter=20000).fit(b)
    each = list(zip(b.s1.tolist(), b.s2.tolist(), strict=True))
    far = lambda u, v: max(np.abs(u.weights(*p) - v.weights(*p)).max() for p in each)
    assert far(learners.SourceOffsetLearner(float("inf"), tol=1e-13, max_iter=20000).fit(b), pooled) < 1e-6
    assert far(learners.SourceOffsetLearner(1.0, pair_ridge=1e-9).fit(b), pairwise) < 1e-5
    assert far(learners.SourceOffsetLearner(2.0, pair_ridge=1e7, tol=1e-12, max_iter=20000).fit(b), working) < 1e-3
    assert far(learners.SourceOffsetLearner(2.0, pair_ridge=1e5, split_penalty=True, tol=1e-14, max_iter=60000).fit(b), pooled) < 2e-2
    assert far(pooled, working) > 0.05
    two = b.where((b.s1 == 0) & (b.s2 == 1))
    assert np.allclose(learners.PooledLearner().fit(two).w0, learners.PairwiseLearner().fit(two).weights(0, 1))


@pytest.mark.parametrize("penalty", ["l1", "l2", "elastic", "group", "none"])
def test_penalties_reach_stationary_points(penalty):
    p = solver.Problem.of(random_block())
    s = solver.solve(p, 2.0, penalty, tol=1e-13, max_iter=20000)
    rate = 1 / p.curvature()
    g0, g = p.gradient(s.w0, s.w)
    assert np.allclose(solver.PENALTIES[penalty](s.w - rate * g, rate * 2.0), s.w, atol=1e-6) and np.abs(g0).max() < 1e-4


@settings(max_examples=10, deadline=None)
@given(st.integers(0, 1000), st.floats(0.5, 4))
def test_scaling_labels_and_penalty_scales_weights(seed, c):
    b = random_block(seed=seed)
    scaled = Block(b.s1, b.s2, b.n, b.gram, b.cross * c, b.yy * c * c)
    fit = lambda x, lam: learners.SourceOffsetLearner(lam, tol=1e-12, max_iter=20000).fit(x)
    assert np.allclose(fit(scaled, 2 * c).w0, c * fit(b, 2.0).w0, atol=1e-5)


def test_standardising_moments_and_back():
    b = random_block()
    t = moments.scaler(b)
    z = b.transformed(t)
    total = z.gram.sum(0) / z.n.sum()
    assert np.allclose(total[0], [1, 0, 0], atol=1e-9) and np.allclose(np.diag(total), 1)
    back = learners.PooledLearner().fit(z).untransformed(t)
    assert np.allclose(back.w0, learners.PooledLearner().fit(b).w0)
    constant = Block(b.s1, b.s2, b.n, np.where(np.eye(3)[2][:, None] + np.eye(3)[2][None] > 0, 0, b.gram), b.cross, b.yy)
    assert moments.scaler(constant)[2, 2] == 1


def test_new_source_equals_joint_restriction():
    b = random_block()
    old = learners.SourceOffsetLearner(1.0).fit(b.where((b.s1 != 5) & (b.s2 != 5)))
    new = learners.fit_new_source(old, b, 5, 0.5)
    assert np.array_equal(new.w0, old.w0) and 5 in new.offsets
    loss = lambda w: solver.Problem.of(b.where(b.s2 == 5))
    del loss
    held = b.where(b.s2 == 5)
    cost = lambda m: tuning.squared_error(m, held) / 2 + 0.5 * np.abs(m.offsets[5]).sum()
    for _ in range(20):
        other = learners.OffsetModel("x", new.w0, new.offsets | {5: new.offsets[5] + np.random.default_rng(_).normal(0, 0.05, 3)})
        assert cost(new) <= cost(other) + 1e-9


def test_fold_moments_and_tuning():
    b = random_block(n=40)
    half = Block(b.s1, b.s2, b.n // 2, b.gram * 0.5, b.cross * 0.5, b.yy * 0.5)
    rest = b.minus(half)
    assert np.allclose(rest.gram, half.gram) and (rest.n == 20).all()
    learner = learners.SourceOffsetLearner(0.0)
    grid = tuning.grid(learner, b)
    assert grid[0] == pytest.approx(solver.lambda_max(learner.problem(b))) and sorted(grid, reverse=True) == grid
    assert tuning.tune(learner, b, {0: half, 1: half}) in grid


def test_losses_have_true_derivatives():
    for f, _ in losses.LOSSES.values():
        m, y = np.linspace(-3, 3, 41), np.where(np.arange(41) % 2, 1.0, -1.0)
        assert np.allclose((f(m + 1e-6, y)[0] - f(m - 1e-6, y)[0]) / 2e-6, f(m, y)[1], atol=1e-4)


def test_svm_separates_what_no_line_does():
    rng = np.random.default_rng(0)
    x = rng.normal(size=(200, 2))
    y = np.where((x * x).sum(1) < 1.2, 1.0, -1.0)
    for how in ({"solver": "dual"}, {"solver": "rff"}):
        assert ((svm.RbfSvm(5.0, 1.0, **how).fit(x, y).score(x) >= 0) == (y > 0)).mean() > 0.93


def test_symmetry_and_sizes():
    b = random_block()
    swapped = Block(b.s2, b.s1, b.n, b.gram, b.cross, b.yy)
    one, two = learners.SourceOffsetLearner(1.0).fit(b), learners.SourceOffsetLearner(1.0).fit(swapped)
    assert learners.symmetric(one) and np.allclose(one.w0, two.w0)
    assert learners.OffsetModel("m", np.array([1.0, 0]), {3: np.array([0, 2.0])}).size() == (4, 2)
    assert np.allclose(one.weights(0, 99), one.w0 + one.offsets.get(0, 0) / 2)
