"""Fits end at optima: other losses, fits on the cluster, the kernel machine, many fits at once; and the budgets of labels."""

import numpy as np
import pytest
from pyspark.sql import functions as F

from offsetlink.operators import learners, losses, moments, resolve, sampling, solver, svm, trials
from offsetlink.workloads import catalogue as c
from tests.conftest import TINY


@pytest.fixture(scope="module")
def pairs(spark):
    df = c.train(spark, TINY).cache()
    yield df
    df.unpersist()


def stacked(frame):
    """Rows of the whole problem: shared features, then those of each source, halved."""
    x = np.column_stack([np.ones(len(frame)), frame[c.XS].to_numpy(float) / c.SCALE])
    d = x.shape[1]
    out = np.zeros((len(frame), 7 * d))
    out[:, :d] = x
    for k in range(len(frame)):
        for s in (frame.s1.iloc[k], frame.s2.iloc[k]):
            out[k, s * d : (s + 1) * d] = x[k] / 2
    return out, frame.y.to_numpy(float), d


def reference(frame, loss, lam, rounds=60000):
    """The least objective, by plain steps with momentum on the stacked rows."""
    x, y, d = stacked(frame)
    value = losses.LOSSES[loss][0]
    rate = 1 / (losses.LOSSES[loss][1] * np.linalg.eigvalsh(x.T @ x)[-1])
    w = v = np.zeros(x.shape[1])
    t, best = 1.0, np.inf
    for _ in range(rounds):
        n = v - rate * (x.T @ value(x @ v, y)[1])
        n[d:] = 0 if np.isinf(lam) else solver.soft_threshold(n[d:], rate * lam)
        t = 1.0 if (v - n) @ (n - w) > 0 else t
        t2 = (1 + np.sqrt(1 + 4 * t * t)) / 2
        step = np.abs(n - v).max()
        w, v, t = n, n + (t - 1) / t2 * (n - w), t2
        if step < 1e-13:
            break
    cost = lambda w: value(x @ w, y)[0].sum() + (0 if np.isinf(lam) else lam * np.abs(w[d:]).sum())
    return min(best, cost(w))


@pytest.mark.parametrize("loss", ["logistic", "squared_hinge", "squared"])
@pytest.mark.parametrize("pooled", [False, True])
def test_other_losses_end_at_the_optimum(pairs, loss, pooled):
    frame = pairs.toPandas()
    m = losses.LossLearner(1.0, loss, pooled=pooled).fit(pairs, c.XS, c.SCALE)
    want = reference(frame, loss, np.inf if pooled else 1.0)
    assert m.info["objective"] == pytest.approx(want, rel=1e-6)
    w = np.array([m.weights(i, j) for i, j in zip(frame.s1, frame.s2, strict=True)])
    x = np.column_stack([np.ones(len(frame)), frame[c.XS].to_numpy(float) / c.SCALE])
    own = losses.LOSSES[loss][0]((x * w).sum(1), frame.y.to_numpy(float))[0].sum() + sum(np.abs(v).sum() for v in m.offsets.values())
    assert own == pytest.approx(m.info["objective"], rel=1e-9)


def test_unfinished_fits_are_refused(pairs):
    with pytest.raises(RuntimeError):
        losses.LossLearner(1.0, "logistic", max_iter=1).fit(pairs, c.XS, c.SCALE)
    m = moments.pair_moments(pairs, c.XS, number="long")
    with pytest.raises(RuntimeError):
        losses.solve_on_cluster(m, c.D, 5.0, c.SCALE, max_iter=2)
    b, _ = c.scaled(c.block_of(pairs)[()])
    assert not solver.solve(solver.Problem.of(b), 1.0, max_iter=2).converged and solver.solve(solver.Problem.of(b), 1.0).converged


@pytest.mark.parametrize("penalty", ["l1", "group"])
def test_cluster_fit_ends_at_the_optimum(pairs, penalty):
    b, t = c.scaled(c.block_of(pairs)[()])
    problem = solver.Problem.of(b)
    m = losses.solve_on_cluster(moments.pair_moments(pairs, c.XS, number="long"), c.D, 5.0, c.SCALE, penalty=penalty)
    back = np.linalg.inv(t.T)
    w0, w = back @ m.w0, np.array([back @ m.offsets.get(int(s), np.zeros(6)) for s in problem.sources])
    best = solver.solve_reference(problem, 5.0).objective if penalty == "l1" else solver.solve(problem, 5.0, penalty, max_iter=50000, tol=1e-12).objective
    assert problem.loss(w0, w) + 5.0 * solver.VALUES[penalty](w) == pytest.approx(best, rel=1e-6)


def test_pairwise_losses_end_at_the_optimum(pairs):
    frame = pairs.toPandas()
    for loss in ("logistic", "squared_hinge"):
        m = losses.fit_pairwise_loss(pairs, c.XS, loss, c.SCALE)
        for (i, j), w in m.pairs.items():
            some = frame[(frame.s1 == i) & (frame.s2 == j)]
            x = np.column_stack([np.ones(len(some)), some[c.XS].to_numpy(float) / c.SCALE])
            g = x.T @ losses.LOSSES[loss][0](x @ w, some.y.to_numpy(float))[1] + 1e-3 * w
            assert np.abs(g).max() < 1e-6


def test_kernel_machine_meets_its_conditions():
    rng = np.random.default_rng(3)
    x = rng.normal(size=(150, 3))
    y = np.where(x[:, 0] * x[:, 1] + 0.3 * rng.normal(size=150) > 0, 1.0, -1.0)
    k = svm.kernel(x, x, 1.0)
    signed = svm.fit_dual(k, y, 2.0, tol=1e-5)
    margin, alpha = y * ((k + 1) @ signed), signed * y
    assert (margin[alpha < 1e-6] > 1 - 1e-2).all() and (margin[alpha > 2 - 1e-6] < 1 + 1e-2).all()
    inside = (alpha > 1e-3) & (alpha < 2 - 1e-3)
    assert np.abs(margin[inside] - 1).max() < 2e-2


def test_cells_fit_what_moments_fit(spark, pairs):
    frame = pairs.toPandas()
    own, block = trials.block_of_rows(frame, c.XS, c.SCALE), c.block_of(pairs)[()]
    for name in ("s1", "s2", "n", "gram", "cross", "yy"):
        assert np.allclose(getattr(own, name), getattr(block, name))
    test = c.train(spark, TINY, c.SIX_TEST)
    cells = pairs.withColumn("half", F.explode(F.array(F.lit(1), F.lit(2)))).where("half = 1 or r < 20")
    got = {(r.half, r.method): r for r in c.evaluate.test_error(trials.run(cells, ["half"], test, c.XS, c.SCALE), by=["half", "method", "n_labels"]).collect()}
    assert got[1, "pooled"].n_labels == 600 and got[2, "pooled"].n_labels == 300 and len(got) == 6
    b, t = c.scaled(block)
    want = c.scoring.score(test, [({"method": "pooled"}, learners.PooledLearner().fit(b).untransformed(t))], c.XS, c.SCALE)
    assert got[1, "pooled"].test_error == pytest.approx(c.evaluate.test_error(want).first().test_error)
    with pytest.raises(Exception, match="too many test pairs"):
        trials.run(cells, ["half"], spark.range(trials.TEST_ROWS + 1).select(F.lit(1).alias("s1"), F.lit(2).alias("s2"), F.col("id").alias("r"), F.lit(1).alias("y"), *(F.lit(0).alias(x) for x in c.XS)), c.XS)


def test_budgets_count_both_sources(pairs):
    rows = sorted(pairs.select("s1", "s2", "r").collect())
    got = {tuple(r) for r in sampling.sample_labels(pairs, F.struct("r", "s1", "s2"), 7, "source").select("s1", "s2", "r").collect()}
    want = set()
    for s in range(1, 7):
        want |= set(sorted((tuple(r) for r in rows if s in (r.s1, r.s2)), key=lambda r: (r[2], r[0], r[1]))[:7])
    assert got == want
    for per, k in (("pair", 2), ("source", 7), ("total", 31)):
        with pytest.raises(ValueError):
            sampling.sample_labels(pairs, F.struct("r", "s1", "s2"), k, per, max_labels=20)
    assert sampling.sample_labels(pairs, F.struct("r", "s1", "s2"), 2, "pair", max_labels=30).count() == 30


def test_fallback_scores_every_pair():
    pairwise = learners.OffsetModel("pairwise", np.zeros(2), pairs={(1, 2): np.array([1.0, 2.0])}, pairs_only=True)
    pooled = learners.OffsetModel("pooled", np.array([3.0, 4.0]))
    both = learners.with_fallback(pairwise, pooled)
    assert both.weights(2, 1).tolist() == [1, 2] and both.weights(1, 3).tolist() == [3, 4] and pairwise.weights(1, 3) is None


def test_clusters_that_need_more_rounds_are_refused(spark):
    path = spark.createDataFrame([(i, i + 1) for i in range(40)], "d1 long, d2 long")
    assert {r.cluster for r in resolve.cluster(path).collect()} == {0}
    with pytest.raises(RuntimeError):
        resolve.cluster(path, rounds=2)
