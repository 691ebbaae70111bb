"""Every query with SQL against DuckDB; the others by what must hold of them."""

import pytest
from pyspark.sql import functions as F

import __spark_entry__ as entry
from tests.conftest import TINY, same, values

MAIN = {k: v for k, v in entry.queries().items() if not k.startswith("op") and k != "pipeline"}
ORACLES = {k: v for k, v in entry.oracle_sql().items() if k in MAIN}


@pytest.mark.parametrize("name", sorted(ORACLES))
def test_query_equals_sql(spark, duck, name):
    df = MAIN[name](spark, TINY)
    want = duck(TINY).sql(ORACLES[name]).df()
    columns = sorted(want.columns)
    assert sorted(df.columns) == columns
    assert same(values(df.collect(), columns), values(want.to_dict("records"), columns))


def test_entry(spark):
    rows = {r.method: r for r in entry.entry(spark).collect()}
    assert set(rows) == {"pooled", "pairwise", "offset"} and rows["offset"].test_error < rows["pooled"].test_error


def by(rows, *keys):
    return {tuple(r[k] for k in keys): r for r in rows}


def test_few_labels_favour_the_offset_learner(spark):
    r = by(MAIN["w3_sample_complexity"](spark, "/root/testdata/sf0.01").collect(), "method", "budget")
    error = lambda m, b: r[m, b]["mean"]
    assert all(v.trials == 5 and v.low <= v["mean"] <= v.high for v in r.values())
    for budget in (5, 10, 20):
        assert error("offset", budget) <= min(error("pooled", budget), error("pairwise", budget)) + 0.003
    assert error("pairwise", 5) > error("pooled", 5) > error("offset", 200)
    assert error("pairwise", 200) < error("pooled", 200)
    assert abs(error("pooled", 20) - error("pooled", 200)) < 0.03


def test_more_sources_hurt_the_pairwise_learner(spark):
    r = by(MAIN["w4_source_complexity"](spark, "/root/testdata/sf0.01").collect(), "method", "size")
    assert {k[1] for k in r} == set(range(2, 31, 2)) and all(v.trials == 50 for v in r.values())
    error = lambda m, s: r[m, s]["mean"]
    for size in range(8, 31, 2):
        assert error("offset", size) < min(error("pooled", size), error("pairwise", size))
    assert error("pairwise", 30) > error("pairwise", 12) > error("pairwise", 4) and error("pooled", 12) > error("pooled", 4)
    assert error("offset", 2) == pytest.approx(error("pooled", 2), abs=0.03)


def test_the_grid_of_budgets(spark):
    from offsetlink.workloads import catalogue as c

    grid = {"pair": (5, 20), "source": (25,), "total": (75,)}
    scored = c.grid_scores(spark, TINY, grid).cache()
    cells = {(r.unit, r.budget, r.trial, r.method): r for r in scored.groupBy("unit", "budget", "trial", "method").agg(F.count("*").alias("rows"), F.count("score").alias("n"), F.max("n_labels").alias("labels")).collect()}
    assert len(cells) == 4 * c.GRID_TRIALS * 4 and len({r.rows for r in cells.values()}) == 1
    for (unit, budget, _, method), r in cells.items():
        assert r.n == r.rows or method == "pairwise" and unit == "total"  # a pair may get no label of a total
        assert r.labels == {"pair": 15 * budget, "total": budget}.get(unit, r.labels) and (unit != "source" or 3 * budget <= r.labels <= 6 * budget)
    assert scored.where("s1 <> 1 or s2 <> 6").count() == 0
    from offsetlink.operators import evaluate

    errors = by(evaluate.test_error(scored.where("unit = 'pair'"), by=["method", "budget"]).collect(), "method", "budget")
    assert errors["pairwise", 20].test_error < errors["pairwise", 5].test_error
    scored.unpersist()


def test_unseen_pairs(spark):
    r = by(MAIN["w10_unseen_pairs"](spark, "/root/testdata/sf0.01").collect(), "method")
    assert r[("pairwise",)].scored == 0 and r[("offset",)].test_error < r[("pooled",)].test_error


def test_null_labels_stay_at_the_base_rate(spark):
    for r in MAIN["w12_null"](spark, TINY).collect():
        assert abs(r.test_error - r.base_rate) < 0.05


def test_runtime_traces(spark):
    r = by(MAIN["w5_runtime_20"](spark, "/root/testdata/sf0.01").collect(), "method", "iter")
    assert r["offset", 200].objective < r["offset", 10].objective and r["offset", 200].test_error < min(v.test_error for k, v in r.items() if k[0] == "pooled")


def test_scoring_shuffles_nothing_and_moments_once(spark):
    from offsetlink.operators import learners, moments, scoring
    from offsetlink.sources.tables import load
    from pyspark.sql import functions as F
    import numpy as np

    pairs = load(spark, TINY, "lineitem").select((F.col("l_orderkey") % 5).cast("int").alias("s1"), (F.col("l_suppkey") % 5 + 5).cast("int").alias("s2"), F.col("l_quantity").alias("x1"), F.lit(1).alias("y"))
    model = learners.OffsetModel("m", np.array([0.1, 0.2]), {1: np.array([0.0, 1.0])})
    plan = scoring.score(pairs, [({"method": "m"}, model)], ["x1"])._jdf.queryExecution().executedPlan().toString()
    assert "Exchange hashpartitioning" not in plan and "BatchEvalPython" not in plan and "l_quantity" in plan and "l_comment" not in plan
    plan = moments.pair_moments(pairs, ["x1"], number="double")._jdf.queryExecution().executedPlan().toString()
    assert plan.count("Exchange hashpartitioning") == 1 and "Python" not in plan


def test_moments_are_additive_and_ignore_partitions(spark):
    from offsetlink.operators import moments
    from offsetlink.workloads import catalogue as c

    df = c.train(spark, TINY).cache()
    key = lambda d: sorted(map(tuple, moments.pair_moments(d, c.XS, number="long").collect()))
    assert key(df) == key(df.repartition(7)) == key(df.selectExpr("s2 AS s1", "s1 AS s2", "y", *c.XS))
    dense = {(r.s1, r.s2, r.k): r.v for r in moments.pair_moments_arrow(df, c.XS).collect()}
    block = c.block_of(df)[()]
    for p, (i, j) in enumerate(zip(block.s1.tolist(), block.s2.tolist(), strict=True)):
        assert dense[(i, j, 1)] == pytest.approx(block.gram[p][0, 1] * c.SCALE)


def test_distributed_fits_agree(spark):
    import numpy as np

    from offsetlink.operators import learners, losses, moments
    from offsetlink.workloads import catalogue as c

    df = c.train(spark, TINY).cache()
    block = c.block_of(df)[()]
    m = moments.pair_moments(df, c.XS, number="long")
    own = learners.PairwiseLearner().fit(block)
    for r in learners.fit_pairwise_distributed(m, c.D, c.SCALE).collect():
        assert np.allclose(r.w, own.weights(r.s1, r.s2), atol=1e-6)
    _, g0, g = losses.gradient(df, c.XS, np.ones(6), np.zeros((6, 6)), list(range(1, 7)), "squared", c.SCALE)
    h0, h = losses.gradient_from_moments(m, c.D, np.ones(6), {}, c.SCALE)
    assert np.allclose(g0, h0) and all(np.allclose(g[s - 1], h[s]) for s in h)


def test_model_round_trip(spark, tmp_path):
    import numpy as np

    from offsetlink.operators.learners import OffsetModel

    m = OffsetModel("offset", np.array([1.0, 2.0]), {4: np.array([0.5, 0.0])}, {(1, 2): np.array([3.0, 4.0])})
    m.save(spark, str(tmp_path / "m"))
    n = OffsetModel.load(spark, str(tmp_path / "m"))
    assert np.array_equal(n.weights(1, 2), m.weights(1, 2)) and np.array_equal(n.weights(4, 9), m.weights(4, 9))


def test_curve_example(spark):
    from offsetlink.operators import evaluate

    rows = list(zip((0.9, 0.7, 0.6, 0.4, 0.1, -0.2, -0.5, -0.8), (1, 1, -1, 1, -1, 1, -1, -1), strict=True))
    df = spark.createDataFrame(rows, "score double, y int")
    curve = {round(r.tau, 1): (r.tp, r.fp, r.fn) for r in evaluate.pr_curve(df).collect()}
    assert curve == {0.9: (1, 0, 3), 0.7: (2, 0, 2), 0.6: (2, 1, 2), 0.4: (3, 1, 1), 0.1: (3, 2, 1), -0.2: (4, 2, 0), -0.5: (4, 3, 0), -0.8: (4, 4, 0)}
    best = evaluate.precision_at_recall(evaluate.pr_curve(df)).first()
    assert (best.tau, round(best.precision, 4)) == (-0.2, 0.6667)
    assert evaluate.test_error(df).first().test_error == 3 / 8
    none = evaluate.precision_recall(df, tau=5.0).first()
    assert none.precision is None and none.recall == 0


def test_synthetic_source(spark):
    from offsetlink.sources.synthetic import SyntheticPairSource

    spark.dataSource.register(SyntheticPairSource)
    df = spark.read.format("synthetic_pairs").option("rows", 1000).option("partitions", 3).load()
    assert df.count() == 1000 and df.where("s1 >= s2 or s2 > 6").count() == 0


def test_streams(spark, tmp_path):
    import uuid

    from offsetlink.streaming import labels
    from pyspark.sql import functions as F

    e = spark.read.parquet(f"{TINY}/events.parquet").withColumn("ts", F.col("ts").cast("timestamp"))
    e.limit(300).write.parquet(str(tmp_path / "in"))
    e.limit(20).write.mode("append").parquet(str(tmp_path / "in"))  # sent twice
    s = labels.stream_moments(labels.label_events(labels.read_stream(spark, str(tmp_path / "in"), 10)), ["x1"], delay="60 days")
    got = labels.run_to_memory(s, f"t{uuid.uuid4().hex}", "update", str(tmp_path / "ck"))
    once = labels.label_events(e.limit(300)).where("s1 <> s2").count()
    assert got.groupBy("s1", "s2").agg(F.max("n").alias("n")).agg(F.sum("n")).first()[0] == once
    assert labels.sessions(labels.label_events(e)).count() > 0 and labels.throughput(labels.label_events(e), "2 days", "1 day").count() > 0


def test_session_functions(spark):
    from offsetlink.plans import relational

    relational.sql_functions(spark)
    r = spark.sql("SELECT soft_threshold(-2.0D, 0.5D) AS s, jaccard(array('a', 'b'), array('b')) AS j").first()
    assert (r.s, r.j) == (-1.5, 0.5)
