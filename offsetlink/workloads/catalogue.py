"""The query catalogue: every method, baseline, measure and workload as a query, with SQL where SQL expresses it."""

from __future__ import annotations

import math
from functools import reduce

import numpy as np
from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from offsetlink.functions import portable as P
from offsetlink.functions import similarity, vectors
from offsetlink.operators import blocking, compare, evaluate, learners, losses, moments, resolve, sampling, scoring, solver, svm, trials, tuning
from offsetlink.plans import relational
from offsetlink.sources import synthetic, tables
from offsetlink.sources.synthetic import Design
from offsetlink.streaming import labels as stream

SIX = Design(sources=6, per_pair=40)
SIX_TEST = Design(sources=6, per_pair=60, role="test")
TEN = Design(sources=10, per_pair=200)
TEN_TEST = Design(sources=10, per_pair=222, role="test")
BUDGETS = (5, 10, 20, 40, 60, 100, 200)
#: Weights for queries that need a fixed model; the constant's first.
FIXED_WEIGHTS = (0.9, -1.2, -0.8, -1.0, -0.6, -0.7)
D = 5
XS = SIX.features
SCALE = float(P.FIXED)

QUERIES: dict = {}
ORACLES: dict[str, str] = {}


def query(sql: str | None = None):
    def add(f):
        QUERIES[f.__name__] = f
        if sql:
            ORACLES[f.__name__] = sql
        return f

    return add


def part(spark, sf_dir):
    return tables.load(spark, sf_dir, "part")


def documents(spark, sf_dir):
    return tables.load(spark, sf_dir, "documents")


def train(spark, sf_dir, d: Design = SIX) -> DataFrame:
    return synthetic.synthetic_pairs(part(spark, sf_dir), d)


def block_of(df: DataFrame, extra=None):
    """Blocks on the driver of integer features, scaled back."""
    return moments.to_driver(moments.pair_moments(df, XS, extra, "long"), D, extra, SCALE)


def scaled(block):
    t = moments.scaler(block)
    return block.transformed(t), t


def fit_offset(block, lam: float | None = None, folds=None, **how) -> learners.OffsetModel:
    b, t = scaled(block)
    learner = learners.SourceOffsetLearner(lam if lam is not None else 0.0, **how)
    if lam is None:
        learner.lam = tuning.tune(learner, b, {k: f.transformed(t) for k, f in folds.items()}) if folds else solver.lambda_max(learner.problem(b)) / 50
    return learner.fit(b).untransformed(t)


def fit_three(block, lam: float | None = None, folds=None) -> list[learners.OffsetModel]:
    b, t = scaled(block)
    return [learners.PooledLearner().fit(b).untransformed(t), learners.PairwiseLearner().fit(b).untransformed(t), fit_offset(block, lam, folds)]


def rounded(df: DataFrame, *columns: str, places: int = 6) -> DataFrame:
    return df.withColumns({c: F.round(c, places) for c in columns})


def kept(df: DataFrame) -> DataFrame:
    """Computed once, in the shared folder."""
    resolve.shared_folder(df.sparkSession)
    return df.checkpoint()


def flagged(spark, rows: list[tuple], ddl: str) -> DataFrame:
    return spark.createDataFrame(rows, ddl)


# -- sources and pre-processing ----------------------------------------------------------------------------------------


@query("SELECT source, count(*) AS records FROM documents GROUP BY source")
def w0_source_sizes(spark, sf_dir):
    return documents(spark, sf_dir).groupBy("source").agg(F.count("*").alias("records"))


@query(f"SELECT m, count(*) AS records FROM (SELECT {tables.six_way_sql('doc_id')} AS m FROM documents) GROUP BY m")
def w0_six_way_sizes(spark, sf_dir):
    return documents(spark, sf_dir).groupBy(tables.six_way(F.col("doc_id")).alias("m")).agg(F.count("*").alias("records"))


@query(r"SELECT regexp_extract(url, '^[a-z]+://(?:www\.)?([^/:?#]+)', 1) AS host, count(*) AS records FROM pages GROUP BY 1")
def w0_page_hosts(spark, sf_dir):
    return tables.page_records(tables.load(spark, sf_dir, "pages")).groupBy("host").agg(F.count("*").alias("records"))


TITLE_SQL = P.ascii_fold_sql(r"regexp_extract(text, '^[^.|\n]*')")
WORDS_SQL = "list_sort(list_distinct(list_filter(string_split_regex({0}, '[^a-z0-9]+'), lambda w: w <> '')))"


@query(f"SELECT doc_id, trim({TITLE_SQL}) AS title FROM documents")
def n1_normalized_titles(spark, sf_dir):
    return tables.document_records(documents(spark, sf_dir)).select("doc_id", F.trim("title").alias("title"))


STOP_SQL = "list_filter({0}, lambda w: NOT list_contains([" + ", ".join(f"'{w}'" for w in blocking.STOP) + "], w))"
TOKENS_SQL = STOP_SQL.format(WORDS_SQL.format(TITLE_SQL))


@query(f"SELECT doc_id, array_to_string({TOKENS_SQL}, ' ') AS tokens FROM documents")
def n2_title_tokens(spark, sf_dir):
    r = tables.document_records(documents(spark, sf_dir))
    return r.select("doc_id", F.array_join(F.array_sort(blocking.tokens(F.col("title"))), " ").alias("tokens"))


def titled(spark, sf_dir) -> DataFrame:
    r = tables.document_records(documents(spark, sf_dir))
    return r.withColumn("title_tokens", blocking.tokens(F.col("title")))


RECORDS_SQL = f"SELECT doc_id, CAST(regexp_extract(source, '([0-9]+)$', 1) AS INTEGER) AS source_id, {TOKENS_SQL} AS ts FROM documents"
HELD_SQL = f"SELECT doc_id, source_id, unnest(ts) AS token FROM ({RECORDS_SQL})"
DF_SQL = f"SELECT token, count(*) AS df FROM ({HELD_SQL}) GROUP BY token"


@query(DF_SQL)
def n3_token_frequency(spark, sf_dir):
    return blocking.token_frequency(titled(spark, sf_dir), "title_tokens")


MAX_DF = 20
BLOCK_SQL = f"SELECT h.token AS block_key, h.doc_id, h.source_id, f.df FROM ({HELD_SQL}) h JOIN ({DF_SQL}) f ON f.token = h.token WHERE f.df BETWEEN 2 AND {MAX_DF}"


def doc_blocks(spark, sf_dir) -> DataFrame:
    return blocking.rare_keys(titled(spark, sf_dir), "title_tokens", MAX_DF)


@query(BLOCK_SQL)
def n4_blocks(spark, sf_dir):
    return doc_blocks(spark, sf_dir).select("block_key", "doc_id", "source_id", "df")


PAIRS_SQL = f"SELECT DISTINCT a.doc_id AS d1, b.doc_id AS d2, a.source_id AS s1, b.source_id AS s2 FROM ({BLOCK_SQL}) a JOIN ({BLOCK_SQL}) b ON a.block_key = b.block_key AND a.doc_id < b.doc_id AND a.source_id <> b.source_id"


@query(PAIRS_SQL)
def n5_candidates(spark, sf_dir):
    return blocking.candidates_by_distinct(doc_blocks(spark, sf_dir))


@query(PAIRS_SQL)
def n6_candidates_minkey(spark, sf_dir):
    return blocking.candidates(doc_blocks(spark, sf_dir))


@query(f"SELECT size, count(*) AS blocks, CAST(sum(size * (size - 1) / 2) AS BIGINT) AS pairs FROM (SELECT block_key, count(*) AS size FROM ({BLOCK_SQL}) GROUP BY 1) GROUP BY size")
def n7_block_sizes(spark, sf_dir):
    return blocking.block_sizes(doc_blocks(spark, sf_dir))


@query(f"WITH b AS ({BLOCK_SQL}), n AS (SELECT block_key, count(*) AS size FROM b GROUP BY 1) SELECT CASE WHEN size > 10 THEN block_key || '|' || (source_id % 4) ELSE block_key END AS block_key, count(*) AS records FROM b JOIN n USING (block_key) GROUP BY 1")
def n7_refined_blocks(spark, sf_dir):
    """Blocks of more than ten records split by a second key."""
    return blocking.refine(doc_blocks(spark, sf_dir), (F.col("source_id") % 4).cast("string"), 10).groupBy("block_key").agg(F.count("*").alias("records"))


@query(PAIRS_SQL)
def n7_salted_candidates(spark, sf_dir):
    return blocking.salted_self_join(doc_blocks(spark, sf_dir), 4)


SIDES_SQL = f"SELECT c.*, trim(u.t) AS t1, trim(v.t) AS t2, u.ws AS w1, v.ws AS w2, u.n AS n1, v.n AS n2 FROM ({PAIRS_SQL}) c JOIN (SELECT doc_id, {TITLE_SQL} AS t, {WORDS_SQL.format(TITLE_SQL)} AS ws, n_chars AS n FROM documents) u ON u.doc_id = c.d1 JOIN (SELECT doc_id, {TITLE_SQL} AS t, {WORDS_SQL.format(TITLE_SQL)} AS ws, n_chars AS n FROM documents) v ON v.doc_id = c.d2"


def sides(spark, sf_dir) -> DataFrame:
    """Candidates with the attributes of both records."""
    r = tables.document_records(documents(spark, sf_dir))
    pick = lambda k, d: r.select(F.col("doc_id").alias(d), F.trim("title").alias(f"t{k}"), F.col("title_tokens").alias(f"w{k}"), F.col("body_tokens").alias(f"b{k}"), F.col("n_chars").alias(f"n{k}"), F.col("n_lines").alias(f"l{k}"), F.col("lang").alias(f"g{k}"))
    return n6_candidates_minkey(spark, sf_dir).join(pick(1, "d1"), "d1").join(pick(2, "d2"), "d2")


@query(f"SELECT d1, d2, CAST(levenshtein(t1, t2) AS INTEGER) AS edits FROM ({SIDES_SQL})")
def n8_edit_distance(spark, sf_dir):
    return sides(spark, sf_dir).select("d1", "d2", similarity.edit_distance(F.col("t1"), F.col("t2")).alias("edits"))


@query(f"SELECT d1, d2, round(coalesce(len(list_intersect(w1, w2)) / nullif(len(list_distinct(list_concat(w1, w2))), 0)::DOUBLE, 0), 6) AS jaccard FROM ({SIDES_SQL})")
def n9_jaccard(spark, sf_dir):
    return rounded(sides(spark, sf_dir).select("d1", "d2", similarity.jaccard(F.col("w1"), F.col("w2")).alias("jaccard")), "jaccard")


@query(f"SELECT d1, d2, abs(n1 - n2) AS diff FROM ({SIDES_SQL})")
def n10_abs_diff(spark, sf_dir):
    return sides(spark, sf_dir).select("d1", "d2", similarity.abs_diff(F.col("n1"), F.col("n2")).alias("diff"))


@query("SELECT p_partkey, round(list_max(list_transform(string_split(p_name, ' '), lambda w: CASE WHEN contains(p_type, w) THEN 1.0 ELSE 1.0 / (1 + levenshtein(w, lower(split_part(p_type, ' ', 1)))) END))::DOUBLE, 6) AS best FROM part")
def n11_best_alternate(spark, sf_dir):
    p = part(spark, sf_dir)
    like = lambda x, y: F.when(F.contains(F.col("p_type"), x), F.lit(1.0)).otherwise(1 / (1 + F.levenshtein(x, y)))
    best = similarity.best_over(F.split("p_name", " "), F.array(F.lower(F.split_part("p_type", F.lit(" "), F.lit(1)))), like)
    return rounded(p.select("p_partkey", best.alias("best")), "best")


# -- synthetic workload ------------------------------------------------------------------------------------------------

LATENT_ROUND = ", ".join(f"round(a{m}, 6) AS a{m}" for m in range(1, D + 1))


@query(f"SELECT entity_id, {LATENT_ROUND} FROM ({synthetic.latent_sql(D)})")
def n19_latent_entities(spark, sf_dir):
    return rounded(synthetic.latent(part(spark, sf_dir), D), *(f"a{m}" for m in range(1, D + 1)))


@query(synthetic.source_records_sql(SIX))
def n19_source_records(spark, sf_dir):
    return synthetic.source_records(synthetic.latent(part(spark, sf_dir), D), SIX)


TRAIN_SQL = synthetic.synthetic_pairs_sql(SIX)


@query(TRAIN_SQL)
def n19_synthetic_pairs(spark, sf_dir):
    return train(spark, sf_dir)


SIGNED = Design(sources=3, per_pair=30, mode="signed")


@query(f"SELECT s1, s2, y, CAST(sum(x1) AS BIGINT) AS x1, count(*) AS n FROM ({synthetic.synthetic_pairs_sql(SIGNED)}) GROUP BY s1, s2, y")
def n12_attr_diff(spark, sf_dir):
    """Signed differences: alike for matches and others, the negative control."""
    return train(spark, sf_dir, SIGNED).groupBy("s1", "s2", "y").agg(F.sum("x1").alias("x1"), F.count("*").alias("n"))


def order():
    return F.struct(P.mix(F.col("r") * 1009 + F.col("s1") * 31 + F.col("s2"), 5), "s1", "s2", "r")


ORDER_SQL = P.mix_sql("(r * 1009 + s1 * 31 + s2)", 5)


def _sample(name: str, per: str, k: int):
    keys = {"pair": "PARTITION BY s1, s2 ", "source": "PARTITION BY source ", "total": ""}[per]
    rows = TRAIN_SQL if per != "source" else f"WITH t AS ({TRAIN_SQL}) SELECT *, s1 AS source FROM t UNION ALL SELECT *, s2 FROM t"
    sql = f"SELECT DISTINCT s1, s2, r, y FROM (SELECT *, row_number() OVER ({keys}ORDER BY {ORDER_SQL}, s1, s2, r) AS rn FROM ({rows})) WHERE rn <= {k}"

    def run(spark, sf_dir):
        return sampling.sample_labels(train(spark, sf_dir), order(), k, per).select("s1", "s2", "r", "y")

    run.__name__ = name
    query(sql)(run)


_sample("n17_sample_per_pair", "pair", 5)
_sample("n17_sample_per_source", "source", 25)
_sample("n17_sample_total", "total", 75)


@query(f"SELECT s1, s2, r, CASE WHEN {P.mix_sql('e1', 3)} % 100 < 30 THEN 'test' ELSE 'train' END AS role FROM ({TRAIN_SQL})")
def n18_split(spark, sf_dir):
    return sampling.split(train(spark, sf_dir), P.mix(F.col("e1"), 3)).select("s1", "s2", "r", "role")


# -- moments and standardising -----------------------------------------------------------------------------------------

MOMENT_COLUMNS = moments.names(D)


def as_long(df: DataFrame, *keys: str) -> DataFrame:
    return df.select(*keys, *(F.col(c).cast("long").alias(c) for c in df.columns if c not in keys))


@query(moments.pair_moments_sql(TRAIN_SQL, D))
def lem_pair_moments(spark, sf_dir):
    return as_long(moments.pair_moments(train(spark, sf_dir), XS), "s1", "s2")


NATION_SQL = """SELECT least(c_nationkey, s_nationkey) AS s1, greatest(c_nationkey, s_nationkey) AS s2, CAST(l_quantity AS BIGINT) AS x1, CAST(round(l_discount * 100) AS BIGINT) AS x2, CAST(round(l_tax * 100) AS BIGINT) AS x3,
  CAST(round(l_extendedprice) AS BIGINT) AS x4, CASE WHEN l_linestatus = 'F' THEN 1 ELSE -1 END AS y
  FROM lineitem JOIN orders ON o_orderkey = l_orderkey JOIN customer ON c_custkey = o_custkey JOIN supplier ON s_suppkey = l_suppkey WHERE c_nationkey <> s_nationkey"""


def nation_pairs(spark, sf_dir) -> DataFrame:
    li, o, c, s = (tables.load(spark, sf_dir, t) for t in ("lineitem", "orders", "customer", "supplier"))
    joined = li.join(o, li.l_orderkey == o.o_orderkey).join(c, o.o_custkey == c.c_custkey).join(s, li.l_suppkey == s.s_suppkey)
    hundredths = lambda x: F.round(F.col(x) * 100).cast("long")
    return joined.select(
        F.col("c_nationkey").alias("s1"), F.col("s_nationkey").alias("s2"), F.col("l_quantity").cast("long").alias("x1"), hundredths("l_discount").alias("x2"), hundredths("l_tax").alias("x3"),
        F.round("l_extendedprice").cast("long").alias("x4"), F.when(F.col("l_linestatus") == "F", 1).otherwise(-1).alias("y"),
    )


@query(moments.pair_moments_sql(NATION_SQL, 4))
def w13_moments_nation(spark, sf_dir):
    """Sums in whole numbers of 64 bits, several times as fast as wider ones; a sum that outgrows them raises an error."""
    return moments.pair_moments(nation_pairs(spark, sf_dir), ["x1", "x2", "x3", "x4"], number="long")


@query(moments.pair_moments_sql(NATION_SQL, 4))
def lem_pair_moments_nation(spark, sf_dir):
    """The same sums in whole numbers of any size."""
    return as_long(moments.pair_moments(nation_pairs(spark, sf_dir), ["x1", "x2", "x3", "x4"]), "s1", "s2")


SCALER_SQL = " UNION ALL ".join(f"SELECT 'x{m}' AS feature, round(avg(x{m} / {SCALE}), 6) AS mean, round(stddev_pop(x{m} / {SCALE}), 6) AS sd FROM t" for m in range(1, D + 1))


@query(f"WITH t AS ({TRAIN_SQL}) {SCALER_SQL}")
def m10_scaler(spark, sf_dir):
    t = moments.scaler(block_of(train(spark, sf_dir))[()])
    return rounded(flagged(spark, [(f"x{m}", float(-t[m, 0] / t[m, m]), float(1 / t[m, m])) for m in range(1, D + 1)], "feature string, mean double, sd double"), "mean", "sd")


@query(f"WITH t AS ({TRAIN_SQL}), s AS (SELECT avg(x1) AS m, stddev_pop(x1) AS d FROM t) SELECT s1, s2, r, round((x1 - m) / d, 6) AS z1 FROM t, s")
def m10_standardized(spark, sf_dir):
    df = train(spark, sf_dir)
    s = df.agg(F.avg("x1").alias("m"), F.stddev_pop("x1").alias("d"))
    return rounded(df.crossJoin(F.broadcast(s)).select("s1", "s2", "r", ((F.col("x1") - F.col("m")) / F.col("d")).alias("z1")), "z1")


# -- the learner -------------------------------------------------------------------------------------------------------


@query(f"SELECT s1, s2, r, round(sign(x1 - 2000) * greatest(abs(x1 - 2000) - 500, 0) / {SCALE}, 6) AS v FROM ({TRAIN_SQL})")
def m3_soft_threshold(spark, sf_dir):
    return rounded(train(spark, sf_dir).select("s1", "s2", "r", (vectors.soft_threshold(F.col("x1") - 2000, 500) / SCALE).alias("v")), "v")


STEP, LAM = 1e-3, 3.0


def _one_feature(spark, sf_dir, steps: int) -> DataFrame:
    """Plain steps on one feature without a constant, where a step is a few sums."""
    b = block_of(train(spark, sf_dir))[()]
    one = moments.Block(b.s1, b.s2, b.n, b.gram[:, 1:2, 1:2], b.cross[:, 1:2], b.yy)
    s = solver.solve(solver.Problem.of(one), LAM, max_iter=steps, tol=-1, step=STEP, accelerate=False)
    rows = [(0, float(s.w0[0]))] + [(int(k), float(w[0])) for k, w in zip(s.sources, s.w, strict=True)]
    return rounded(flagged(spark, rows, "source int, w double"), "w")


def _steps_sql(steps: int) -> str:
    ctes = [
        f"t AS MATERIALIZED ({TRAIN_SQL})",
        f"p AS MATERIALIZED (SELECT s1, s2, sum(x1 * x1) / {SCALE**2} AS xx, sum(x1 * y) / {SCALE} AS xy FROM t GROUP BY s1, s2)",
        "w_0 AS MATERIALIZED (SELECT CAST(range AS INTEGER) AS source, 0.0::DOUBLE AS w FROM range(0, 7))",
    ]
    for k in range(1, steps + 1):
        old = f"w_{k - 1}"
        ctes.append(f"r_{k} AS MATERIALIZED (SELECT p.s1, p.s2, p.xx * (z.w + (a.w + b.w) / 2) - p.xy AS r FROM p JOIN {old} z ON z.source = 0 JOIN {old} a ON a.source = p.s1 JOIN {old} b ON b.source = p.s2)")
        ctes.append(f"g_{k} AS MATERIALIZED (SELECT 0 AS source, sum(r) AS g FROM r_{k} UNION ALL SELECT source, sum(r) / 2 FROM (SELECT s1 AS source, r FROM r_{k} UNION ALL SELECT s2, r FROM r_{k}) GROUP BY source)")
        v = f"(o.w - {STEP} * g.g)"
        ctes.append(f"w_{k} AS MATERIALIZED (SELECT o.source, CASE WHEN o.source = 0 THEN {v} ELSE sign({v}) * greatest(abs({v}) - {STEP * LAM}, 0) END AS w FROM {old} o JOIN g_{k} g USING (source))")
    return f"WITH {', '.join(ctes)} SELECT source, round(w, 6) AS w FROM w_{steps}"


@query(_steps_sql(1))
def m3_one_step(spark, sf_dir):
    return _one_feature(spark, sf_dir, 1)


@query(_steps_sql(3))
def m3_three_steps(spark, sf_dir):
    return _one_feature(spark, sf_dir, 3)


@query()
def m1_fit_weights(spark, sf_dir):
    m = fit_offset(block_of(train(spark, sf_dir))[()])
    return m.to_df(spark).select("method", "kind", "s1", "s2", F.transform("w", lambda v: F.round(v, 6)).alias("w"))


@query()
def m1_objective(spark, sf_dir):
    b, _ = scaled(block_of(train(spark, sf_dir))[()])
    learner = learners.SourceOffsetLearner(5.0)
    s = learner.solution(b)
    return flagged(spark, [(s.steps, round(s.objective, 6), round(solver.solve_reference(learner.problem(b), 5.0).objective, 6))], "steps int, objective double, reference double")


def _fit_sql(steps: int = 3000) -> str:
    """Weights of one feature at the optimum, by many plain steps in SQL: w[1] is shared, w[source + 1] an offset."""
    pull = "list_sum(list_transform(list_filter(p, lambda q: s = 0 OR q.i = s OR q.j = s), lambda q: q.xx * (w[1] + (w[q.i + 1] + w[q.j + 1]) / 2) - q.xy)) * CASE WHEN s = 0 THEN 1.0 ELSE 0.5 END"
    step = f"list_transform(range(0, 7), lambda s: list_transform([w[s + 1] - rate * {pull}], lambda v: CASE WHEN s = 0 THEN v ELSE sign(v) * greatest(abs(v) - rate * {LAM}, 0) END)[1])::DOUBLE[]"
    sums = f"SELECT s1, s2, sum(x1 * x1) / {SCALE**2} AS xx, sum(x1 * y) / {SCALE} AS xy, sum(y * y) AS yy FROM ({TRAIN_SQL}) GROUP BY s1, s2"
    return f"""WITH RECURSIVE m AS MATERIALIZED (SELECT list({{'i': s1, 'j': s2, 'xx': xx, 'xy': xy}} ORDER BY s1, s2) AS p, 1 / (1.5 * sum(xx)) AS rate, sum(yy) AS yy FROM ({sums})),
      it(k, w) AS (SELECT 0, list_transform(range(0, 7), lambda s: 0.0::DOUBLE) UNION ALL SELECT k + 1, {step} FROM it, m WHERE k < {steps}),
      best AS MATERIALIZED (SELECT w FROM it WHERE k = {steps})"""


def _fit_d1(spark, sf_dir, **how) -> tuple[solver.Problem, solver.Solution]:
    b = block_of(train(spark, sf_dir))[()]
    problem = solver.Problem.of(moments.Block(b.s1, b.s2, b.n, b.gram[:, 1:2, 1:2], b.cross[:, 1:2], b.yy))
    return problem, solver.solve(problem, LAM, **({"tol": 1e-11, "max_iter": 20000} | how))


WEIGHTS_SQL = "SELECT source, round(w[source + 1], 5) + 0.0 AS w FROM best, (SELECT CAST(range AS INTEGER) AS source FROM range(0, 7))"


def _weights_d1(s: solver.Solution) -> list[tuple]:
    return [(0, round(float(s.w0[0]), 5) + 0.0), *((int(k), round(float(w[0]), 5) + 0.0) for k, w in zip(s.sources, s.w, strict=True))]


@query(f"{_fit_sql()} {WEIGHTS_SQL}")
def m1_fit_d1(spark, sf_dir):
    """Shared weight and offsets of one feature without a constant, at the optimum."""
    return flagged(spark, _weights_d1(_fit_d1(spark, sf_dir)[1]), "source int, w double")


@query(f"{_fit_sql()} SELECT round(list_sum(list_transform(p, lambda q: q.xx * power(w[1] + (w[q.i + 1] + w[q.j + 1]) / 2, 2) / 2 - q.xy * (w[1] + (w[q.i + 1] + w[q.j + 1]) / 2))) + yy / 2 + {LAM} * list_sum(list_transform(w[2:], lambda v: abs(v))), 4) AS objective FROM best, m")
def m1_objective_d1(spark, sf_dir):
    return flagged(spark, [(round(_fit_d1(spark, sf_dir)[1].objective, 4),)], "objective double")


@query(f"{_fit_sql()}, steps AS (SELECT unnest(['backtrack', 'bound', 'exact']) AS step) SELECT step, f.* FROM steps, ({WEIGHTS_SQL}) f")
def m3_step_sizes(spark, sf_dir):
    """All ways to set steps end at the same weights."""
    rows = [(step, *row) for step in ("backtrack", "bound", "exact") for row in _weights_d1(_fit_d1(spark, sf_dir, step=step)[1])]
    return flagged(spark, rows, "step string, source int, w double")


GRADIENT_SQL = "CASE WHEN source = 0 THEN 1.0 ELSE 0.5 END * list_sum(list_transform(list_filter(p, lambda q: source = 0 OR q.i = source OR q.j = source), lambda q: q.xx * (w[1] + (w[q.i + 1] + w[q.j + 1]) / 2) - q.xy))"


@query(f"{_fit_sql()} SELECT source, round({GRADIENT_SQL}, 4) + 0.0 AS gradient, abs(w[source + 1]) > 1e-9 AS moved, abs({GRADIENT_SQL}) <= CASE WHEN source = 0 THEN 0 ELSE {LAM} END + 1e-6 AS optimal FROM best, m, (SELECT CAST(range AS INTEGER) AS source FROM range(0, 7))")
def m1_kkt_residual(spark, sf_dir):
    """Gradients at the optimum of one feature: 0 for the shared weight, within the penalty for offsets, at it for those not 0."""
    problem, s = _fit_d1(spark, sf_dir)
    g0, g = problem.gradient(s.w0, s.w)
    rows = [(0, float(g0[0]), float(s.w0[0]), 0.0), *((int(k), float(v[0]), float(w[0]), LAM) for k, v, w in zip(s.sources, g, s.w, strict=True))]
    return flagged(spark, [(k, round(v, 4) + 0.0, abs(w) > 1e-9, abs(v) <= most + 1e-6) for k, v, w, most in rows], "source int, gradient double, moved boolean, optimal boolean")


@query(f"SELECT s1, s2, round((xy - xx * 0.1 + 0.5 * 0.4 - (xx + 0.5) * 0.2) / (xx + 1.0), 6) AS deviation FROM (SELECT s1, s2, sum(x1 * x1) / {SCALE**2} AS xx, sum(x1 * y) / {SCALE} AS xy FROM ({TRAIN_SQL}) GROUP BY s1, s2)")
def m2_pair_deviation_d1(spark, sf_dir):
    """Scalar deviations at mu = 0.5, w0 = 0.1, w_i = 0.2, w_j = 0.4, against the closed form written out."""
    b = block_of(train(spark, sf_dir))[()]
    one = lambda v: np.array([v])
    rows = [(int(i), int(j), float(solver.pair_deviation(b.gram[p][1:2, 1:2], b.cross[p][1:2], one(0.1), one(0.2), one(0.4), 0.5)[0])) for p, (i, j) in enumerate(zip(b.s1, b.s2, strict=True))]
    return rounded(flagged(spark, rows, "s1 int, s2 int, deviation double"), "deviation")


def _errors(spark, sf_dir, models: list[learners.OffsetModel], test: Design = SIX_TEST) -> DataFrame:
    scored = scoring.score(train(spark, sf_dir, test), [({"method": m.method}, m) for m in models], XS, SCALE)
    measured = evaluate.test_error(scored, by=["method"]).join(evaluate.precision_recall(scored, by=["method"]), "method")
    return rounded(measured.select("method", "test_error", "n_test", "precision", "recall"), "test_error", "precision", "recall")


def _named(m: learners.OffsetModel, name: str) -> learners.OffsetModel:
    m.method = name
    return m


@query()
def m2_fit_finite_ridge(spark, sf_dir):
    block = block_of(train(spark, sf_dir))[()]
    return _errors(spark, sf_dir, [*fit_three(block), *(_named(fit_offset(block, pair_ridge=mu), f"offset_ridge_{mu:g}") for mu in (0.1, 3.0, 1e6))])


@query()
def m2_literal_program(spark, sf_dir):
    """As the ridge grows the literal program becomes the pooled learner, the working form doesn't."""
    block = block_of(train(spark, sf_dir))[()]
    literal = [_named(fit_offset(block, 1.0, pair_ridge=mu, split_penalty=True), f"literal_{mu:g}") for mu in (3.0, 1e5)]
    return _errors(spark, sf_dir, [*fit_three(block, 1.0), *literal])


FIXED_SQL = " + ".join([repr(FIXED_WEIGHTS[0]), *(f"({w!r} * (x{m} / {SCALE}))" for m, w in enumerate(FIXED_WEIGHTS[1:], 1))])
SCORED_SQL = f"SELECT s1, s2, r, y, round(({FIXED_SQL})::DOUBLE, 6) AS score FROM ({TRAIN_SQL})"


def fixed_scores(spark, sf_dir) -> DataFrame:
    return rounded(scoring.score_fixed(train(spark, sf_dir), list(FIXED_WEIGHTS), XS, SCALE), "score").select("s1", "s2", "r", "y", "score")


@query(SCORED_SQL)
def m4_score_fixed_weights(spark, sf_dir):
    return fixed_scores(spark, sf_dir)


@query(f"SELECT s1, s2, r, CASE WHEN score >= 0 THEN 1 ELSE -1 END AS predicted, round(abs(score), 6) AS confidence FROM ({SCORED_SQL})")
def m4_decide(spark, sf_dir):
    return rounded(scoring.decide(fixed_scores(spark, sf_dir)).select("s1", "s2", "r", "predicted", "confidence"), "confidence")


def _fixed_offsets() -> learners.OffsetModel:
    return learners.OffsetModel("fixed", np.array(FIXED_WEIGHTS), {s: np.array([0.1 * s, 0, 0, 0, 0, 0.0]) for s in (1, 2, 3)})


@query(f"SELECT s1, s2, r, round((({FIXED_SQL}) + 0.5 * ((CASE WHEN s1 <= 3 THEN 0.1 * s1 ELSE 0 END) + (CASE WHEN s2 <= 3 THEN 0.1 * s2 ELSE 0 END)))::DOUBLE, 6) AS score FROM ({TRAIN_SQL})")
def m5_unseen_pair_scores(spark, sf_dir):
    """Pairs without weights of their own, and sources without an offset."""
    return rounded(scoring.score(train(spark, sf_dir), [({"method": "fixed"}, _fixed_offsets())], XS, SCALE).select("s1", "s2", "r", "score"), "score")


def _gradient_sql(slope: str) -> str:
    parts = " UNION ALL ".join(f"SELECT {m} AS feature, round(sum({slope} * {'1.0' if m == 0 else f'(x{m} / {SCALE})'}), 4) AS g FROM t" for m in range(D + 1))
    return f"WITH t AS (SELECT *, ({FIXED_SQL})::DOUBLE AS m FROM ({TRAIN_SQL})) {parts}"


def _gradient(spark, sf_dir, loss: str) -> DataFrame:
    _, g0, _ = losses.gradient(train(spark, sf_dir), XS, np.array(FIXED_WEIGHTS), np.zeros((6, D + 1)), list(range(1, 7)), loss, SCALE)
    return rounded(flagged(spark, [(m, float(v)) for m, v in enumerate(g0)], "feature int, g double"), "g", places=4)


@query(_gradient_sql("(-y / (1 + exp(y * m)))"))
def m6_logistic_gradient(spark, sf_dir):
    return _gradient(spark, sf_dir, "logistic")


@query(_gradient_sql("(-y * greatest(0, 1 - y * m))"))
def m6_hinge_gradient(spark, sf_dir):
    return _gradient(spark, sf_dir, "squared_hinge")


def _newton_sql(slope: str, curve: str, steps: int = 25) -> str:
    """Weights of a constant and one feature at the optimum of a loss, by steps of its quadratic model in SQL."""
    total = lambda e: f"list_sum(list_transform(p, lambda q: {e}))"
    m = "(w[1] + w[2] * q.x)"
    s, c = slope.format(m=m), curve.format(m=m)
    sums = f"[{total(s)}, {total(f'{s} * q.x')}, {total(c)}, {total(f'{c} * q.x')}, {total(f'{c} * q.x * q.x')}]"
    step = f"list_transform([{sums}], lambda h: [w[1] - (h[5] * h[1] - h[4] * h[2]) / (h[3] * h[5] - h[4] * h[4]), w[2] - (h[3] * h[2] - h[4] * h[1]) / (h[3] * h[5] - h[4] * h[4])])[1]::DOUBLE[]"
    return f"WITH RECURSIVE d AS MATERIALIZED (SELECT list({{'x': x1 / {SCALE}, 'y': y}} ORDER BY s1, s2, r) AS p FROM ({TRAIN_SQL})), it(k, w) AS (SELECT 0, [0.0, 0.0]::DOUBLE[] UNION ALL SELECT k + 1, {step} FROM it, d WHERE k < {steps}) SELECT round(w[1], 5) AS intercept, round(w[2], 5) AS slope FROM it WHERE k = {steps}"


def _pooled_loss(spark, sf_dir, loss: str) -> DataFrame:
    df = train(spark, sf_dir).cache()
    m = losses.LossLearner(0.0, loss, pooled=True).fit(df, ["x1"], SCALE)
    df.unpersist()
    return flagged(spark, [(round(float(m.w0[0]), 5), round(float(m.w0[1]), 5))], "intercept double, slope double")


@query(_newton_sql("(-q.y / (1 + exp(q.y * {m})))", "(1 / (2 + exp(q.y * {m}) + exp(-q.y * {m})))"))
def b5_pooled_logistic(spark, sf_dir):
    return _pooled_loss(spark, sf_dir, "logistic")


@query(_newton_sql("(-q.y * greatest(0, 1 - q.y * {m}))", "(CASE WHEN q.y * {m} < 1 THEN 1.0 ELSE 0.0 END)"))
def b5_pooled_hinge(spark, sf_dir):
    return _pooled_loss(spark, sf_dir, "squared_hinge")


@query()
def m6_loss_variants(spark, sf_dir):
    df = train(spark, sf_dir).cache()
    models = [losses.LossLearner(1.0, loss).fit(df, XS, SCALE) for loss in ("logistic", "squared_hinge")]
    df.unpersist()
    return _errors(spark, sf_dir, models)


@query()
def m1b_cluster_solve(spark, sf_dir):
    """The same optimum as on the driver, from iterations over moments that stay on the cluster."""
    m = moments.pair_moments(train(spark, sf_dir), XS, number="long")
    here = fit_offset(moments.to_driver(m, D, None, SCALE)[()], 5.0)
    return _errors(spark, sf_dir, [losses.solve_on_cluster(m, D, 5.0, SCALE), _named(here, "offset_on_driver")])


@query()
def m7_degenerate_ends(spark, sf_dir):
    """An infinite penalty gives the pooled learner; a vanishing ridge the pairwise one."""
    b, _ = scaled(block_of(train(spark, sf_dir))[()])
    pooled, pairwise = learners.PooledLearner().fit(b), learners.PairwiseLearner().fit(b)
    ends = learners.SourceOffsetLearner(float("inf")).fit(b), learners.SourceOffsetLearner(1.0, pair_ridge=1e-9).fit(b)
    far = lambda u, v: round(float(max(np.abs(u.weights(i, j) - v.weights(i, j)).max() for i, j in pairwise.pairs)), 4)
    return flagged(spark, [("infinite penalty, pooled", far(ends[0], pooled)), ("no ridge, pairwise", far(ends[1], pairwise))], "ends string, distance double")


@query(moments.pair_moments_sql(f"SELECT * FROM ({TRAIN_SQL}) WHERE s1 = 1", D))
def m8_star_moments(spark, sf_dir):
    return moments.pair_moments(train(spark, sf_dir).where("s1 = 1"), XS, number="long")


@query()
def m8_star_fit(spark, sf_dir):
    b, t = scaled(block_of(train(spark, sf_dir).where("s1 = 1"))[()])
    m = learners.star_learner(1, 2.0).fit(b).untransformed(t)
    scored = scoring.score(train(spark, sf_dir, SIX_TEST).where("s1 = 1"), [({"method": "star"}, m)], XS, SCALE)
    return rounded(evaluate.test_error(scored, by=["method", "s2"]), "test_error")


@query(moments.pair_moments_sql(f"SELECT *, CAST({P.mix_sql('e1', 9)} % 10 AS INTEGER) AS fold FROM ({TRAIN_SQL})", D, ("fold",)))
def m9_fold_moments(spark, sf_dir):
    return moments.pair_moments(sampling.with_folds(train(spark, sf_dir), P.mix(F.col("e1"), 9), 10), XS, ["fold"], "long")


def _folds(df: DataFrame) -> dict:
    return {k[0]: b for k, b in block_of(sampling.with_folds(df, P.mix(F.col("e1"), 9), 10), ["fold"]).items()}


@query()
def m9_cv_curve(spark, sf_dir):
    df = train(spark, sf_dir)
    b, t = scaled(block_of(df)[()])
    learner = learners.SourceOffsetLearner(0.0)
    rows = tuning.cross_validate(learner, b, {k: f.transformed(t) for k, f in _folds(df).items()}, tuning.grid(learner, b))
    return flagged(spark, [(round(r["lam"], 6), round(float(r["mse"]), 6)) for r in rows], "lam double, mse double")


@query()
def m9a_holdout(spark, sf_dir):
    """The penalty chosen by one held-out fold against that of all ten, and the test errors that they give."""
    df = train(spark, sf_dir)
    b, t = scaled(block_of(df)[()])
    folds = {k: f.transformed(t) for k, f in _folds(df).items()}
    learner, models, lams = learners.SourceOffsetLearner(0.0), [], {}
    for how, holdout in (("holdout", True), ("folds", False)):
        learner.lam = lams[how] = tuning.tune(learner, b, folds, holdout=holdout)
        models.append(_named(learner.fit(b).untransformed(t), how))
    chosen = flagged(spark, [(k, round(v, 6)) for k, v in lams.items()], "method string, lam double")
    return _errors(spark, sf_dir, models).join(F.broadcast(chosen), "method")


@query(f"SELECT s1, s2, r FROM (SELECT *, row_number() OVER (PARTITION BY s1, s2 ORDER BY abs(score), r) AS rn FROM ({SCORED_SQL})) WHERE rn <= 5")
def m12_label_queue(spark, sf_dir):
    scored = fixed_scores(spark, sf_dir).withColumns({"d1": F.col("r"), "d2": F.lit(0)})
    return sampling.select_for_labelling(scored, 5).select("s1", "s2", "r")


@query()
def m13_new_source(spark, sf_dir):
    """The sixth source arrives after the others were fitted."""
    b, t = scaled(block_of(train(spark, sf_dir))[()])
    old = b.where((b.s1 != 6) & (b.s2 != 6))
    before = learners.SourceOffsetLearner(5.0).fit(old)
    after = learners.fit_new_source(before, b, 6, 1.0)
    pairs = train(spark, sf_dir, SIX_TEST).where("s2 = 6")
    scored = scoring.score(pairs, [({"method": "without"}, before.untransformed(t)), ({"method": "with"}, after.untransformed(t))], XS, SCALE)
    return rounded(evaluate.test_error(scored, by=["method"]), "test_error")


@query()
def m14_penalties(spark, sf_dir):
    block = block_of(train(spark, sf_dir))[()]
    return _errors(spark, sf_dir, [_named(fit_offset(block, 5.0, penalty=p), f"offset_{p}") for p in ("l1", "l2", "elastic", "group", "none")])


@query()
def m11_kernel_lift(spark, sf_dir):
    """The offset learner on random cosine features."""
    dim = 40
    lift = lambda d: losses.random_features(train(spark, sf_dir, d), XS, dim, 1.0, SCALE)
    zs = [f"z{k + 1}" for k in range(dim)]
    b = moments.to_driver(moments.pair_moments(lift(SIX), zs, number="double"), dim)[()]
    m = learners.SourceOffsetLearner(2.0, max_iter=500).fit(b)
    return rounded(evaluate.test_error(scoring.score(lift(SIX_TEST), [({"method": "offset_lifted"}, m)], zs), by=["method"]), "test_error")


# -- baselines ---------------------------------------------------------------------------------------------------------


@query(f"SELECT round((sn * sxy - sx * sy) / (sn * sxx - sx * sx), 6) AS slope, round((sxx * sy - sx * sxy) / (sn * sxx - sx * sx), 6) AS intercept FROM (SELECT count(*)::DOUBLE AS sn, sum(x1) / {SCALE} AS sx, sum(y)::DOUBLE AS sy, sum(x1 * x1) / {SCALE**2} AS sxx, sum(x1 * y) / {SCALE} AS sxy FROM ({TRAIN_SQL}))")
def b1_pooled_d2(spark, sf_dir):
    b = block_of(train(spark, sf_dir))[()]
    w = learners.PooledLearner().fit(moments.Block(b.s1, b.s2, b.n, b.gram[:, :2, :2], b.cross[:, :2], b.yy)).w0
    return rounded(flagged(spark, [(float(w[1]), float(w[0]))], "slope double, intercept double"), "slope", "intercept")


@query()
def b1_pooled(spark, sf_dir):
    return _errors(spark, sf_dir, fit_three(block_of(train(spark, sf_dir))[()])[:1])


@query(f"SELECT s1, s2, round((sn * sxy - sx * sy) / (sn * sxx - sx * sx), 6) AS slope, round((sxx * sy - sx * sxy) / (sn * sxx - sx * sx), 6) AS intercept FROM (SELECT s1, s2, count(*)::DOUBLE AS sn, sum(x1) / {SCALE} AS sx, sum(y)::DOUBLE AS sy, sum(x1 * x1) / {SCALE**2} AS sxx, sum(x1 * y) / {SCALE} AS sxy FROM ({TRAIN_SQL}) GROUP BY s1, s2)")
def b2_pairwise_d2(spark, sf_dir):
    w = learners.fit_pairwise_distributed(moments.pair_moments(train(spark, sf_dir), ["x1"], number="long"), 1, SCALE)
    return rounded(w.select("s1", "s2", F.col("w")[1].alias("slope"), F.col("w")[0].alias("intercept")), "slope", "intercept")


@query()
def b2_pairwise(spark, sf_dir):
    return _errors(spark, sf_dir, fit_three(block_of(train(spark, sf_dir))[()])[1:2])


@query()
def b2a_fallback(spark, sf_dir):
    """Pairwise scorers where a pair has labels, the pooled one elsewhere; errors on all pairs, three tenths unlabelled."""
    hidden = P.mix(F.col("s1") * 100 + F.col("s2"), 1) % 10 < 3
    pooled, pairwise, _ = fit_three(block_of(train(spark, sf_dir).where(~hidden))[()])
    return _errors(spark, sf_dir, [pooled, pairwise, learners.with_fallback(pairwise, pooled)])


@query(f"SELECT s1, s2, r, array_to_string(list_transform(range(1, 7), lambda k: CASE WHEN k = s1 OR k = s2 THEN '1' ELSE '0' END), '') AS code FROM ({TRAIN_SQL})")
def b3_source_encoding(spark, sf_dir):
    code = F.array_join(F.transform(svm.encode_sources(F.col("s1"), F.col("s2"), 6), lambda v: v.cast("int").cast("string")), "")
    return train(spark, sf_dir).select("s1", "s2", "r", code.alias("code"))


@query(f"WITH t AS MATERIALIZED (SELECT s1, s2, r, x1 / {SCALE} AS x, x2 / {SCALE} AS z FROM ({TRAIN_SQL})) SELECT s1, s2, a.r AS i, b.r AS j, round(exp(-(pow(a.x - b.x, 2) + pow(a.z - b.z, 2)) / 0.5), 6) AS k FROM t a JOIN t b USING (s1, s2)")
def b3_kernel_matrix(spark, sf_dir):
    """The kernel of two features among the labelled pairs of each source pair."""

    def cells(key, f):
        f = f.sort_values("r")
        k = svm.kernel(*[f[["x1", "x2"]].to_numpy(float) / SCALE] * 2, 0.5)
        i, j = np.meshgrid(f.r, f.r, indexing="ij")
        return type(f)({"s1": key[0], "s2": key[1], "i": i.ravel(), "j": j.ravel(), "k": k.ravel().round(6)})

    return train(spark, sf_dir).select("s1", "s2", "r", "x1", "x2").groupBy("s1", "s2").applyInPandas(cells, "s1 int, s2 int, i int, j int, k double")


def _svm(df: DataFrame, sources: int, **how) -> svm.RbfSvm:
    f = df.limit(svm.DUAL_ROWS + 1).toPandas().sort_values(["s1", "s2", "r"])
    if len(f) > svm.DUAL_ROWS:
        raise ValueError("too many labels for one machine's memory")
    return svm.RbfSvm(**how).fit(svm.inputs(f, XS, sources, SCALE), f.y.to_numpy(float))


@query()
def b3_svm_predictions(spark, sf_dir):
    df = train(spark, sf_dir)
    out = []
    for how in ({"c": 1.0, "sigma": 2.0}, {"c": 1.0, "sigma": 2.0, "solver": "rff"}):
        scored = svm.predict(train(spark, sf_dir, SIX_TEST), _svm(df, 6, **how), XS, 6, SCALE)
        out.append(evaluate.test_error(scored).select(F.lit(how.get("solver", "dual")).alias("solver"), "test_error", "n_test"))
    return rounded(out[0].unionByName(out[1]), "test_error", places=4)


@query()
def b3_svm_grid(spark, sf_dir):
    """Grid search with ten folds, one task for each cell and fold."""
    small = Design(sources=4, per_pair=20)
    df = sampling.with_folds(train(spark, sf_dir, small), P.mix(F.col("e1"), 9), 10)
    return rounded(svm.tune(df, XS, 4, [0.3, 1.0], [1.0, 2.0], 10, SCALE), "error")


# -- measures ----------------------------------------------------------------------------------------------------------

CONFUSION_SQL = f"SELECT CAST(count(*) FILTER (WHERE score >= 0 AND y > 0) AS BIGINT) AS tp, CAST(count(*) FILTER (WHERE score >= 0 AND y < 0) AS BIGINT) AS fp, CAST(count(*) FILTER (WHERE score < 0 AND y > 0) AS BIGINT) AS fn, CAST(count(*) FILTER (WHERE score < 0 AND y < 0) AS BIGINT) AS tn FROM ({SCORED_SQL})"


@query(CONFUSION_SQL)
def r1_confusion(spark, sf_dir):
    return evaluate.confusion(fixed_scores(spark, sf_dir))


@query(f"SELECT round(tp / (tp + fp), 6) AS precision, round(tp / (tp + fn), 6) AS recall FROM ({CONFUSION_SQL})")
def r2_precision_recall(spark, sf_dir):
    return rounded(evaluate.precision_recall(fixed_scores(spark, sf_dir)).select("precision", "recall"), "precision", "recall")


@query(f"SELECT round(avg(CASE WHEN (score >= 0) <> (y > 0) THEN 1.0 ELSE 0.0 END), 6) AS test_error, count(*) AS n_test FROM ({SCORED_SQL})")
def r4_test_error(spark, sf_dir):
    return rounded(evaluate.test_error(fixed_scores(spark, sf_dir)), "test_error")


@query(f"SELECT round(avg(e), 6) AS macro_error, count(*) AS n_pairs FROM (SELECT s1, s2, avg(CASE WHEN (score >= 0) <> (y > 0) THEN 1.0 ELSE 0.0 END) AS e FROM ({SCORED_SQL}) GROUP BY s1, s2)")
def r4_macro_error(spark, sf_dir):
    return rounded(evaluate.macro_error(fixed_scores(spark, sf_dir)), "macro_error")


def _curve_sql(tau: str) -> str:
    counts = f"SELECT {tau} AS tau, sum(CASE WHEN y > 0 THEN 1 ELSE 0 END) AS pos, sum(CASE WHEN y < 0 THEN 1 ELSE 0 END) AS neg FROM ({SCORED_SQL}) GROUP BY 1"
    run = "OVER (ORDER BY tau DESC ROWS UNBOUNDED PRECEDING)"
    return f"SELECT round(tau, 6) AS tau, CAST(tp AS BIGINT) AS tp, CAST(fp AS BIGINT) AS fp, CAST(total - tp AS BIGINT) AS fn, round(tp / (tp + fp), 6) AS precision, round(tp / total, 6) AS recall FROM (SELECT tau, sum(pos) {run} AS tp, sum(neg) {run} AS fp, sum(pos) OVER () AS total FROM ({counts}))"


@query(_curve_sql("score"))
def r5_pr_curve_exact(spark, sf_dir):
    return rounded(evaluate.pr_curve(fixed_scores(spark, sf_dir)), "tau", "precision", "recall")


@query(_curve_sql("(-2.0 + greatest(0, least(63, floor((score + 2.0) / 0.0625))) * 0.0625)::DOUBLE"))
def r5_pr_curve_binned(spark, sf_dir):
    return rounded(evaluate.pr_curve(fixed_scores(spark, sf_dir), bins=64), "tau", "precision", "recall")


@query(f"SELECT max(tau) AS tau, max_by(precision, tau) AS precision, max_by(recall, tau) AS recall FROM ({_curve_sql('score')}) WHERE recall >= 0.85")
def r6_precision_at_recall(spark, sf_dir):
    return rounded(evaluate.precision_at_recall(evaluate.pr_curve(fixed_scores(spark, sf_dir))), "tau", "precision", "recall")


TRIALS = Design(sources=4, per_pair=20, trials=10)
TRIAL_ERRORS_SQL = f"SELECT trial, avg(CASE WHEN (({FIXED_SQL})::DOUBLE >= 0) <> (y > 0) THEN 1.0 ELSE 0.0 END) AS e FROM ({synthetic.synthetic_pairs_sql(TRIALS)}) GROUP BY trial"


def trial_errors(spark, sf_dir) -> DataFrame:
    scored = scoring.score_fixed(train(spark, sf_dir, TRIALS), list(FIXED_WEIGHTS), XS, SCALE)
    return evaluate.test_error(scored, by=["trial"]).withColumn("method", F.lit("fixed"))


@query(f"SELECT 'fixed' AS method, count(*) AS trials, round(avg(e), 6) AS mean, round(avg(e) - 2.262 * stddev_samp(e) / sqrt(count(*)), 6) AS low, round(avg(e) + 2.262 * stddev_samp(e) / sqrt(count(*)), 6) AS high, round(2 * 2.262 * stddev_samp(e) / sqrt(count(*)), 6) AS width FROM ({TRIAL_ERRORS_SQL})")
def r7_band_t(spark, sf_dir):
    return rounded(evaluate.band(trial_errors(spark, sf_dir), "test_error", ["method"]), "mean", "low", "high", "width")


@query(f"SELECT 'fixed' AS method, count(*) AS trials, round(avg(e), 6) AS mean, round(quantile_cont(e, 0.025), 6) AS low, round(quantile_cont(e, 0.975), 6) AS high, round(quantile_cont(e, 0.975) - quantile_cont(e, 0.025), 6) AS width FROM ({TRIAL_ERRORS_SQL})")
def r7_band_percentile(spark, sf_dir):
    return rounded(evaluate.band(trial_errors(spark, sf_dir), "test_error", ["method"], "percentile"), "mean", "low", "high", "width")


@query(f"WITH t AS ({TRAIN_SQL}) SELECT 'pair' AS level, s1, s2, count(*) AS labels FROM t GROUP BY s1, s2 UNION ALL SELECT 'source', source, NULL, count(*) FROM (SELECT s1 AS source FROM t UNION ALL SELECT s2 FROM t) GROUP BY source UNION ALL SELECT 'total', NULL, NULL, count(*) FROM t")
def r8_label_ledger(spark, sf_dir):
    return evaluate.label_ledger(train(spark, sf_dir))


@query(f"SELECT level, s1, s2, CAST(count(*) AS BIGINT) AS labels FROM (SELECT CASE WHEN grouping(s1) = 0 AND grouping(s2) = 0 THEN 'pair' WHEN grouping(s1) = 0 THEN 'first' ELSE 'total' END AS level, s1, s2, count(*) AS c FROM ({TRAIN_SQL}) GROUP BY GROUPING SETS ((s1, s2), (s1), ())) GROUP BY ALL")
def r8_grouping_sets(spark, sf_dir):
    train(spark, sf_dir).createOrReplaceTempView("offsetlink_train")
    sets = spark.sql("SELECT CASE WHEN grouping(s1) = 0 AND grouping(s2) = 0 THEN 'pair' WHEN grouping(s1) = 0 THEN 'first' ELSE 'total' END AS level, s1, s2 FROM offsetlink_train GROUP BY GROUPING SETS ((s1, s2), (s1), ())")
    return sets.groupBy("level", "s1", "s2").agg(F.count("*").alias("labels"))


@query(f"{_fit_sql()} SELECT 'offset' AS method, CAST(1 + len(list_filter(w[2:], lambda v: abs(v) > 1e-9)) AS INTEGER) AS parameters, CAST(len(list_filter(w, lambda v: abs(v) > 1e-9)) AS INTEGER) AS nonzero FROM best")
def r12_model_size(spark, sf_dir):
    """Numbers that a fitted model of one feature keeps: the shared weight and those offsets that aren't 0."""
    _, s = _fit_d1(spark, sf_dir)
    m = learners.OffsetModel("offset", s.w0, {int(k): w for k, w in zip(s.sources, s.w, strict=True) if np.any(np.abs(w) > 1e-9)})
    return flagged(spark, [(m.method, *m.size())], "method string, parameters int, nonzero int")


# -- documents end to end ----------------------------------------------------------------------------------------------

GRAMS_SQL = "SELECT doc_id, unnest(list_distinct(list_transform(range(1, greatest(len(ws) - 1, 1)), lambda i: array_to_string(ws[i:i + 2], ' ')))) AS g FROM (SELECT doc_id, list_filter(string_split_regex(" + P.ascii_fold_sql("text") + ", '[^a-z0-9]+'), lambda w: w <> '') AS ws FROM documents)"


def near_classes(spark, sf_dir) -> tuple[DataFrame, DataFrame]:
    """Documents by equal sets of word triples (doc_id, class: the least of them), and pairs of classes (c1 < c2) whose
    triples have Jaccard >= 1/2: the truth, kept apart from the features.

    Such sets share one of their rarest n - ceil(n / 2) + 1 triples, so only those propose pairs; the proposed pairs are
    then counted over all triples.  Triples of one set only come first in that order and propose nothing, so they go
    before sets are ranked.
    """
    words = F.filter(F.split(P.ascii_fold(F.col("text")), "[^a-z0-9]+"), lambda w: w != "")
    docs = documents(spark, sf_dir).select("doc_id", words.alias("ws"))
    # The lambda sees its own argument only: a filter that moves below would else compute the words for each element.
    shifted = F.arrays_zip(F.col("ws").alias("a"), F.slice("ws", 2, F.greatest(F.size("ws"), F.lit(1))).alias("b"), F.slice("ws", 3, F.greatest(F.size("ws"), F.lit(1))).alias("c"))
    triples = F.filter(shifted, lambda z: z["c"].isNotNull())
    grams = F.array_sort(F.array_distinct(F.transform(triples, lambda z: F.xxhash64(z["a"], z["b"], z["c"]))))
    sized = docs.select("doc_id", grams.alias("grams")).where(F.size("grams") > 0).withColumn("fp", F.xxhash64("grams"))
    sets = sized.groupBy("fp").agg(F.min("doc_id").alias("class"), F.first("grams").alias("grams")).withColumn("n", F.size("grams"))
    held = sets.select("class", "n", F.explode("grams").alias("g"))
    shared = held.groupBy("g").agg(F.count("*").alias("df")).where("df > 1")
    ranked = held.join(shared, "g").groupBy("class", "n").agg(F.array_sort(F.collect_list(F.struct("df", "g"))).alias("gs"))
    first = ranked.select("class", "n", F.explode(F.slice("gs", F.lit(1), F.greatest(F.floor(F.col("n") / 2).cast("int") + 1 - (F.col("n") - F.size("gs")), F.lit(0)))).alias("x")).select("class", "n", "x.g")
    a, b = first.select(F.col("class").alias("c1"), F.col("n").alias("n1"), "g"), first.select(F.col("class").alias("c2"), F.col("n").alias("n2"), "g")
    pairs = a.join(b, "g").where("c1 < c2 and 2 * n1 >= n2 and 2 * n2 >= n1").select("c1", "c2", "n1", "n2").distinct()
    left, right = sets.select(F.col("class").alias("c1"), F.col("grams").alias("g1")), sets.select(F.col("class").alias("c2"), F.col("grams").alias("g2"))
    common = F.size(F.array_intersect("g1", "g2"))
    links = pairs.join(left, "c1").join(right, "c2").where(2 * common >= F.col("n1") + F.col("n2") - common).select("c1", "c2")
    return sized.select("doc_id", "fp").join(sets.select("fp", "class"), "fp").select("doc_id", "class"), links


def near_copies(spark, sf_dir) -> DataFrame:
    """d1, d2 of all near copies, classes expanded."""
    members, links = near_classes(spark, sf_dir)
    one, two = members.select(F.col("doc_id").alias("x"), F.col("class").alias("c1")), members.select(F.col("doc_id").alias("y"), F.col("class").alias("c2"))
    equal = one.join(two, F.col("c1") == F.col("c2")).where("x < y").select("x", "y")
    every = equal.unionByName(links.join(one, "c1").join(two, "c2").select("x", "y"))
    return every.select(F.least("x", "y").alias("d1"), F.greatest("x", "y").alias("d2"))


TRUTH_SQL = f"WITH g AS MATERIALIZED ({GRAMS_SQL}), n AS MATERIALIZED (SELECT doc_id, count(*) AS n FROM g GROUP BY doc_id) SELECT c.d1, c.d2 FROM (SELECT a.doc_id AS d1, b.doc_id AS d2, count(*) AS common FROM g a JOIN g b ON a.g = b.g AND a.doc_id < b.doc_id GROUP BY 1, 2) c JOIN n x ON x.doc_id = c.d1 JOIN n y ON y.doc_id = c.d2 WHERE 2 * c.common >= x.n + y.n - c.common"


@query(TRUTH_SQL)
def w8_truth(spark, sf_dir):
    return near_copies(spark, sf_dir)


def doc_pairs(spark, sf_dir) -> DataFrame:
    """Candidates with five features and the label."""
    keys = blocking.record_keys(titled(spark, sf_dir), "title_tokens", MAX_DF)
    pairs = compare.compared(documents(spark, sf_dir), keys)
    return pairs.select("d1", "d2", "s1", "s2", *XS, F.when(F.col("match"), 1).otherwise(-1).alias("y"))


BODY_SQL = "list_distinct(list_filter(string_split_regex(" + P.ascii_fold_sql("text") + ", '[^a-z0-9]+'), lambda w: w <> ''))"
FEATURES_SQL = f"""WITH t AS MATERIALIZED ({TRUTH_SQL}), b AS MATERIALIZED (SELECT doc_id, {BODY_SQL} AS ws, len(string_split(text, chr(10))) AS l, lang FROM documents)
  SELECT s.d1, s.d2, s.s1, s.s2, round(coalesce(len(list_intersect(w1, w2)) / nullif(len(list_distinct(list_concat(w1, w2))), 0)::DOUBLE, 0), 6) AS x1,
    round(coalesce(len(list_intersect(u.ws, v.ws)) / nullif(len(list_distinct(list_concat(u.ws, v.ws))), 0)::DOUBLE, 0), 6) AS x2, round(abs(n1 - n2) / greatest(n1, n2, 1)::DOUBLE, 6) AS x3, round(abs(u.l - v.l) / greatest(u.l, v.l, 1)::DOUBLE, 6) AS x4,
    CASE WHEN u.lang = v.lang THEN 1.0 ELSE 0.0 END::DOUBLE AS x5, CASE WHEN t.d1 IS NULL THEN -1 ELSE 1 END AS y
  FROM ({SIDES_SQL}) s JOIN b u ON u.doc_id = s.d1 JOIN b v ON v.doc_id = s.d2 LEFT JOIN t ON t.d1 = s.d1 AND t.d2 = s.d2"""


@query(FEATURES_SQL)
def w8_features(spark, sf_dir):
    return rounded(doc_pairs(spark, sf_dir), *XS)


ACROSS_SQL = f"SELECT t.d1, t.d2 FROM ({TRUTH_SQL}) t JOIN documents a ON a.doc_id = t.d1 JOIN documents b ON b.doc_id = t.d2 WHERE a.source <> b.source"


@query(f"WITH t AS MATERIALIZED ({ACROSS_SQL}), c AS MATERIALIZED ({PAIRS_SQL}), n AS (SELECT (sum(k) * sum(k) - sum(k * k)) / 2 AS every FROM (SELECT count(*) AS k FROM documents GROUP BY source)), q AS (SELECT (SELECT count(*) FROM t) AS true_pairs, (SELECT count(*) FROM t JOIN c USING (d1, d2)) AS kept_pairs, (SELECT count(*) FROM c) AS candidates) SELECT *, round(kept_pairs / nullif(true_pairs, 0)::DOUBLE, 6) AS completeness, round(1 - candidates / (SELECT every FROM n)::DOUBLE, 6) AS reduction FROM q")
def r13_blocking_quality(spark, sf_dir):
    """Pairs of different sources: how many true ones blocking keeps, and how many of all it leaves out."""
    docs = documents(spark, sf_dir).select("doc_id", "source")
    sizes = docs.groupBy("source").count().agg(F.sum("count").alias("n"), F.sum(F.col("count") * F.col("count")).alias("nn")).first()
    side = lambda k: docs.select(F.col("doc_id").alias(f"d{k}"), F.col("source").alias(f"source{k}"))
    truth = near_copies(spark, sf_dir).join(side(1), "d1").join(side(2), "d2").where("source1 <> source2")
    return rounded(evaluate.blocking_quality(n6_candidates_minkey(spark, sf_dir), truth, (sizes.n * sizes.n - sizes.nn) // 2), "completeness", "reduction")


def doc_model(pairs: DataFrame) -> learners.OffsetModel:
    b = moments.to_driver(moments.pair_moments(pairs, XS, number="double"), D)[()]
    z, t = scaled(b)
    learner = learners.SourceOffsetLearner(0.0)
    learner.lam = solver.lambda_max(learner.problem(z)) / 20
    return learner.fit(z).untransformed(t)


@query()
def w8_resolution(spark, sf_dir):
    """Learn on half of the candidates, resolve the others, cluster, and merge."""
    pairs = resolve.stored(doc_pairs(spark, sf_dir), "pairs")
    half = P.mix(F.col("d1") * 7919 + F.col("d2"), 3) % 2
    scored = scoring.score(pairs, [({"method": "offset"}, doc_model(pairs.where(half == 0)))], XS)
    clusters = resolve.cluster(kept(resolve.resolve(scored)))
    return resolve.merge_records(tables.document_records(documents(spark, sf_dir)), clusters)


@query()
def w11_homogeneous(spark, sf_dir):
    """Twenty sources that are alike: the offsets should add nothing to the pooled learner."""
    pairs = resolve.stored(doc_pairs(spark, sf_dir), "pairs")
    half = P.mix(F.col("d1") * 7919 + F.col("d2"), 3) % 2
    b, t = scaled(moments.to_driver(moments.pair_moments(pairs.where(half == 0), XS, number="double"), D)[()])
    models = [learners.PooledLearner().fit(b).untransformed(t), doc_model(pairs.where(half == 0))]
    scored = scoring.score(pairs.where(half == 1), [({"method": m.method}, m) for m in models], XS)
    return rounded(evaluate.precision_recall(scored, by=["method"]), "precision", "recall")


MATCH_SQL = f"SELECT d1, d2 FROM ({SIDES_SQL}) WHERE len(list_intersect(w1, w2)) >= 0.5 * nullif(len(list_distinct(list_concat(w1, w2))), 0)"


def title_matches(spark, sf_dir) -> DataFrame:
    j = similarity.jaccard(F.col("w1"), F.col("w2"))
    return sides(spark, sf_dir).select("d1", "d2", "s1", "s2", j.alias("score")).where(F.col("score") >= 0.5)


STOPS = "[" + ", ".join(f"'{w}'" for w in blocking.STOP) + "]"
TITLED_SQL = f"SELECT doc_id, TRY_CAST(nullif(regexp_extract(source, '([0-9]+)$', 1), '') AS INTEGER) AS source_id, {TITLE_SQL} AS title, {WORDS_SQL.format(TITLE_SQL)} AS ws, lang FROM documents"
ALIKE_SQL = f"2 * len(list_intersect(a.ws, b.ws)) >= len(list_distinct(list_concat(a.ws, b.ws))) AND len(list_filter(list_intersect(a.ws, b.ws), lambda w: NOT list_contains({STOPS}, w))) > 0"
CLUSTERS_SQL = f"""WITH RECURSIVE h AS MATERIALIZED ({TITLED_SQL}), e AS MATERIALIZED (SELECT a.doc_id AS a, b.doc_id AS b FROM h a JOIN h b ON a.source_id <> b.source_id AND a.doc_id <> b.doc_id WHERE {ALIKE_SQL}),
  r(a, b) AS (SELECT DISTINCT a, a FROM e UNION SELECT r.a, e.b FROM r JOIN e ON e.a = r.b)"""


@query(f"{CLUSTERS_SQL} SELECT a AS record, min(b) AS cluster FROM r GROUP BY a")
def n15_components(spark, sf_dir):
    """Clusters of records of different sources with alike titles, words of any frequency and all copies included."""
    return resolve.cluster_by_words(tables.document_records(documents(spark, sf_dir)), "title_tokens")


def title_sets(spark, sf_dir) -> DataFrame:
    """Title word sets (text_, ws, least): records with equal sets stand behind the least of them."""
    r = tables.document_records(documents(spark, sf_dir)).select("doc_id", F.array_sort("title_tokens").alias("ws")).where(F.size(F.array_except("ws", F.array(*map(F.lit, blocking.STOP)))) > 0)
    return r.groupBy(F.array_join("ws", " ").alias("text_")).agg(F.first("ws").alias("ws"), F.min("doc_id").alias("least"), F.count("*").alias("copies"))


HELD_SETS_SQL = f"SELECT array_to_string(ws, ' ') AS t, any_value(ws) AS ws, min(doc_id) AS least, count(*) AS copies FROM ({TITLED_SQL}) WHERE len(list_filter(ws, lambda w: NOT list_contains({STOPS}, w))) > 0 GROUP BY 1"


@query(f"SELECT least, copies FROM ({HELD_SETS_SQL})")
def n6_title_classes(spark, sf_dir):
    """Records by equal titles: the least record of each class and the class's size; the exact way beside capped blocks."""
    return title_sets(spark, sf_dir).select("least", "copies")


@query(f"WITH s AS MATERIALIZED ({HELD_SETS_SQL}) SELECT least(a.least, b.least) AS d1, greatest(a.least, b.least) AS d2 FROM s a JOIN s b ON a.t < b.t WHERE {ALIKE_SQL}")
def n6_similar_titles(spark, sf_dir):
    """Pairs of classes whose titles are alike, by words of any frequency: exact, where n6_candidates_minkey blocks by rare words."""
    sets = title_sets(spark, sf_dir)
    named = lambda k: sets.select(F.col("text_").alias(f"k{k}"), F.col("least").alias(f"least{k}"))
    pairs = blocking.similar_sets(sets, "text_", "ws", 0.5).join(named(1), "k1").join(named(2), "k2")
    return pairs.select(F.least("least1", "least2").alias("d1"), F.greatest("least1", "least2").alias("d2"))


@query(f"SELECT d1, d2 FROM (SELECT d1, d2, row_number() OVER (PARTITION BY d1 ORDER BY len(list_intersect(w1, w2)) / len(list_distinct(list_concat(w1, w2)))::DOUBLE DESC, d2) AS rn FROM ({SIDES_SQL}) WHERE len(list_intersect(w1, w2)) >= 0.5 * nullif(len(list_distinct(list_concat(w1, w2))), 0)) WHERE rn = 1")
def n15_best_match(spark, sf_dir):
    return resolve.best_match(title_matches(spark, sf_dir)).select("d1", "d2")


SCORED_MATCH_SQL = f"SELECT d1, d2, s1, s2, len(list_intersect(w1, w2)) / len(list_distinct(list_concat(w1, w2)))::DOUBLE AS score FROM ({SIDES_SQL}) WHERE len(list_intersect(w1, w2)) >= 0.5 * nullif(len(list_distinct(list_concat(w1, w2))), 0)"


@query(f"SELECT d1, d2, s1, s2, round(score, 6) AS score FROM (SELECT *, row_number() OVER (PARTITION BY d1, s2 ORDER BY score DESC, d2) AS a, row_number() OVER (PARTITION BY d2, s1 ORDER BY score DESC, d1) AS b FROM ({SCORED_MATCH_SQL})) WHERE a = 1 AND b = 1")
def n15_one_per_source(spark, sf_dir):
    return rounded(resolve.one_per_source(title_matches(spark, sf_dir)), "score")


MERGE_SQL = f"""{CLUSTERS_SQL}, c AS (SELECT a AS doc_id, min(b) AS cluster FROM r GROUP BY a)
  SELECT coalesce(cluster, doc_id) AS cluster, count(*) AS records, (max({{'n': length(title), 't': title}})).t AS title, arg_min(lang, doc_id) AS lang,
    coalesce(array_to_string(list_sort(list_distinct(list(source_id) FILTER (WHERE source_id IS NOT NULL))), ','), '') AS sources
  FROM h LEFT JOIN c USING (doc_id) GROUP BY 1"""


@query(MERGE_SQL)
def n16_merge(spark, sf_dir):
    """Merges by titles, common words and large groups of copies included."""
    records = tables.document_records(documents(spark, sf_dir))
    return resolve.merge_records(records, resolve.cluster_by_words(records, "title_tokens"))


@query()
def w9_master_match(spark, sf_dir):
    """Benchmark items are the master, documents the other sources.

    A document that holds six tenths of an item's words holds one of any four tenths and one more of them, so documents meet
    items by each item's rarest words, as many as that and however common.
    """
    words = lambda c: F.array_distinct(F.filter(F.split(P.ascii_fold(c), "[^a-z0-9]+"), lambda w: F.length(w) >= 6))
    items = tables.load(spark, sf_dir, "benchmark").select(F.col("item_id").alias("doc_id"), words(F.col("text")).alias("ws"))
    docs = documents(spark, sf_dir).select((F.col("doc_id") + 1_000_000_000).alias("doc_id"), words(F.col("text")).alias("ws"))
    asked, held = (x.select(F.col("doc_id").alias(d), F.explode("ws").alias("w")) for x, d in ((items, "d1"), (docs, "d2")))
    df = held.join(asked.select("w").distinct(), "w", "left_semi").groupBy("w").agg(F.count("*").alias("df"))
    ranked = asked.join(df, "w", "left").groupBy("d1").agg(F.array_sort(F.collect_list(F.struct(F.coalesce("df", F.lit(0)).alias("df"), "w"))).alias("ws"))
    rarest = ranked.select("d1", F.explode(F.slice("ws", F.lit(1), F.floor(F.size("ws") * 2 / 5 + 1e-3).cast("int") + 1)).alias("x")).select("d1", "x.w")
    pairs = held.join(rarest, "w").select("d1", "d2").distinct()
    left, right = items.select(F.col("doc_id").alias("d1"), F.col("ws").alias("w1")), docs.select(F.col("doc_id").alias("d2"), F.col("ws").alias("w2"))
    share = F.size(F.array_intersect("w1", "w2")) / F.greatest(F.size("w1"), F.lit(1))
    scored = pairs.join(left, "d1").join(right, "d2").select(F.col("d1").alias("item_id"), (F.col("d2") - 1_000_000_000).alias("doc_id"), share.alias("containment"))
    return rounded(scored.where(F.col("containment") >= 0.6), "containment")


# -- experiment workloads ----------------------------------------------------------------------------------------------


#: Rows of the grid: budgets per source pair, per source and in total, in three steps each; and trials with labels of their own.
GRID = {"pair": (5, 20, 60), "source": (25, 100, 300), "total": (75, 300, 900)}
GRID_TRIALS = 5
#: The kernel baseline's grid: c, sigma, folds.
SVM_GRID = ((1.0, 10.0), (1.0, 2.0), 10)


def grid_scores(spark, sf_dir, grid: dict = GRID) -> DataFrame:
    """Scores of four methods on one fixed pair of sources, for all budgets and trials; 200 labels wait per pair."""
    pool = sampling.with_folds(train(spark, sf_dir, Design(sources=6, per_pair=200, trials=GRID_TRIALS)), P.mix(F.col("e1"), 9), 10)
    parts = [sampling.sample_labels(pool, order(), k, unit, ["trial"]).withColumns({"unit": F.lit(unit), "budget": F.lit(k)}) for unit, sizes in grid.items() for k in sizes]
    labels = parts[0]
    for p in parts[1:]:
        labels = labels.unionByName(p)
    test = synthetic.synthetic_pairs(part(spark, sf_dir), Design(sources=6, per_pair=400, role="test"), (F.col("s1") == 1) & (F.col("s2") == 6))
    return trials.run(labels, ["unit", "budget", "trial"], test, XS, SCALE, folds=5, svm_grid=SVM_GRID, sources=6)


@query()
def w1_pr_grid(spark, sf_dir):
    """Three by three curves of four methods on one fixed pair of sources, with bands over trials at each recall."""
    curve = evaluate.pr_curve(grid_scores(spark, sf_dir), ["unit", "budget", "method", "trial"], bins=256)
    at = curve.select("unit", "budget", "method", "trial", "precision", F.explode(F.sequence(F.lit(1), F.greatest(F.floor(F.col("recall") * 20 + 1e-9).cast("int"), F.lit(1)))).alias("step"), "recall")
    best = at.where(F.col("recall") >= F.col("step") / 20 - 1e-9).groupBy("unit", "budget", "method", "trial", "step").agg(F.max("precision").alias("precision"))
    bands = evaluate.band(best, "precision", ["unit", "budget", "method", "step"]).withColumn("recall", F.col("step") / 20).drop("step")
    return rounded(bands, "mean", "low", "high", "width")


@query()
def w1_budget_units(spark, sf_dir):
    """Errors on the fixed pair under budgets counted per source pair, per source and in total."""
    errors = evaluate.test_error(grid_scores(spark, sf_dir), by=["unit", "budget", "method", "trial", "n_labels"])
    out = evaluate.band(errors, "test_error", ["unit", "budget", "method"])
    return rounded(out, "mean", "low", "high", "width")


@query()
def w2_precision_at_085(spark, sf_dir):
    """Precision at recall 0.85 on the fixed pair against all labels used, for the nine budgets; mean and band of trials."""
    curve = evaluate.pr_curve(grid_scores(spark, sf_dir), ["unit", "budget", "n_labels", "method", "trial"], bins=1024)
    at = evaluate.precision_at_recall(curve, 0.85, ["unit", "budget", "n_labels", "method", "trial"])
    labels = at.groupBy("unit", "budget").agg(F.avg("n_labels").alias("labels"))
    return rounded(evaluate.band(at, "precision", ["unit", "budget", "method"]).join(F.broadcast(labels), ["unit", "budget"]), "mean", "low", "high", "width", "labels")


def budget_errors(spark, sf_dir, d: Design, test: Design, budgets: tuple[int, ...]) -> DataFrame:
    """Test errors by method, budget (labels per source pair) and trial."""
    pool = sampling.with_folds(train(spark, sf_dir, d), P.mix(F.col("e1"), 9), 5)
    nested = pool.withColumn("budget", F.explode(F.filter(F.array(*map(F.lit, budgets)), lambda b: F.col("r") < b)))
    scored = trials.run(nested, ["budget", "trial"], train(spark, sf_dir, test), XS, SCALE, folds=5)
    return evaluate.test_error(scored, by=["method", "budget", "trial", "n_labels"])


@query()
def w3_sample_complexity(spark, sf_dir):
    """Error against labels per source pair, on ten sources; mean and band of trials."""
    errors = budget_errors(spark, sf_dir, Design(sources=10, per_pair=200, trials=5), TEN_TEST, BUDGETS)
    return rounded(evaluate.band(errors, "test_error", ["method", "budget"]), "mean", "low", "high", "width")


#: The sweep over sources: 2 to 30 in steps of two, labels a source, trials, test pairs of each size.
SWEEP, SWEEP_LABELS, SWEEP_TRIALS, SWEEP_TEST = tuple(range(2, 31, 2)), 40, 50, 10_000


def source_sweep(spark, sf_dir, sizes: tuple[int, ...], per_source: int, n_trials: int, n_test: int) -> DataFrame:
    """Errors by method, number of sources and trial, with labels in proportion to sources.

    Sources are nested: the first S of one profile, with per_source * S labels spread over their pairs, drawn anew in each
    trial.  A label is in all sizes whose share of its pair reaches it.
    """
    most = max(sizes)
    in_size = lambda s, labels: (F.col("s2") <= s) & (F.col("r") < math.ceil(2 * labels / (s * (s - 1))))
    level = lambda s, labels: F.when(in_size(s, labels), F.lit(s))
    levels = F.filter(F.array(*(level(s, per_source * s) for s in sizes)), lambda s: s.isNotNull())
    some = lambda of: reduce(Column.__or__, (in_size(s, of(s)) for s in sizes))
    d = Design(sources=most, per_pair=2 * per_source, trials=n_trials)
    labels = synthetic.synthetic_pairs(part(spark, sf_dir), d, some(lambda s: per_source * s)).withColumn("size", F.explode(levels))
    test = synthetic.synthetic_pairs(part(spark, sf_dir), Design(sources=most, per_pair=n_test, role="test"), some(lambda s: n_test))

    def among(key, rows):
        s = key[0]
        return ((rows.s2 <= s) & (rows.r < math.ceil(2 * n_test / (s * (s - 1))))).to_numpy()

    return evaluate.test_error(trials.run(labels, ["size", "trial"], test, XS, SCALE, among=among), by=["method", "size", "trial"])


@query()
def w4_source_complexity(spark, sf_dir):
    """Error against the number of sources at a constant number of labels a source; mean and band of 50 trials."""
    errors = source_sweep(spark, sf_dir, SWEEP, SWEEP_LABELS, SWEEP_TRIALS, SWEEP_TEST)
    return rounded(evaluate.band(errors, "test_error", ["method", "size"]), "mean", "low", "high", "width")


def _runtime(spark, sf_dir, per_pair: int) -> DataFrame:
    """Test error of each method's iterates; the iterates of all methods are scored in one join."""
    b, t = scaled(block_of(train(spark, sf_dir, Design(sources=10, per_pair=per_pair)))[()])
    learner = learners.SourceOffsetLearner(solver.lambda_max(learners.SourceOffsetLearner(0.0).problem(b)) / 50, max_iter=200, accelerate=False)
    snaps, keep = [], (0, 1, 2, 5, 10, 20, 50, 100, 200)
    for name, trace in (("offset", learner.solution(b, trace=True).trace), ("pooled", learners.PooledLearner().solution(b, trace=True, max_iter=200).trace)):
        for s in (s for s in trace if s["iter"] in keep):
            snaps.append((name, s, learners.OffsetModel(name, s["w0"], {int(k): w for k, w in zip(b.sources, s["w"], strict=True)}).untransformed(t)))
    for s in (s for s in learners.PairwiseLearner().trajectory(b, 200) if s["iter"] in keep):
        pairs = {(int(i), int(j)): w for i, j, w in zip(b.s1, b.s2, s["pairs"], strict=True)}
        snaps.append(("pairwise", s, learners.OffsetModel("pairwise", np.zeros(D + 1), pairs=pairs, pairs_only=True).untransformed(t)))
    scored = scoring.score(train(spark, sf_dir, Design(sources=10, per_pair=60, role="test")), [({"method": n, "iter": s["iter"]}, m) for n, s, m in snaps], XS, SCALE)
    times = flagged(spark, [(n, s["iter"], float(s["elapsed_ms"]), float(s["objective"])) for n, s, _ in snaps], "method string, iter long, elapsed_ms double, objective double")
    return rounded(evaluate.test_error(scored, by=["method", "iter"]).join(F.broadcast(times), ["method", "iter"]), "test_error", "objective")


@query()
def w5_runtime_20(spark, sf_dir):
    return _runtime(spark, sf_dir, 20)


@query()
def w5_runtime_100(spark, sf_dir):
    return _runtime(spark, sf_dir, 100)


@query()
def w6_label_growth(spark, sf_dir):
    """The fewest labels that reach one error, by number of sources, and the exponent of their growth; errors are means of trials."""
    sizes, budgets = (4, 6, 8, 10, 12, 16), (3, 5, 8, 12, 18, 27, 40, 60, 90)
    d = Design(sources=max(sizes), per_pair=max(budgets), trials=3)
    cells = F.flatten(F.array(*(F.array(*(F.when((F.col("s2") <= s) & (F.col("r") < b), F.struct(F.lit(s).alias("size"), F.lit(b).alias("budget"))) for b in budgets)) for s in sizes)))
    labels = train(spark, sf_dir, d).withColumn("cell", F.explode(F.filter(cells, lambda c: c.isNotNull()))).select("*", "cell.*").drop("cell")
    test = train(spark, sf_dir, Design(sources=max(sizes), per_pair=60, role="test"))
    scored = trials.run(labels, ["size", "budget", "trial"], test, XS, SCALE, among=lambda key, rows: (rows.s2 <= key[0]).to_numpy())
    errors = evaluate.test_error(scored, by=["method", "size", "budget", "trial", "n_labels"])
    means = errors.groupBy("method", "size", "budget").agg(F.avg("test_error").alias("test_error"), F.max("n_labels").alias("labels"))
    costs = evaluate.labels_to_target(means.withColumnRenamed("size", "sources"), 0.14, ["method", "sources"])
    return rounded(evaluate.growth_exponent(costs, by=["method"]), "exponent", places=4)


@query(f"SELECT s1, s2, count(*) AS labels, CAST(sum(CASE WHEN y > 0 THEN 1 ELSE 0 END) AS BIGINT) AS matches FROM ({synthetic.synthetic_pairs_sql(Design(sources=6, per_pair=200))}) GROUP BY s1, s2")
def w7_label_ledger(spark, sf_dir):
    df = train(spark, sf_dir, Design(sources=6, per_pair=200))
    return df.groupBy("s1", "s2").agg(F.count("*").alias("labels"), F.sum(F.when(F.col("y") > 0, 1).otherwise(0)).alias("matches"))


@query()
def w10_unseen_pairs(spark, sf_dir):
    """Three tenths of the source pairs have no labels; errors on those only, where the pairwise learner has no answer."""
    hidden = P.mix(F.col("s1") * 100 + F.col("s2"), 1) % 10 < 3
    df = train(spark, sf_dir, Design(sources=10, per_pair=40))
    models = fit_three(block_of(df.where(~hidden))[()])
    scored = scoring.score(train(spark, sf_dir, TEN_TEST).where(hidden), [({"method": m.method}, m) for m in models], XS, SCALE)
    wrong = F.avg(F.when(F.col("score").isNotNull(), ((F.col("score") >= 0) != (F.col("y") > 0)).cast("double")))
    return rounded(scored.groupBy("method").agg(wrong.alias("test_error"), F.count("score").alias("scored"), F.count("*").alias("pairs")), "test_error")


@query()
def w12_null(spark, sf_dir):
    """Labels without signal: every method must stay at the base rate."""
    e = tables.load(spark, sf_dir, "embeddings").select("vec_id", (F.col("vec_id") % 6 + 1).cast("int").alias("s"), "embedding", "label")
    n = e.count()
    a, b = (e.select(*(F.col(c).alias(f"{c}{k}") for c in e.columns)) for k in (1, 2))
    # Each vector meets those at thirty distances around the ring of ids.
    met = a.withColumn("vec_id2", F.explode(F.transform(F.sequence(F.lit(1), F.lit(30)), lambda k: (F.col("vec_id1") + 7 * k) % n))).join(b, "vec_id2")
    part_ = lambda k: F.aggregate(F.zip_with(F.slice("embedding1", 12 * k + 1, 12), F.slice("embedding2", 12 * k + 1, 12), lambda x, y: F.abs(x - y).cast("double")), F.lit(0.0), lambda t, v: t + v)
    pairs = met.where("s1 <> s2").select("s1", "s2", F.when(F.col("label1") == F.col("label2"), 1).otherwise(-1).alias("y"), *(part_(k).alias(f"x{k + 1}") for k in range(D)), "vec_id1")
    pairs = resolve.stored(moments.canonical(pairs), "pairs")
    half = F.col("vec_id1") % 2
    b_, t = scaled(moments.to_driver(moments.pair_moments(pairs.where(half == 0), XS, number="double"), D)[()])
    models = [learners.PooledLearner().fit(b_).untransformed(t), learners.PairwiseLearner().fit(b_).untransformed(t), learners.SourceOffsetLearner(5.0).fit(b_).untransformed(t)]
    scored = scoring.score(pairs.where(half == 1), [({"method": m.method}, m) for m in models], XS)
    base = F.avg((F.col("y") > 0).cast("double")).alias("base_rate")
    return rounded(evaluate.test_error(scored, by=["method"]).join(scored.groupBy("method").agg(base), "method"), "test_error", "base_rate")


EVENT_SQL = "SELECT event_id, ts, CAST(user_id % 6 + 1 AS INTEGER) AS s1, CAST((user_id + k % 5 + 1) % 6 + 1 AS INTEGER) AS s2, CAST(floor(value * 100) AS BIGINT) AS x1, CASE WHEN k % 2 = 0 THEN 1 ELSE -1 END AS y FROM (SELECT *, coalesce(TRY_CAST(json_extract_string(props, '$.k') AS INTEGER), 0) AS k FROM events)"
CANON_SQL = f"SELECT least(s1, s2) AS s1, greatest(s1, s2) AS s2, x1, y, ts FROM ({EVENT_SQL}) WHERE s1 <> s2"


@query(moments.pair_moments_sql(CANON_SQL, 1))
def w14_stream_moments(spark, sf_dir):
    """Moments of label arrivals, by a stream over the event files; equal to the batch result."""
    import uuid

    source = spark.readStream.schema(spark.read.parquet(f"{sf_dir}/events.parquet").schema).option("pathGlobFilter", "events.parquet").parquet(sf_dir)
    totals = stream.stream_moments(stream.label_events(source), ["x1"])
    return stream.run_to_memory(totals, f"moments_{uuid.uuid4().hex}")


# -- operators around the methods --------------------------------------------------------------------------------------


@query("SELECT a.p_partkey AS p1, b.p_partkey AS p2 FROM part a JOIN part b ON a.p_brand = b.p_brand AND a.p_partkey < b.p_partkey AND abs(a.p_retailprice - b.p_retailprice) <= 5.0")
def rel_range_join(spark, sf_dir):
    pairs = relational.range_pairs(part(spark, sf_dir), "p_partkey", "p_retailprice", 5.0, ["p_brand"])
    return pairs.where("p_partkey_1 < p_partkey_2").select(F.col("p_partkey_1").alias("p1"), F.col("p_partkey_2").alias("p2"))


@query("SELECT e.event_id, (SELECT max_by(v.event_id, (v.ts, v.event_id)) FROM events v WHERE v.user_id = e.user_id AND v.event_type = 'purchase' AND v.ts <= e.ts) AS version FROM events e WHERE e.event_type = 'click'")
def rel_asof_join(spark, sf_dir):
    e = tables.load(spark, sf_dir, "events")
    versions = e.where("event_type = 'purchase'").groupBy("user_id", "ts").agg(F.max("event_id").alias("version"))
    clicks = e.where("event_type = 'click'").select("event_id", "user_id", "ts")
    return relational.asof_join(clicks, versions, "user_id", "ts", "version").select("event_id", "version")


@query("SELECT doc_id, source FROM documents SEMI JOIN labels USING (doc_id)")
def rel_semi_join(spark, sf_dir):
    return documents(spark, sf_dir).join(tables.load(spark, sf_dir, "labels"), "doc_id", "left_semi").select("doc_id", "source")


@query("SELECT doc_id, source FROM documents ANTI JOIN labels USING (doc_id)")
def rel_anti_join(spark, sf_dir):
    return documents(spark, sf_dir).join(tables.load(spark, sf_dir, "labels"), "doc_id", "left_anti").select("doc_id", "source")


@query("SELECT coalesce(a.doc_id, b.doc_id) AS doc_id, a.lang, b.toxic FROM (SELECT * FROM documents WHERE lang = 'fr') a FULL JOIN (SELECT * FROM labels WHERE toxic = 1) b ON a.doc_id = b.doc_id")
def rel_full_join(spark, sf_dir):
    a, b = documents(spark, sf_dir).where("lang = 'fr'").select("doc_id", "lang"), tables.load(spark, sf_dir, "labels").where("toxic = 1").select("doc_id", "toxic")
    return a.join(b, "doc_id", "full").select("doc_id", "lang", "toxic")


@query("SELECT l_returnflag, l_linestatus, count(*) AS n, CAST(sum(CAST(l_quantity AS BIGINT)) AS BIGINT) AS quantity FROM lineitem GROUP BY ROLLUP (l_returnflag, l_linestatus)")
def rel_rollup(spark, sf_dir):
    return tables.load(spark, sf_dir, "lineitem").rollup("l_returnflag", "l_linestatus").agg(F.count("*").alias("n"), F.sum(F.col("l_quantity").cast("long")).alias("quantity"))


@query("SELECT l_returnflag, l_linestatus, count(*) AS n FROM lineitem GROUP BY CUBE (l_returnflag, l_linestatus)")
def rel_cube(spark, sf_dir):
    return tables.load(spark, sf_dir, "lineitem").cube("l_returnflag", "l_linestatus").agg(F.count("*").alias("n"))


@query("SELECT source, count(*) FILTER (WHERE lang = 'de') AS de, count(*) FILTER (WHERE lang = 'en') AS en, count(*) FILTER (WHERE lang = 'es') AS es, count(*) FILTER (WHERE lang = 'fr') AS fr FROM documents GROUP BY source")
def rel_pivot(spark, sf_dir):
    return documents(spark, sf_dir).groupBy("source").pivot("lang", ["de", "en", "es", "fr"]).agg(F.count("doc_id")).na.fill(0)


@query("SELECT conv_id, turn, role, lag(role) OVER w AS before, CAST(dense_rank() OVER w AS INTEGER) AS place FROM conversations WINDOW w AS (PARTITION BY conv_id ORDER BY turn)")
def rel_windows(spark, sf_dir):
    w = Window.partitionBy("conv_id").orderBy("turn")
    return tables.load(spark, sf_dir, "conversations").select("conv_id", "turn", "role", F.lag("role").over(w).alias("before"), F.dense_rank().over(w).alias("place"))


@query(f"({PAIRS_SQL}) EXCEPT SELECT d1, d2, s1, s2 FROM ({SIDES_SQL}) WHERE len(list_intersect(w1, w2)) >= 0.5 * nullif(len(list_distinct(list_concat(w1, w2))), 0)")
def rel_set_ops(spark, sf_dir):
    return n6_candidates_minkey(spark, sf_dir).exceptAll(title_matches(spark, sf_dir).select("d1", "d2", "s1", "s2"))


@query("SELECT event_type, coalesce(TRY_CAST(json_extract_string(props, '$.k') AS INTEGER), -1) AS k, count(*) AS n FROM events GROUP BY 1, 2")
def rel_json(spark, sf_dir):
    return tables.load(spark, sf_dir, "events").groupBy("event_type", F.coalesce(F.get_json_object("props", "$.k").try_cast("int"), F.lit(-1)).alias("k")).agg(F.count("*").alias("n"))


@query(f"SELECT s1, s2, r, feature, round(share, 6) AS share FROM (SELECT s1, s2, r, unnest(['x1', 'x2']) AS feature, unnest([{FIXED_WEIGHTS[1]!r} * x1 / {SCALE}, {FIXED_WEIGHTS[2]!r} * x2 / {SCALE}])::DOUBLE AS share FROM ({TRAIN_SQL}))")
def rel_contributions(spark, sf_dir):
    """What each feature adds to a score, as a map, taken apart again."""
    shares = vectors.contributions(["x1", "x2"], [F.col("x1") / SCALE, F.col("x2") / SCALE], [F.lit(FIXED_WEIGHTS[1]), F.lit(FIXED_WEIGHTS[2])])
    return rounded(train(spark, sf_dir).select("s1", "s2", "r", F.explode(shares).alias("feature", "share")), "share")


@query("SELECT time_bucket(INTERVAL 1 DAY, ts) AS start, count(*) AS labels FROM events GROUP BY 1")
def rel_event_windows(spark, sf_dir):
    e = tables.load(spark, sf_dir, "events").withColumn("ts", F.col("ts").cast("timestamp"))
    return stream.throughput(e).select(F.col("start").cast("timestamp_ntz").alias("start"), "labels")


@query("SELECT n_name, p_partkey FROM nation, LATERAL (SELECT p_partkey FROM part WHERE p_size = n_nationkey + 1 ORDER BY p_retailprice DESC, p_partkey LIMIT 2)")
def rel_top_k(spark, sf_dir):
    n, p = tables.load(spark, sf_dir, "nation"), part(spark, sf_dir)
    joined = p.join(F.broadcast(n), p.p_size == n.n_nationkey + 1)
    return relational.top_k(joined, ["n_name"], [F.desc("p_retailprice"), "p_partkey"], 2).select("n_name", "p_partkey")


# -- more variants and operators ---------------------------------------------------------------------------------------


@query("SELECT p_partkey, round((c - a) / 2, 6) AS first, round((d - b) / 2, 6) AS second FROM (SELECT p_partkey, p_size::DOUBLE AS a, p_retailprice AS b, (p_size % 7)::DOUBLE AS c, p_retailprice / 3 AS d FROM part)")
def m2_limit_deviation(spark, sf_dir):
    a = F.array(F.col("p_size").cast("double"), F.col("p_retailprice"))
    b = F.array((F.col("p_size") % 7).cast("double"), F.col("p_retailprice") / 3)
    v = vectors.limit_deviation(a, b)
    return rounded(part(spark, sf_dir).select("p_partkey", v[0].alias("first"), v[1].alias("second")), "first", "second")


@query("SELECT p_partkey, round(abs(p_size - 25) + abs(p_retailprice), 6) AS l1, round(sqrt(pow(p_size - 25, 2) + pow(p_retailprice, 2)), 6) AS l2, round(greatest(abs(p_size - 25), abs(p_retailprice)), 6) AS largest FROM part")
def rel_norms(spark, sf_dir):
    v = F.array((F.col("p_size") - 25).cast("double"), F.col("p_retailprice"))
    return rounded(part(spark, sf_dir).select("p_partkey", *(vectors.norm(v, k).alias(n) for k, n in (("l1", "l1"), ("l2", "l2"), ("max", "largest")))), "l1", "l2", "largest")


@query()
def r11_scoring_cost(spark, sf_dir):
    """Seconds and pairs a second of one linear scorer and of the offset learner's, on the same pairs, best of three."""
    import time

    pairs = train(spark, sf_dir, Design(sources=10, per_pair=1000)).cache()
    n = pairs.count()
    model = fit_offset(block_of(pairs)[()])
    ways = {"linear": lambda: scoring.score_fixed(pairs, list(FIXED_WEIGHTS), XS, SCALE), "offset": lambda: scoring.score(pairs, [({"method": "offset"}, model)], XS, SCALE)}
    rows = []
    for name, way in ways.items():
        took = []
        for _ in range(3):
            began = time.perf_counter()
            way().agg(F.sum("score")).first()
            took.append(time.perf_counter() - began)
        rows.append((name, n, min(took), n / min(took)))
    pairs.unpersist()
    return flagged(spark, rows, "scorer string, pairs long, seconds double, pairs_a_second double")


@query()
def r14_convergence(spark, sf_dir):
    """Ratios of successive gaps of plain steps, against the optimum of the reference solver."""
    b, _ = scaled(block_of(train(spark, sf_dir))[()])
    learner = learners.SourceOffsetLearner(5.0, accelerate=False, max_iter=60, tol=-1)
    best = solver.solve_reference(learner.problem(b), 5.0).objective
    trace = flagged(spark, [(r["iter"], float(r["objective"])) for r in learner.solution(b, trace=True).trace], "iter int, objective double")
    return rounded(evaluate.convergence_rate(trace, best), "gap", "ratio")


@query()
def r15_dominance(spark, sf_dir):
    """Which method leads at which recall, with 20 labels per pair."""
    scored = grid_scores(spark, sf_dir, {"pair": (20,)})
    return rounded(evaluate.dominance(evaluate.pr_curve(scored, ["method"], bins=512)), "precision")


@query()
def b5_other_losses(spark, sf_dir):
    """Pooled and pairwise learners under logistic and squared hinge losses."""
    df = train(spark, sf_dir).cache()
    models = [losses.LossLearner(0.0, loss, pooled=True).fit(df, XS, SCALE) for loss in ("logistic", "squared_hinge")]
    models += [losses.fit_pairwise_loss(df, XS, loss, SCALE) for loss in ("logistic", "squared_hinge")]
    df.unpersist()
    return _errors(spark, sf_dir, models)


@query()
def w1_documents(spark, sf_dir):
    """Curves on documents in six unequal sources, learned from half of the candidates: pooled against offset learner."""
    pairs = doc_pairs(spark, sf_dir).withColumns({"s1": tables.six_way(F.col("d1")).cast("int"), "s2": tables.six_way(F.col("d2")).cast("int")})
    pairs = resolve.stored(moments.canonical(pairs), "pairs")
    half = P.mix(F.col("d1") * 7919 + F.col("d2"), 3) % 2
    b, t = scaled(moments.to_driver(moments.pair_moments(pairs.where(half == 0), XS, number="double"), D)[()])
    models = [learners.PooledLearner().fit(b).untransformed(t), doc_model(pairs.where(half == 0))]
    scored = scoring.score(pairs.where(half == 1), [({"method": m.method}, m) for m in models], XS)
    return rounded(evaluate.pr_curve(scored, ["method"], bins=128), "tau", "precision", "recall")


@query("SELECT doc_id, 'quality' AS what, quality AS value FROM labels UNION ALL SELECT doc_id, 'toxic', toxic FROM labels")
def rel_unpivot(spark, sf_dir):
    return tables.load(spark, sf_dir, "labels").unpivot("doc_id", ["quality", "toxic"], "what", "value")


@query("SELECT p_partkey, CAST(ntile(10) OVER (ORDER BY p_retailprice, p_partkey) AS INTEGER) AS tenth FROM part")
def rel_ntile(spark, sf_dir):
    return relational.tiles(part(spark, sf_dir).select("p_partkey", "p_retailprice"), ["p_retailprice", "p_partkey"], 10, "tenth").select("p_partkey", "tenth")


@query(f"SELECT token, df FROM (SELECT *, row_number() OVER (ORDER BY df DESC, token) AS rn FROM ({DF_SQL})) WHERE rn <= 25")
def rel_heavy_tokens(spark, sf_dir):
    return blocking.token_frequency(titled(spark, sf_dir), "title_tokens").orderBy(F.desc("df"), "token").limit(25)


@query("SELECT a.lang, count(*) AS pairs FROM (SELECT DISTINCT lang, source FROM documents) a JOIN (SELECT DISTINCT lang FROM documents) b ON a.lang IS NOT DISTINCT FROM b.lang GROUP BY a.lang")
def rel_null_safe_join(spark, sf_dir):
    d = documents(spark, sf_dir)
    a, b = d.select("lang", "source").distinct(), d.select(F.col("lang").alias("other")).distinct()
    return a.join(b, a["lang"].eqNullSafe(b["other"])).groupBy("lang").agg(F.count("*").alias("pairs"))


@query("SELECT item_id, unnest(list_sort(list_distinct(regexp_extract_all(lower(text), '[a-z0-9]+')))) AS block_key FROM benchmark")
def rel_table_function(spark, sf_dir):
    spark.udtf.register("token_blocks", relational.token_blocks())
    tables.load(spark, sf_dir, "benchmark").createOrReplaceTempView("offsetlink_benchmark")
    return spark.sql("SELECT item_id, block_key FROM offsetlink_benchmark, LATERAL token_blocks(text)")


@query(f"SELECT s1, s2, CAST(sum(x1 * x2) AS DOUBLE) AS g1_2 FROM ({TRAIN_SQL}) GROUP BY s1, s2")
def rel_grouped_gram(spark, sf_dir):
    return train(spark, sf_dir).groupBy("s1", "s2").agg(relational.grouped_gram()("x1", "x2").alias("g1_2"))


@query("SELECT l_returnflag, round(covar_pop(l_quantity, l_extendedprice), 3) AS covariance, round(corr(l_quantity, l_extendedprice), 6) AS correlation, round(regr_slope(l_extendedprice, l_quantity), 4) AS slope FROM lineitem GROUP BY l_returnflag")
def rel_covariance(spark, sf_dir):
    li = tables.load(spark, sf_dir, "lineitem")
    out = li.groupBy("l_returnflag").agg(F.covar_pop("l_quantity", "l_extendedprice").alias("covariance"), F.corr("l_quantity", "l_extendedprice").alias("correlation"), F.regr_slope("l_extendedprice", "l_quantity").alias("slope"))
    return out.select("l_returnflag", F.round("covariance", 3).alias("covariance"), F.round("correlation", 6).alias("correlation"), F.round("slope", 4).alias("slope"))


@query()
def rel_approximate(spark, sf_dir):
    """Distinct counts and quantiles in bounded memory beside the exact ones."""
    li = tables.load(spark, sf_dir, "lineitem")
    return li.groupBy("l_returnflag").agg(
        F.approx_count_distinct("l_partkey", 0.02).alias("distinct_parts"), F.count_distinct("l_partkey").alias("exact_parts"),
        F.percentile_approx("l_extendedprice", 0.5, 10_000).alias("median"), F.percentile("l_extendedprice", F.lit(0.5)).alias("exact_median"),
    )


@query("WITH f AS (SELECT p_partkey, nullif(p_size % 7, 0)::DOUBLE AS a, CASE WHEN p_partkey % 5 = 0 THEN NULL ELSE p_retailprice END AS b FROM part), m AS (SELECT avg(a) AS a, avg(b) AS b FROM f) SELECT p_partkey, round(coalesce(f.a, m.a), 6) AS a, round(coalesce(f.b, m.b), 6) AS b, f.a IS NULL AS a_missing FROM f, m")
def rel_filled_features(spark, sf_dir):
    """Missing features by their mean, from one aggregate, and a flag that they were missing."""
    f = part(spark, sf_dir).select("p_partkey", F.nullif(F.col("p_size") % 7, F.lit(0)).cast("double").alias("a"), F.when(F.col("p_partkey") % 5 != 0, F.col("p_retailprice")).alias("b"))
    m = f.agg(F.avg("a").alias("mean_a"), F.avg("b").alias("mean_b"))
    filled = f.crossJoin(F.broadcast(m)).select("p_partkey", F.coalesce("a", "mean_a").alias("x"), F.coalesce("b", "mean_b").alias("y"), F.col("a").isNull().alias("a_missing"))
    return filled.select("p_partkey", F.round("x", 6).alias("a"), F.round("y", 6).alias("b"), "a_missing")


@query("SELECT approx.source, approx.langs FROM (SELECT source, count(DISTINCT lang) AS langs FROM documents GROUP BY source) approx")
def rel_distinct_counts(spark, sf_dir):
    return documents(spark, sf_dir).groupBy("source").agg(F.count_distinct("lang").alias("langs"))


@query(f"SELECT event_id, round((0.5 - 0.01 * x1 + CASE WHEN s1 = 2 THEN 0.1 ELSE 0 END + CASE WHEN s2 = 2 THEN 0.1 ELSE 0 END)::DOUBLE, 6) AS score FROM (SELECT event_id, least(s1, s2) AS s1, greatest(s1, s2) AS s2, x1 FROM ({EVENT_SQL}) WHERE s1 <> s2)")
def w14_stream_scores(spark, sf_dir):
    """Arriving pairs scored as they come."""
    source = spark.readStream.schema(spark.read.parquet(f"{sf_dir}/events.parquet").schema).option("pathGlobFilter", "events.parquet").parquet(sf_dir)
    model = learners.OffsetModel("m", np.array([0.5, -0.01]), {2: np.array([0.2, 0.0])})
    scored = stream.score_stream(moments.canonical(stream.label_events(source)), [({"method": "m"}, model)], ["x1"])
    return stream.run_to_files(rounded(scored.select("event_id", "score"), "score"), "scores")


@query("SELECT user_id, a.event_id AS e1, b.event_id AS e2 FROM events a JOIN events b USING (user_id) WHERE a.event_type = 'click' AND b.event_type = 'purchase' AND b.ts BETWEEN a.ts - INTERVAL 6 HOUR AND a.ts + INTERVAL 6 HOUR")
def w14_stream_meeting(spark, sf_dir):
    """Two streams joined within a time bound."""
    import uuid

    schema = spark.read.parquet(f"{sf_dir}/events.parquet").schema
    read = lambda: spark.readStream.schema(schema).option("pathGlobFilter", "events.parquet").parquet(sf_dir).withColumn("ts", F.col("ts").cast("timestamp"))
    met = stream.meet(read().where("event_type = 'click'"), read().where("event_type = 'purchase'"), "user_id", "6 HOURS", "60 days")
    return stream.run_to_memory(met, f"met_{uuid.uuid4().hex}", "append")


def flagship(spark: SparkSession, sf_dir: str) -> DataFrame:
    """One row per method: errors, precision, recall, labels used, parameters and those not 0."""
    df = train(spark, sf_dir)
    models = fit_three(block_of(df)[()], folds=_folds(df))
    sizes = flagged(spark, [(m.method, *m.size()) for m in models], "method string, parameters int, nonzero int")
    labels = SIX.per_pair * SIX.sources * (SIX.sources - 1) // 2
    return _errors(spark, sf_dir, models).join(F.broadcast(sizes), "method").withColumn("labels", F.lit(labels))
