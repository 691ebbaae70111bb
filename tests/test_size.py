"""What lets queries grow: where rows go, how many pairs are tried."""

import __spark_entry__ as entry
from tests.conftest import TINY, values


def test_stream_scores_go_to_files(spark, duck):
    got = entry.queries()["w14_stream_scores"](spark, TINY)
    assert got.inputFiles()  # a table in the driver's memory has none
    want = duck(TINY).sql(entry.oracle_sql()["w14_stream_scores"]).df()
    assert values(got.collect(), ["event_id", "score"]) == values(want.to_dict("records"), ["event_id", "score"])


def _same(spark, duck, sf_dir, name, columns):
    got = entry.queries()[name](spark, sf_dir)
    want = duck(sf_dir).sql(entry.oracle_sql()[name]).df()
    assert values(got.collect(), columns) == values(want.to_dict("records"), columns)
    return got


def test_features_of_candidates_need_no_triples_of_all_documents(spark, duck, tmp_path):
    from pyspark.sql import functions as F

    d = spark.read.parquet(f"{TINY}/documents.parquet")
    lang = F.when(F.col("doc_id") % 3 > 0, F.col("lang"))
    d.withColumn("lang", lang).coalesce(1).write.parquet(str(tmp_path / "out"))
    next((tmp_path / "out").glob("*.parquet")).rename(tmp_path / "documents.parquet")
    got = _same(spark, duck, str(tmp_path), "w8_features", ["d1", "d2", "s1", "s2", "x1", "x2", "x3", "x4", "x5", "y"])
    assert "Generate" not in got._jdf.queryExecution().optimizedPlan().toString()  # of candidates only, from what was stored


def test_bit_maps_bound_what_two_sets_share():
    import numpy as np

    from offsetlink.operators import compare

    rng = np.random.default_rng(1)
    for n1, n2, both in [(1, 1, 0), (1, 1, 1), (5, 9, 4), (300, 500, 250), (400, 400, 0), (1000, 40, 40), (64, 65, 64)]:
        every = np.unique(rng.integers(0, 1 << 63, n1 + n2 - both, np.int64).astype(np.uint64))
        a, b = np.sort(every[:n1]), np.sort(every[n1 - both :])
        bound = compare.most_shared(len(a), compare.bit_map(a), len(b), compare.bit_map(b))
        assert both <= bound <= min(n1, n2)
        assert both or n1 < 100 or 3 * bound < n1 + n2  # far sets of some size are told apart without their texts


def test_range_pairs_meet_once_and_few_others(spark, duck):
    from pyspark.sql import functions as F

    from offsetlink.plans import relational

    _same(spark, duck, "/root/testdata/sf0.01", "rel_range_join", ["p1", "p2"])
    rows = spark.createDataFrame([(1, 0.0), (2, 5.0), (3, 5.0), (4, -5.0), (5, 10.1), (6, None), (7, -0.0), (8, 0.3)], "k long, x double")
    got = {tuple(r) for r in relational.range_pairs(rows, "k", "x", 5.0).collect()}
    x = {r.k: r.x for r in rows.collect() if r.x is not None}
    assert got == {(a, b) for a in x for b in x if a < b and abs(x[a] - x[b]) <= 5.0}
    # Of rows at steps of 1, a row meets its own bin and the nine above it: 0.5 + 9 bins for 8 bins of pairs.
    even = spark.range(4000).select(F.col("id").alias("k"), F.col("id").cast("double").alias("x"))
    assert relational.range_pairs(even, "k", "x", 400.0).count() == sum(min(400, 3999 - k) for k in range(4000))


def test_range_pairs_are_dealt_by_number_whatever_the_rows_weigh(spark, duck):
    got = _same(spark, duck, "/root/testdata/sf0.01", "rel_range_join", ["p1", "p2"])
    assert "Join" not in got._jdf.queryExecution().optimizedPlan().toString()  # no pair is tried in vain
    # Few bytes of rows make many pairs: their partitions aren't merged into as many as rows fill.
    assert got.rdd.getNumPartitions() >= 8 * spark.sparkContext.defaultParallelism


def test_range_pairs_of_odd_rows(spark):
    import math
    import random

    from offsetlink.plans import relational

    draw = random.Random(3)
    odd = [0.0, -0.0, 5.0, -5.0, 4e-16, 1e-17, -1e-17, 900.1, 905.1, 905.1000000000001, 1e17, 1e17 + 16, math.nan, math.inf, -math.inf, None]
    rows = [(k, g, v) for k, (g, v) in enumerate((g, v) for g in ("a", "b", None) for v in odd + [round(draw.uniform(-20, 20), 1) for _ in range(40)])]
    rows += [(None, "a", 1.0), (0, "a", 3.0), (0, "b", 7.0)]  # a null key, a key that occurs in more rows
    got = sorted(map(tuple, relational.range_pairs(spark.createDataFrame(rows, "k long, g string, x double"), "k", "x", 5.0, ["g"]).collect()))
    whole = [r for r in rows if None not in r and math.isfinite(r[2])]
    assert got == sorted((min(a[0], b[0]), max(a[0], b[0])) for i, a in enumerate(whole) for b in whole[:i] if a[1] == b[1] and abs(a[2] - b[2]) <= 5.0)


def test_range_pairs_of_a_bin_go_out_in_batches(monkeypatch):
    import pyarrow as pa

    from offsetlink.plans import relational

    monkeypatch.setattr(relational, "PAIRS", 7)
    x = [0.0, 3.0, 1.0, 2.0, 2.0, 4.9, 6.0, 5.5, 0.0, 9.0]
    bins = [int(v // 5) for v in x]
    batch = pa.RecordBatch.from_arrays([pa.array(range(len(x))), pa.array(x), pa.array(bins), pa.array([0] * len(x))], names=["key_", "x_", "own_", "bin_"])
    out = list(relational._pairs_of_bin(5.0, ["k1", "k2"])(iter([batch[:4], batch[4:]])))
    assert all(b.num_rows == 7 for b in out[:-1]) and 0 < out[-1].num_rows <= 7
    got = [tuple(r.values()) for b in out for r in b.to_pylist()]
    assert sorted(got) == [(i, j) for i in range(len(x)) for j in range(i + 1, len(x)) if min(bins[i], bins[j]) == 0 and abs(x[i] - x[j]) <= 5.0]


def test_hashes_of_words_are_bounded(monkeypatch):
    import pyarrow as pa

    from offsetlink.operators import compare

    made = []
    monkeypatch.setattr(compare, "Hashes", type("Spy", (compare.Hashes,), {"__init__": lambda self: made.append(self)}))
    most = 0
    texts = [" ".join(f"w{k}x{i}" for i in range(1000)) for k in range(150)]
    batches = [pa.RecordBatch.from_arrays([pa.array([k]), pa.array([1]), pa.array(["en"]), pa.array([9]), pa.array([t])], names=["doc_id", "source", "lang", "n_chars", "text"]) for k, t in enumerate(texts)]
    for _ in compare._packed(iter(batches)):
        most = max(most, len(made[0]))
    assert 40_000 < most <= 60_000


def _without_triples_of_all(monkeypatch, spark, name):
    from offsetlink.workloads import catalogue

    def refused(*_):
        raise AssertionError("triples of all documents")

    monkeypatch.setattr(catalogue, "near_classes", refused)
    return entry.queries()[name](spark, "/root/testdata/sf0.01").collect()


def test_homogeneous_sources_label_candidates_only(spark, monkeypatch):
    assert {r.method for r in _without_triples_of_all(monkeypatch, spark, "w11_homogeneous")} == {"pooled", "offset"}


def test_six_way_curves_label_candidates_only(spark, monkeypatch):
    assert {r.method for r in _without_triples_of_all(monkeypatch, spark, "w1_documents")} == {"pooled", "offset"}
