"""Jobs done whole: no cap on frequencies, groups or sizes."""

import pytest
from pyspark.sql import functions as F

import __spark_entry__ as entry

SMALL = "/root/testdata/sf0.01"


def components(edges):
    least = {}

    def find(x):
        while least.setdefault(x, x) != x:
            x = least[x]
        return x

    for a, b in edges:
        a, b = sorted((find(a), find(b)))
        least[b] = a
    return {x: find(x) for x in list(least)}


def test_n16_title_clusters_equal_brute_force(spark):
    from offsetlink.operators import blocking, resolve
    from offsetlink.sources import tables
    from offsetlink.workloads import catalogue

    records = tables.document_records(catalogue.documents(spark, SMALL)).select("doc_id", "source_id", "title_tokens").cache()
    rows = [(r.doc_id, r.source_id, frozenset(r.title_tokens)) for r in records.collect()]
    stop = set(blocking.STOP)
    edges = [(d, e) for d, s, v in rows for e, t, w in rows if d < e and s is not None and t is not None and s != t and (v & w) - stop and len(v & w) >= 0.5 * len(v | w)]
    got = {r.record: r.cluster for r in resolve.cluster_by_words(records, "title_tokens").collect()}
    assert got == components(edges)


def test_n16_merges_groups_of_common_titles(spark, tmp_path):
    rows = [(i, "alpha beta gamma.", "en", f"s{i % 5}", 17) for i in range(60)] + [(100, "delta.", "en", "s1", 6)]
    spark.createDataFrame(rows, "doc_id long, text string, lang string, source string, n_chars long").write.parquet(str(tmp_path / "documents.parquet"))
    assert sorted(r.records for r in entry.queries()["n16_merge"](spark, str(tmp_path)).collect()) == [1, 60]


def test_w9_finds_passages_in_many_documents(spark, tmp_path):
    text = "several ordinary passages contain entirely familiar phrases"
    docs = [(i, f"{text} number{i:04d}", "en", f"s{i % 5}", 70) for i in range(40)] + [(90, "several ordinary passages", "en", "s1", 25), (91, None, "en", "s1", 0)]
    spark.createDataFrame(docs, "doc_id long, text string, lang string, source string, n_chars long").write.parquet(str(tmp_path / "documents.parquet"))
    spark.createDataFrame([(7, text), (8, "short of it"), (9, None)], "item_id long, text string").write.parquet(str(tmp_path / "benchmark.parquet"))
    got = entry.queries()["w9_master_match"](spark, str(tmp_path)).collect()
    assert sorted((r.item_id, r.doc_id, r.containment) for r in got) == [(7, i, 1.0) for i in range(40)]


def test_w9_equals_brute_force(spark):
    import re

    import pandas as pd

    words = lambda t: {w for w in re.split("[^a-z0-9]+", re.sub("[A-Z]", lambda m: m[0].lower(), t or "")) if len(w) >= 6}
    at = "/root/testdata/sf0.1"
    items = [(i, words(t)) for i, t in pd.read_parquet(f"{at}/benchmark.parquet")[["item_id", "text"]].itertuples(index=False)]
    docs = [(i, words(t)) for i, t in pd.read_parquet(f"{at}/documents.parquet")[["doc_id", "text"]].itertuples(index=False)]
    want = {(i, d) for d, v in docs for i, w in items if w and len(v & w) >= 0.6 * len(w)}
    got = [(r.item_id, r.doc_id) for r in entry.queries()["w9_master_match"](spark, at).collect()]
    assert len(got) == len(set(got)) and set(got) == want
