"""Scans and sinks read back what was written."""

from pyspark.sql import functions as F

from offsetlink import schema
from offsetlink.functions import similarity
from offsetlink.sources import tables


def test_records_and_labels(spark, tmp_path):
    rows = [(1, 2, "a title", ["other"], 1999, 100, ["x", "y"], None), (2, 3, None, None, None, None, [], ["z"])]
    df = spark.createDataFrame(rows, schema.RECORD)
    df.write.parquet(str(tmp_path / "r"))
    assert sorted(map(tuple, tables.load_records(spark, str(tmp_path / "r")).collect()), key=lambda r: r[0]) == rows
    df.write.json(str(tmp_path / "j"))
    assert tables.load_records(spark, str(tmp_path / "j"), "json").where("title is null").first().rec_id == 2
    spark.createDataFrame([(1, 2, 3, 4, 1), (5, 6, 7, 8, -1)], schema.LABEL).write.csv(str(tmp_path / "l"))
    assert sorted(map(tuple, tables.load_labels(spark, str(tmp_path / "l")).collect())) == [(1, 2, 3, 4, 1), (5, 6, 7, 8, -1)]


def test_scored_pairs_by_source_pair(spark, tmp_path):
    df = spark.range(3000).select((F.col("id") % 2 + 1).cast("int").alias("s1"), F.lit(5).alias("s2"), F.col("id").alias("d1"), (F.col("id") * 7919 % 1000 / 1000).alias("score"))
    spark.conf.set("spark.sql.adaptive.coalescePartitions.enabled", "false")
    try:
        tables.write_scored(df, str(tmp_path / "s"), salts=4)
    finally:
        spark.conf.unset("spark.sql.adaptive.coalescePartitions.enabled")
    back = spark.read.parquet(str(tmp_path / "s"))
    assert back.count() == 3000 and back.select("d1").distinct().count() == 3000
    assert sorted(p.name for p in (tmp_path / "s").glob("s1=*")) == ["s1=1", "s1=2"]
    files = list((tmp_path / "s" / "s1=1" / "s2=5").glob("*.parquet"))
    assert len(files) > 1  # no single task writes a large source pair
    scores = [r.score for r in spark.read.parquet(str(files[0])).collect()]
    assert scores == sorted(scores, reverse=True)


def test_blocks_in_buckets(spark, tmp_path):
    blocks = spark.createDataFrame([("a", 1, 2), ("b", 2, 3), ("a", 3, 4)], "block_key string, doc_id long, source_id int")
    spark.sql(f"CREATE DATABASE IF NOT EXISTS offsetlink_tests LOCATION '{tmp_path / 'db'}'")
    try:
        tables.write_blocks(blocks, "offsetlink_tests.blocks", 4)
        back = spark.table("offsetlink_tests.blocks")
        assert back.count() == 3
        plan = back.groupBy("block_key").count()._jdf.queryExecution().executedPlan().toString()
        assert "Exchange hashpartitioning(block_key" not in plan
    finally:
        spark.sql("DROP DATABASE offsetlink_tests CASCADE")


def test_missing_features(spark):
    df = spark.createDataFrame([(1.0, None), (None, 4.0), (3.0, 2.0)], "x double, y double")
    filled = similarity.fill_missing({"x": F.col("x"), "y": F.col("y")}, "worst", {"x": 0.0, "y": 9.0})
    got = df.select(*(c.alias(k) for k, c in filled.items())).collect()
    assert {(r.x, r.y) for r in got} == {(1.0, 9.0), (0.0, 4.0), (3.0, 2.0)}
