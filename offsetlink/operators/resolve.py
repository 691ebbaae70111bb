"""From scored pairs to entities: thresholds, clusters, best matches, merged records."""

from __future__ import annotations

import atexit
import shutil
import tempfile
import uuid

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from offsetlink.operators import blocking


def resolve(scored: DataFrame, tau: float = 0.0) -> DataFrame:
    return scored.where(F.col("score") >= tau)


def shared_folder(spark: SparkSession) -> str:
    """Checkpoints go to spark.checkpoint.dir; to a temporary folder only where that is unset and there is one machine."""
    sc = spark.sparkContext
    if sc._jsc.sc().getCheckpointDir().isDefined():
        return sc._jsc.sc().getCheckpointDir().get()
    at = spark.conf.get("spark.checkpoint.dir", None) or sc.getConf().get("spark.checkpoint.dir")
    if not at:
        if not sc.master.startswith("local") or sc.master.startswith("local-cluster"):
            raise ValueError("spark.checkpoint.dir must name a folder that driver and executors share")
        at = tempfile.mkdtemp(prefix="offsetlink-")
        atexit.register(shutil.rmtree, at, ignore_errors=True)
    sc.setCheckpointDir(at)
    return sc._jsc.sc().getCheckpointDir().get()


def stored(df: DataFrame, name: str) -> DataFrame:
    """Computed once, into compressed files of the shared folder."""
    at = f"{shared_folder(df.sparkSession)}/{name}-{uuid.uuid4().hex}"
    df.write.parquet(at)
    return df.sparkSession.read.schema(df.schema).parquet(at)


def cluster(matches: DataFrame, rounds: int = 50) -> DataFrame:
    """record and cluster (its least record), by labels that flow along matches and jump; cut by checkpoints.

    Raises if labels still move after so many rounds.
    """
    shared_folder(matches.sparkSession)
    e = matches.select(F.col("d1").alias("a"), F.col("d2").alias("b"))
    e = e.unionByName(e.select(F.col("b").alias("a"), F.col("a").alias("b"))).distinct().checkpoint()
    labels = e.groupBy(F.col("a").alias("record")).agg(F.min("b").alias("low")).select("record", F.least("record", "low").alias("cluster")).checkpoint()
    before = None
    for _ in range(rounds):
        sent = e.join(labels, e["a"] == labels["record"]).select(F.col("b").alias("record"), "cluster")
        pushed = labels.unionByName(sent).groupBy("record").agg(F.min("cluster").alias("cluster"))
        further = pushed.select(F.col("record").alias("cluster"), F.col("cluster").alias("further"))
        labels = pushed.join(further, "cluster").select("record", F.col("further").alias("cluster")).checkpoint()
        total = labels.agg(F.sum(F.col("cluster").cast("decimal(38,0)"))).first()[0]
        if total == before:
            return labels
        before = total
    raise RuntimeError(f"clusters still change after {rounds} rounds")


def cluster_by_words(records: DataFrame, column: str, tau: float = 0.5, key: str = "doc_id", source: str = "source_id") -> DataFrame:
    """What cluster gives on all pairs of records of different sources whose word sets are alike, without those pairs.

    Records with equal sets stand behind one set.  A set with records of two sources or more is connected in itself; two
    alike sets are connected unless all records of both are of one source.
    """
    held = records.where(F.col(source).isNotNull()).select(key, source, F.array_sort(F.array_distinct(column)).alias("ws")).withColumn("text_", F.array_join("ws", " "))
    words = F.size(F.array_except("ws", F.array(*map(F.lit, blocking.STOP)))) > 0
    sets = held.where(words).groupBy("text_").agg(F.first("ws").alias("ws"), F.min(key).alias("least"), F.min(source).alias("from"), F.max(source).alias("to"))
    pairs = blocking.similar_sets(sets, "text_", "ws", tau)
    named = lambda k: sets.select(F.col("text_").alias(f"k{k}"), F.col("least").alias(f"d{k}"), F.col("from").alias(f"from{k}"), F.col("to").alias(f"to{k}"))
    one = (F.col("from1") == F.col("to1")) & (F.col("from2") == F.col("to2")) & (F.col("from1") == F.col("from2"))
    labels = cluster(pairs.join(named(1), "k1").join(named(2), "k2").where(~one).select("d1", "d2")).withColumnRenamed("record", "least")
    found = sets.join(labels, "least", "left").where(F.col("cluster").isNotNull() | (F.col("from") < F.col("to")))
    return held.join(found.select("text_", F.coalesce("cluster", "least").alias("cluster")), "text_").select(F.col(key).alias("record"), "cluster")


def best_match(scored: DataFrame, record: str = "d1") -> DataFrame:
    """The best-scored partner of each record; ties go to the lesser partner."""
    w = Window.partitionBy(record).orderBy(F.desc("score"), "d2")
    return scored.withColumn("rank_", F.row_number().over(w)).where("rank_ = 1").drop("rank_")


def one_per_source(scored: DataFrame) -> DataFrame:
    """Pairs that are each other's best within their two sources."""
    left = Window.partitionBy("d1", "s2").orderBy(F.desc("score"), "d2")
    right = Window.partitionBy("d2", "s1").orderBy(F.desc("score"), "d1")
    both = scored.withColumns({"l_": F.row_number().over(left), "r_": F.row_number().over(right)})
    return both.where("l_ = 1 and r_ = 1").drop("l_", "r_")


def merge_records(records: DataFrame, clusters: DataFrame, key: str = "doc_id") -> DataFrame:
    """One row per cluster: longest title, most usual language, all sources, size; unmatched records stay alone."""
    named = records.join(clusters.select(F.col("record").alias(key), "cluster"), key, "left").withColumn("cluster", F.coalesce("cluster", key))
    return named.groupBy("cluster").agg(
        F.count("*").alias("records"), F.max(F.struct(F.length("title").alias("n"), F.col("title")))["title"].alias("title"),
        F.min_by("lang", key).alias("lang"), F.array_join(F.array_sort(F.collect_set("source_id")), ",").alias("sources"),
    )
