"""Streams of labels: moments that grow with arrivals, late labels, and scores under the latest model."""

from __future__ import annotations

import uuid

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from offsetlink.operators import moments, resolve

EVENTS = "event_id long, ts timestamp, user_id long, event_type string, value double, props string"


def label_events(events: DataFrame, sources: int = 6) -> DataFrame:
    """Label arrivals of events: two sources by user and JSON counter, one feature, a label by parity of the counter."""
    k = F.get_json_object("props", "$.k").cast("int")
    s1 = (F.col("user_id") % sources + 1).cast("int")
    s2 = ((F.col("user_id") + F.coalesce(k, F.lit(0)) % (sources - 1) + 1) % sources + 1).cast("int")
    return events.select("event_id", "ts", s1.alias("s1"), s2.alias("s2"), F.floor(F.col("value") * 100).cast("long").alias("x1"), F.when(F.coalesce(k, F.lit(0)) % 2 == 0, 1).otherwise(-1).alias("y"))


def read_stream(spark: SparkSession, path: str, per_trigger: int = 1) -> DataFrame:
    return spark.readStream.schema(EVENTS).option("maxFilesPerTrigger", per_trigger).parquet(path)


def stream_moments(labels: DataFrame, features: list[str], delay: str | None = None, window: str | None = None) -> DataFrame:
    """Running moments by source pair; with a delay, labels sent twice within it count once; with a window, by time."""
    if delay:
        labels = labels.withWatermark("ts", delay).dropDuplicatesWithinWatermark(["event_id"])
    if window:
        labels = labels.withColumn("window", F.window("ts", window))
    return moments.pair_moments(labels, features, ["window"] if window else None, "long")


def run_to_memory(frame: DataFrame, name: str, mode: str = "complete", checkpoint: str | None = None) -> DataFrame:
    """Run a stream over all that is there now, into a table in memory."""
    writer = frame.writeStream.outputMode(mode).format("memory").queryName(name)
    query = (writer.option("checkpointLocation", checkpoint) if checkpoint else writer).start()
    query.processAllAvailable()
    query.stop()
    return frame.sparkSession.table(name)


def run_to_files(frame: DataFrame, name: str) -> DataFrame:
    """Run a stream that only appends over all that is there now, into files of the shared folder: its rows pass no driver."""
    spark = frame.sparkSession
    at = f"{resolve.shared_folder(spark)}/{name}-{uuid.uuid4().hex}"
    query = frame.writeStream.outputMode("append").format("parquet").option("path", f"{at}/rows").option("checkpointLocation", f"{at}/progress").trigger(availableNow=True).start()
    query.awaitTermination()
    return spark.read.schema(frame.schema).parquet(f"{at}/rows")


def throughput(labels: DataFrame, width: str = "1 day", slide: str | None = None) -> DataFrame:
    """Labels per window of event time."""
    w = F.window("ts", width, slide) if slide else F.window("ts", width)
    return labels.groupBy(w.alias("w")).agg(F.count("*").alias("labels")).select(F.col("w.start").alias("start"), "labels")


def sessions(labels: DataFrame, gap: str = "30 minutes", by: str = "s1") -> DataFrame:
    return labels.groupBy(F.session_window("ts", gap).alias("w"), by).agg(F.count("*").alias("labels")).select(by, F.col("w.start").alias("start"), F.col("w.end").alias("end"), "labels")


def score_stream(labels: DataFrame, models: list, features: list[str], scale: float = 1.0) -> DataFrame:
    """Arriving pairs scored under models that are broadcast; a static side, so no state."""
    from offsetlink.operators import scoring

    return scoring.score(labels, models, features, scale)


def meet(left: DataFrame, right: DataFrame, key: str, within: str = "1 hour", delay: str = "2 hours") -> DataFrame:
    """Records of two streams with the same block key within a time of one another; watermarks bound the state."""
    a = left.withWatermark("ts", delay).select(F.col(key), F.col("event_id").alias("e1"), F.col("ts").alias("t1"))
    b = right.withWatermark("ts", delay).select(F.col(key).alias("other_key"), F.col("event_id").alias("e2"), F.col("ts").alias("t2"))
    near = F.expr(f"{key} = other_key AND t2 BETWEEN t1 - INTERVAL {within} AND t1 + INTERVAL {within}")
    return a.join(b, near).select(key, "e1", "e2")
