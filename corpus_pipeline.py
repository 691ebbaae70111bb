"""The corpus pipeline: language ID, n-gram Jaccard join, benchmark decontamination, secret scans, piece encoding.

Each stage works on all that the one before kept, and takes (spark, docs, sf_dir).  run() writes each stage's result to
the shared folder and reads it again, so no stage is computed twice and lost executors cost one stage at most.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from offsetlink.llm import common, language_id, merge_dropout, secrets, shingle_join, winnowing

COLUMNS = ["doc_id", "text", "lang", "source", "n_chars"]


def _columns(docs: DataFrame) -> DataFrame:
    return docs.select(*(c for c in COLUMNS if c in docs.columns))


def identify_languages(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Drop documents without a language: null text, no letter.  lang becomes the predicted one; learned from docs."""
    trees = language_id.fit(language_id.training_rows(docs))
    return _columns(language_id.assign(docs, trees)).where(F.col("lang") != "und")


def join_near_copies(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Keep one row of each group of near copies, the one with the least doc_id; ids may repeat or be null."""
    return shingle_join.keep_one(_columns(docs))


def decontaminate(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Drop documents whose text the contamination rule marks; other rows with their doc_id, or without one, stay."""
    return winnowing.clean(_columns(docs), common.read(spark, sf_dir, "benchmark"))


def mask_secrets(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Replace secrets in texts by a mask, and set n_chars to the new length; no document goes."""
    return _columns(secrets.redact(secrets.scan(_columns(docs)))).withColumn("n_chars", F.length("text").cast("long"))


def encode_pieces(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Piece ids of every text under merge-dropout, checked by decoding; a row for each row, nulls where the text is null."""
    done = merge_dropout.round_trip(docs)
    return done.select("doc_id", "piece_ids", F.when(F.col("piece_ids").isNotNull(), F.size("piece_ids")).cast("long").alias("n_pieces"), F.sha2("text", 256).alias("text_sha256"), F.col("text").eqNullSafe(F.col("decoded")).alias("lossless"))


STAGES = [
    ("language_id", identify_languages),
    ("shingle_join", join_near_copies),
    ("winnowing", decontaminate),
    ("secrets", mask_secrets),
    ("merge_dropout", encode_pieces),
]
# Language ID and piece encoding aren't SQL; tests compare the stages with brute force.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = common.read(spark, sf_dir, "documents")
    before = []
    for name, stage in STAGES:
        docs = common.cut(stage(spark, docs, sf_dir), f"pipeline-{name}")
        common.drop(*before)
        before = [docs]
    return docs
