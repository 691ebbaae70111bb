"""Scans and sinks: tables, records from several sources, labels, scored pairs, models."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from offsetlink import schema
from offsetlink.functions import portable

#: Unequal sizes of six sources, as per-mille cuts in the proportions of the published inventory.
SIX_WAY = (451, 714, 835, 924, 989)


def load(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.schema(schema.TABLES[name]).parquet(f"{sf_dir}/{name}.parquet")


def load_records(spark: SparkSession, path: str, fmt: str = "parquet", ddl: str = schema.RECORD, **options) -> DataFrame:
    return spark.read.format(fmt).schema(ddl).options(**options).load(path)


def load_jdbc(spark: SparkSession, url: str, table: str, column: str, lower: int, upper: int, partitions: int, **properties) -> DataFrame:
    """A table of a database, read in ranges of a numeric column."""
    return spark.read.jdbc(url, table, column=column, lowerBound=lower, upperBound=upper, numPartitions=partitions, properties=properties)


def load_labels(spark: SparkSession, path: str, fmt: str = "csv") -> DataFrame:
    return load_records(spark, path, fmt, schema.LABEL)


def six_way(doc_id: Column) -> Column:
    """One of six sources of unequal size."""
    cut = portable.mix(doc_id, 17) % 1000
    out = F.lit(len(SIX_WAY) + 1)
    for m, top in reversed(list(enumerate(SIX_WAY, 1))):
        out = F.when(cut < top, F.lit(m)).otherwise(out)
    return out


def six_way_sql(doc_id: str) -> str:
    cut = f"({portable.mix_sql(doc_id, 17)} % 1000)"
    return "CASE " + " ".join(f"WHEN {cut} < {top} THEN {m}" for m, top in enumerate(SIX_WAY, 1)) + f" ELSE {len(SIX_WAY) + 1} END"


def document_records(documents: DataFrame) -> DataFrame:
    """Records of documents: title and body words, lines, length; the native source number."""
    folded = portable.ascii_fold(F.regexp_extract("text", r"^[^.|\n]*", 0))
    words = lambda c: F.array_distinct(F.filter(F.split(c, "[^a-z0-9]+"), lambda w: w != ""))
    return documents.select(
        "doc_id", F.regexp_extract("source", r"(\d+)$", 1).try_cast("int").alias("source_id"), folded.alias("title"), words(folded).alias("title_tokens"),
        words(portable.ascii_fold(F.col("text"))).alias("body_tokens"), "lang", "n_chars", F.size(F.split(F.coalesce("text", F.lit("")), "\n")).alias("n_lines"),
    )


def page_records(pages: DataFrame) -> DataFrame:
    """Title and host (the source) of crawled pages."""
    host = F.regexp_extract("url", r"^[a-z]+://(?:www\.)?([^/:?#]+)", 1)
    return pages.select("page_id", host.alias("host"), F.trim(F.regexp_extract("html", r"(?is)<title[^>]*>([^<]*)", 1)).alias("title"))


def write_scored(scored: DataFrame, path: str, partition_by: tuple[str, ...] = ("s1", "s2"), max_records: int = 5_000_000, salts: int = 16) -> None:
    """Scored pairs by source pair, sorted by score within files; a large source pair is written by several tasks."""
    salt = F.pmod(F.xxhash64(*scored.columns), F.lit(salts))
    scored.repartition(*partition_by, salt).sortWithinPartitions(*partition_by, F.desc("score")).write.option("maxRecordsPerFile", max_records).partitionBy(*partition_by).mode("overwrite").parquet(path)


def write_blocks(blocks: DataFrame, table: str, buckets: int) -> None:
    """A bucketed table of blocks, so that later joins on the key need no shuffle."""
    blocks.write.bucketBy(buckets, "block_key").sortBy("block_key").mode("overwrite").saveAsTable(table)
