"""Blocking: records meet only where they share a rare token, across sources, and each pair once."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

#: A few very common words that never block, beside what document frequency excludes.
STOP = ("the", "and", "of", "a", "to", "in", "is", "de", "la", "der", "die", "und", "el", "les")


def tokens(text: Column, stop: tuple[str, ...] = STOP) -> Column:
    """Distinct lower-case words of letters and digits, without stop words."""
    words = F.filter(F.split(F.lower(text), "[^a-z0-9]+"), lambda w: w != "")
    return F.array_except(F.array_distinct(words), F.array(*map(F.lit, stop)))


def token_frequency(records: DataFrame, column: str) -> DataFrame:
    """Number of records that hold each token of an array column."""
    return records.select(F.explode(F.array_distinct(column)).alias("token")).groupBy("token").agg(F.count("*").alias("df"))


def record_keys(records: DataFrame, column: str, max_df: int, key: str = "doc_id") -> DataFrame:
    """Each record's tokens of at most max_df records (key, keys), sorted by rarity, then token; records without any are left out."""
    held = records.select(key, F.explode(F.array_distinct(column)).alias("token"))
    rare = token_frequency(records, column).where((F.col("df") <= max_df) & (F.col("df") > 1))
    return held.join(rare, "token").groupBy(key).agg(F.array_sort(F.collect_list(F.struct("df", "token"))).alias("keys"))


def rare_keys(records: DataFrame, column: str, max_df: int, key: str = "doc_id", source: str = "source_id") -> DataFrame:
    """Block rows (block_key, key, source, df, keys): tokens of at most max_df records, each with the record's rare tokens.

    keys is sorted by rarity, then token, so that the first shared key of two records is the same from either side.
    """
    held = records.select(key, source, F.explode(F.array_distinct(column)).alias("token"))
    rare = token_frequency(records, column).where((F.col("df") <= max_df) & (F.col("df") > 1))
    kept = held.join(rare, "token")
    keys = kept.groupBy(key).agg(F.array_sort(F.collect_list(F.struct("df", "token"))).alias("keys"))
    return kept.join(keys, key).select(F.col("token").alias("block_key"), key, source, "df", "keys")


def candidates(blocks: DataFrame, key: str = "doc_id", source: str = "source_id") -> DataFrame:
    """Pairs of records of different sources that share a block; each once, from their first shared key.

    The check of the first shared key replaces a distinct over all pairs and its shuffle.
    """
    a = blocks.select("block_key", "df", F.col(key).alias("d1"), F.col(source).alias("s1"), F.col("keys").alias("k1"))
    b = blocks.select("block_key", F.col(key).alias("d2"), F.col(source).alias("s2"), F.col("keys").alias("k2"))
    first = F.array_min(F.array_intersect("k1", "k2"))
    pairs = a.join(b, "block_key").where((F.col("s1") != F.col("s2")) & (F.col("d1") < F.col("d2")))
    return pairs.where(first == F.struct("df", F.col("block_key").alias("token"))).select("d1", "d2", "s1", "s2")


def candidates_by_distinct(blocks: DataFrame, key: str = "doc_id", source: str = "source_id") -> DataFrame:
    """The same pairs by a distinct; kept to compare."""
    a = blocks.select("block_key", F.col(key).alias("d1"), F.col(source).alias("s1"))
    b = blocks.select("block_key", F.col(key).alias("d2"), F.col(source).alias("s2"))
    return a.join(b, "block_key").where((F.col("s1") != F.col("s2")) & (F.col("d1") < F.col("d2"))).select("d1", "d2", "s1", "s2").distinct()


def block_sizes(blocks: DataFrame) -> DataFrame:
    return blocks.groupBy("block_key").agg(F.count("*").alias("size")).groupBy("size").agg(F.count("*").alias("blocks"), (F.count("*") * F.col("size") * (F.col("size") - 1) / 2).cast("long").alias("pairs"))


def refine(blocks: DataFrame, second: Column, most: int) -> DataFrame:
    """Blocks of more than most rows get a second key, so that only records that share both meet."""
    sizes = blocks.groupBy("block_key").agg(F.count("*").alias("size"))
    key = F.when(F.col("size") > most, F.concat_ws("|", "block_key", second)).otherwise(F.col("block_key"))
    return blocks.join(sizes, "block_key").withColumn("block_key", key).drop("size")


def similar_sets(sets: DataFrame, key: str, column: str, tau: float = 0.5, stop: tuple[str, ...] = STOP) -> DataFrame:
    """Pairs (k1, k2) of different sets of Jaccard at least tau that share a word that is no stop word; each pair once.

    Exact, with words of any frequency: the lesser set (by size, then key) is indexed by its rarest words, as many as it
    can lack of the overlap with a set of its size, the other asks with as many as it can lack of tau of its own.
    """
    words = sets.select(key, F.explode(column).alias("w"))
    df = words.groupBy("w").agg(F.count("*").alias("df"))
    ranked = words.join(df, "w").groupBy(key).agg(F.transform(F.array_sort(F.collect_list(F.struct("df", "w"))), lambda x: x["w"]).alias("ws")).withColumn("n", F.size("ws"))
    # A thousandth of a word against rounding errors; a longer prefix is always right.
    prefix = lambda share: F.explode(F.slice("ws", F.lit(1), F.col("n") - F.ceil(F.col("n") * share - 1e-3).cast("int") + 1)).alias("w")
    side = lambda k, share: ranked.select(F.col(key).alias(f"k{k}"), F.col("ws").alias(f"ws{k}"), F.col("n").alias(f"n{k}"), prefix(share))
    met = side(1, 2 * tau / (1 + tau)).join(side(2, tau), "w").where((F.struct("n1", "k1") < F.struct("n2", "k2")) & (F.col("n1") >= tau * F.col("n2") - 1e-3))
    met = met.withColumn("both", F.array_intersect("ws1", "ws2")).where(F.get("both", F.lit(0)) == F.col("w"))
    alike = F.size("both") / (F.col("n1") + F.col("n2") - F.size("both")) >= tau
    return met.where(alike & (F.size(F.array_except("both", F.array(*map(F.lit, stop)))) > 0)).select("k1", "k2")


def salted_self_join(blocks: DataFrame, salts: int, key: str = "doc_id", source: str = "source_id") -> DataFrame:
    """The self-join with one side dealt into salts and the other repeated for each, so that a hot block is split."""
    a = blocks.select("block_key", F.col(key).alias("d1"), F.col(source).alias("s1"), F.pmod(F.xxhash64(key), F.lit(salts)).alias("salt"))
    b = blocks.select("block_key", F.col(key).alias("d2"), F.col(source).alias("s2"), F.explode(F.sequence(F.lit(0).cast("long"), F.lit(salts - 1).cast("long"))).alias("salt"))
    return a.join(b, ["block_key", "salt"]).where((F.col("s1") != F.col("s2")) & (F.col("d1") < F.col("d2"))).select("d1", "d2", "s1", "s2").distinct()
