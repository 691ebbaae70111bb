"""Plans that Spark has no single operator for."""

from __future__ import annotations

import re
from collections.abc import Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

#: Partitions of pairs for each core at least; pairs in a batch.
DEALT, PAIRS = 8, 1 << 16


def range_bin_join(a: DataFrame, b: DataFrame, x: str, y: str, width: float, keys: list[str] | None = None) -> DataFrame:
    """Rows of a and b with |x - y| <= width: an equi-join on bins, with one side in three neighbouring bins."""
    left = a.withColumn("bin_", F.floor(F.col(x) / width))
    right = b.withColumn("bin_", F.explode(F.array(*(F.floor(F.col(y) / width) + k for k in (-1, 0, 1)))))
    return left.join(right, ["bin_", *(keys or [])]).where(F.abs(F.col(x) - F.col(y)) <= width).drop("bin_")


def range_pairs(rows: DataFrame, key: str, x: str, width: float, keys: list[str] | None = None, parts: int = 4) -> DataFrame:
    """Pairs of rows of one table with |x - x'| <= width and equal keys, each once: the lesser key as key_1, the other as key_2.

    Bins are a part of the width, and a row goes to its own bin and those below from where it can be met.  In a bin sorted
    by x the partners of a row follow it, up to an end found by bisection: no pair is tried in vain.  As pairs are many more
    than rows, bins are dealt by number, not by bytes of rows.  x is taken as a double; null, NaN and infinities meet nothing.
    """
    keys = keys or []
    session, kind = rows.sparkSession, rows.schema[key].dataType.simpleString()
    at = rows.select(*keys, F.col(key).alias("key_"), F.col(x).cast("double").alias("x_")).where(F.abs("x_") < float("inf")).dropna(subset=[*keys, "key_"])
    own = at.withColumn("own_", F.floor(F.col("x_") / (width / parts)))
    # A bin more than the width has, against rounding where bins are cut.
    met = own.select("*", F.explode(F.array(*(F.col("own_") - k for k in range(parts + 2)))).alias("bin_"))
    n = max(int(session.conf.get("spark.sql.shuffle.partitions")), DEALT * session.sparkContext.defaultParallelism)
    return met.repartition(n, *keys, "bin_").groupBy(*keys, "bin_").applyInArrow(_pairs_of_bin(width, [f"{key}_1", f"{key}_2"]), f"`{key}_1` {kind}, `{key}_2` {kind}")


def _pairs_of_bin(width: float, names: list[str]):
    def pairs(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        t = pa.Table.from_batches(batches)
        x = t.column("x_").to_numpy()
        order = np.argsort(x, kind="stable")
        x, key = x[order], t.column("key_").to_numpy()[order]
        # A bin's own rows are before those of bins above.
        i = np.arange(pc.sum(pc.equal(t.column("own_"), t.column("bin_"))).as_py())
        low, high = i + 1, np.full(len(i), len(x))
        while (some := np.flatnonzero(low < high)).size:
            middle = (low[some] + high[some]) // 2
            near = np.abs(x[some] - x[middle]) <= width
            low[some[near]], high[some[~near]] = middle[near] + 1, middle[~near]
        count = low - i - 1
        ends = np.cumsum(count)
        total = int(ends[-1]) if len(ends) else 0
        for begin in range(0, total, PAIRS):
            end = min(begin + PAIRS, total)
            a, b = np.searchsorted(ends, (begin, end - 1), "right")
            c, first = count[a : b + 1].copy(), i[a : b + 1] + 1
            done = begin - (ends[a] - count[a])  # pairs of row a that were made before
            c[0] -= done
            first[0] += done
            c[-1] -= ends[b] - end
            one, two = np.repeat(key[a : b + 1], c), key.take(np.arange(end - begin) + np.repeat(first - (np.cumsum(c) - c), c))
            yield pa.RecordBatch.from_arrays([pa.array(np.minimum(one, two)), pa.array(np.maximum(one, two))], names=names)

    return pairs


def asof_join(events: DataFrame, versions: DataFrame, key: str, time: str, value: str) -> DataFrame:
    """events with the latest version's value at their time, by one sorted pass over the union of both."""
    v = versions.select(key, time, F.lit(0).alias("kind_"), F.struct(F.col(value)).alias("new_"))
    e = events.withColumn("row_", F.struct(*events.columns))
    left = v.select(key, time, "kind_", "new_", F.lit(None).cast(e.schema["row_"].dataType).alias("row_"))
    right = e.select(key, time, F.lit(1).alias("kind_"), F.lit(None).cast(v.schema["new_"].dataType).alias("new_"), "row_")
    w = Window.partitionBy(key).orderBy(time, "kind_").rowsBetween(Window.unboundedPreceding, 0)
    both = left.unionByName(right).withColumn("known_", F.last("new_", True).over(w))
    return both.where("kind_ = 1").select("row_.*", F.col(f"known_.{value}").alias(value))


def top_k(df: DataFrame, keys: list[str], order: list, k: int) -> DataFrame:
    return df.withColumn("rank_", F.row_number().over(Window.partitionBy(*keys).orderBy(*order))).where(F.col("rank_") <= k).drop("rank_")


def sql_functions(spark) -> None:
    """Session functions that Catalyst inlines."""
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION soft_threshold(v DOUBLE, tau DOUBLE) RETURNS DOUBLE RETURN signum(v) * greatest(abs(v) - tau, 0.0D)")
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION jaccard(a ARRAY<STRING>, b ARRAY<STRING>) RETURNS DOUBLE RETURN try_divide(size(array_intersect(a, b)), size(array_union(a, b)))")


def token_blocks():
    """A table function from a title to its block keys; explode over an expression is the faster form."""

    @F.udtf(returnType="block_key: string")
    class TokenBlocks:
        def eval(self, title: str):
            for word in sorted(set(re.findall("[a-z0-9]+", (title or "").lower()))):
                yield (word,)

    return TokenBlocks


def grouped_gram():
    """The sum of products as a grouped-aggregate function; a check of the plain sums."""
    @F.pandas_udf("double")
    def gram(a: pd.Series, b: pd.Series) -> float:
        return float((a.astype(float) * b.astype(float)).sum())

    return gram


def range_bins(rows: DataFrame, column: str, bins: int = 64) -> Column:
    """The number of a row's range of a numeric column, rising: ranges of about equal rows, from approximate quantiles."""
    quantiles = [k / bins for k in range(1, bins)]
    edges = rows.agg(F.percentile_approx(column, quantiles, 1000)).first()[0] or []
    return F.size(F.filter(F.array(*(F.lit(float(e)) for e in sorted(set(edges)))).cast("array<double>"), lambda e: e < F.col(column)))


def row_numbers(rows: DataFrame, order: list[str], name: str = "row_number", bins: int = 64) -> DataFrame:
    """Numbers from 1 over all rows in a total order that begins with a numeric column, without one task that sorts them all.

    Rows are numbered within ranges of the first column, and a range starts where the counts of those before end.
    """
    binned = rows.withColumn("range_", range_bins(rows, order[0], bins))
    counts = binned.groupBy("range_").agg(F.count("*").alias("size_"))
    before = F.coalesce(F.sum("size_").over(Window.orderBy("range_").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0))
    starts = counts.select("range_", before.alias("before_"))
    inside = F.row_number().over(Window.partitionBy("range_").orderBy(*order))
    return binned.withColumn("inside_", inside).join(starts, "range_").withColumn(name, F.col("before_") + F.col("inside_")).drop("range_", "inside_", "before_")


def tiles(rows: DataFrame, order: list[str], n: int, name: str = "tile") -> DataFrame:
    """What ntile(n) gives over all rows: the first tiles have one row more where rows don't divide evenly."""
    count = rows.count()
    small, longer = divmod(count, n)
    at, head = F.col(name) - 1, longer * (small + 1)
    tile = F.when(at < head, F.floor(at / (small + 1))).otherwise(longer + F.floor((at - head) / max(small, 1))) + 1
    return row_numbers(rows, order, name).withColumn(name, tile.cast("int"))
