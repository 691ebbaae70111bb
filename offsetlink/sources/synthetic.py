"""Synthetic multi-source data on the part table: latent entities, noisy records per source, labelled pairs.

Every value is an expression over md5 of its place, with a SQL twin, so a pair's features don't depend on partitions.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition

from offsetlink.functions import portable as P


@dataclass(frozen=True)
class Design:
    """What a synthetic workload looks like.  sigma is clean or noisy by source and attribute."""

    sources: int = 6
    dims: int = 5
    per_pair: int = 40
    trials: int = 1
    role: str = "train"
    clean: float = 0.04
    noisy: float = 0.4
    noisy_tenths: int = 3
    match_every: int = 2
    mode: str = "abs"

    @property
    def features(self) -> list[str]:
        return [f"x{m}" for m in range(1, self.dims + 1)]


def latent(part: DataFrame, dims: int) -> DataFrame:
    """Attributes uniform in the unit interval for each part."""
    return part.select(F.col("p_partkey").alias("entity_id"), *(P.uniform("e", F.col("p_partkey"), F.lit(m)).alias(f"a{m}") for m in range(1, dims + 1)))


def latent_sql(dims: int) -> str:
    cols = ", ".join(f"{P.uniform_sql(chr(39) + 'e' + chr(39), 'p_partkey', str(m))} AS a{m}" for m in range(1, dims + 1))
    return f"SELECT p_partkey AS entity_id, {cols} FROM part"


def _sigma(d: Design, s, m):
    return F.when(P.u32("p", s, F.lit(m)) % 10 < d.noisy_tenths, F.lit(d.noisy)).otherwise(F.lit(d.clean))


def _sigma_sql(d: Design, s: str, m: int) -> str:
    return f"(CASE WHEN {P.u32_sql(chr(39) + 'p' + chr(39), s, str(m))} % 10 < {d.noisy_tenths} THEN {d.noisy}::DOUBLE ELSE {d.clean}::DOUBLE END)"


def source_records(entities: DataFrame, d: Design) -> DataFrame:
    """Each entity as each source sees it; the small side is the range of sources."""
    sources = entities.sparkSession.range(1, d.sources + 1).select(F.col("id").cast("int").alias("source_id"))
    seen = entities.crossJoin(F.broadcast(sources))
    noisy = lambda m: F.round(F.col(f"a{m}") + _sigma(d, F.col("source_id"), m) * P.normal(F.col("entity_id"), F.col("source_id"), F.lit(m)), 6)
    return seen.select("entity_id", "source_id", *(noisy(m).alias(f"b{m}") for m in range(1, d.dims + 1)))


def source_records_sql(d: Design) -> str:
    cols = ", ".join(f"round(a{m} + {_sigma_sql(d, 'source_id', m)} * {P.normal_sql('entity_id', 'source_id', str(m))}, 6) AS b{m}" for m in range(1, d.dims + 1))
    return f"SELECT entity_id, source_id, {cols} FROM ({latent_sql(d.dims)}) CROSS JOIN (SELECT CAST(range AS INTEGER) AS source_id FROM range(1, {d.sources + 1}))"


def pair_keys(spark: SparkSession, parts: int, d: Design) -> DataFrame:
    """Which entities each labelled pair of each source pair compares; train and test entities differ in parity."""
    half, odd = parts // 2, 1 if d.role == "train" else 2
    s = spark.range(1, d.sources + 1)
    pairs = s.select(F.col("id").cast("int").alias("s1")).crossJoin(s.select(F.col("id").cast("int").alias("s2"))).where("s1 < s2")
    grid = spark.range(d.per_pair * d.trials).select((F.col("id") % d.per_pair).cast("int").alias("r"), F.floor(F.col("id") / d.per_pair).cast("int").alias("trial"))
    place = (F.lit(d.role), F.col("s1"), F.col("s2"), F.col("r"), F.col("trial"))
    anchor, shift = P.u32("anchor", *place) % half, P.u32("shift", *place) % (half - 1) + 1
    match = F.col("r") % d.match_every == 0
    keyed = grid.crossJoin(F.broadcast(pairs)).select("s1", "s2", "r", "trial", anchor.alias("h1"), F.when(match, anchor).otherwise((anchor + shift) % half).alias("h2"), F.when(match, 1).otherwise(-1).alias("y"))
    return keyed.select("s1", "s2", "r", "trial", (2 * F.col("h1") + odd).alias("e1"), (2 * F.col("h2") + odd).alias("e2"), "y")


def pair_keys_sql(d: Design) -> str:
    odd = 1 if d.role == "train" else 2
    place = (f"'{d.role}'", "s1", "s2", "r", "trial")
    a, b = P.u32_sql("'anchor'", *place), P.u32_sql("'shift'", *place)
    return f"""SELECT s1, s2, r, trial, 2 * h1 + {odd} AS e1, 2 * (CASE WHEN r % {d.match_every} = 0 THEN h1 ELSE (h1 + step) % half END) + {odd} AS e2, CASE WHEN r % {d.match_every} = 0 THEN 1 ELSE -1 END AS y
      FROM (SELECT s1, s2, r, trial, half, {a} % half AS h1, {b} % (half - 1) + 1 AS step
        FROM (SELECT CAST(range AS INTEGER) AS s1 FROM range(1, {d.sources + 1})) CROSS JOIN (SELECT CAST(range AS INTEGER) AS s2 FROM range(1, {d.sources + 1}))
        CROSS JOIN (SELECT CAST(range AS INTEGER) AS r FROM range({d.per_pair})) CROSS JOIN (SELECT CAST(range AS INTEGER) AS trial FROM range({d.trials}))
        CROSS JOIN (SELECT count(*) // 2 AS half FROM part) WHERE s1 < s2)"""


def synthetic_pairs(part: DataFrame, d: Design, where: Column | None = None) -> DataFrame:
    """s1, s2, r, trial, e1, e2, y and features x1..xd: attribute differences in ten-thousandths (long).

    where picks pairs by s1, s2, r and trial before their records are made.
    """
    parts = part.count()
    keys = pair_keys(part.sparkSession, parts, d)
    keys = keys if where is None else keys.where(where)
    entities = latent(part, d.dims)
    one = entities.select(F.col("entity_id").alias("e1"), *(F.col(f"a{m}").alias(f"p{m}") for m in range(1, d.dims + 1)))
    two = entities.select(F.col("entity_id").alias("e2"), *(F.col(f"a{m}").alias(f"q{m}") for m in range(1, d.dims + 1)))
    joined = keys.join(one, "e1").join(two, "e2")

    def feature(m: int):
        left = F.col(f"p{m}") + _sigma(d, F.col("s1"), m) * P.normal(F.col("e1"), F.col("s1"), F.lit(m))
        right = F.col(f"q{m}") + _sigma(d, F.col("s2"), m) * P.normal(F.col("e2"), F.col("s2"), F.lit(m))
        diff = left - right
        diff = F.abs(diff) if d.mode == "abs" else diff * diff if d.mode == "sq" else diff
        return F.round(diff * P.FIXED).cast("long").alias(f"x{m}")

    return joined.select("s1", "s2", "r", "trial", "e1", "e2", "y", *map(feature, range(1, d.dims + 1)))


def synthetic_pairs_sql(d: Design) -> str:
    def feature(m: int) -> str:
        left = f"(u.a{m} + {_sigma_sql(d, 'k.s1', m)} * {P.normal_sql('k.e1', 'k.s1', str(m))})"
        right = f"(v.a{m} + {_sigma_sql(d, 'k.s2', m)} * {P.normal_sql('k.e2', 'k.s2', str(m))})"
        diff = {"abs": f"abs({left} - {right})", "sq": f"pow({left} - {right}, 2)", "signed": f"({left} - {right})"}[d.mode]
        return f"CAST(round({diff} * {P.FIXED}) AS BIGINT) AS x{m}"

    cols = ", ".join(map(feature, range(1, d.dims + 1)))
    return f"SELECT k.s1, k.s2, k.r, k.trial, k.e1, k.e2, k.y, {cols} FROM ({pair_keys_sql(d)}) k JOIN ({latent_sql(d.dims)}) u ON u.entity_id = k.e1 JOIN ({latent_sql(d.dims)}) v ON v.entity_id = k.e2"


class SyntheticPairSource(DataSource):
    """spark.read.format("synthetic_pairs"): pairs of any number without an input table, for load tests.

    Options: rows, sources, dims, partitions.  Values come from a counter-based generator keyed by the row's number.
    """

    @classmethod
    def name(cls) -> str:
        return "synthetic_pairs"

    def schema(self) -> str:
        return "s1 int, s2 int, y int, " + ", ".join(f"x{m} double" for m in range(1, int(self.options.get("dims", 5)) + 1))

    def reader(self, schema) -> DataSourceReader:
        return _PairReader(self.options)


class _PairReader(DataSourceReader):
    def __init__(self, options) -> None:
        self.rows, self.sources = int(options.get("rows", 1000)), int(options.get("sources", 6))
        self.dims, self.parts = int(options.get("dims", 5)), int(options.get("partitions", 4))

    def partitions(self) -> list[InputPartition]:
        return [InputPartition(k) for k in range(self.parts)]

    def read(self, partition) -> Iterator:
        import numpy as np
        import pyarrow as pa

        low, high = (self.rows * k // self.parts for k in (partition.value, partition.value + 1))
        for at in range(low, high, 65536):
            n = min(65536, high - at)
            rng = np.random.Generator(np.random.Philox(key=20240607, counter=at))
            s1 = rng.integers(1, self.sources, n)
            s2 = s1 + rng.integers(1, self.sources - s1 + 1)
            y = np.where(rng.random(n) < 0.5, 1, -1)
            x = np.abs(rng.normal(0, np.where(y == 1, 0.1, 0.5)[:, None], (n, self.dims)))
            columns = [pa.array(s1.astype(np.int32)), pa.array(s2.astype(np.int32)), pa.array(y.astype(np.int32)), *(pa.array(c) for c in x.T)]
            yield pa.RecordBatch.from_arrays(columns, names=["s1", "s2", "y", *(f"x{m}" for m in range(1, self.dims + 1))])
