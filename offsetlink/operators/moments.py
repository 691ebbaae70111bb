"""Pair moments: all that the squared loss needs of the labelled pairs, by one aggregation.

For each source pair (and trial, budget or fold) the sums of products of features, of features with labels, and counts.
The sums are partial before the only shuffle, so what is shuffled doesn't grow with a source pair's rows.  Iterations,
cross-validation, standardising and all linear baselines then run on moments.
"""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

#: Most numbers that moments may have to be collected; more stay on the cluster.
DRIVER_NUMBERS = 50_000_000


def canonical(pairs: DataFrame) -> DataFrame:
    """s1 < s2, whatever the order in the input; pairs within one source go."""
    low, high = F.least("s1", "s2"), F.greatest("s1", "s2")
    return pairs.where(F.col("s1") != F.col("s2")).withColumns({"s1": low, "s2": high})


def names(d: int) -> list[str]:
    """Columns of the upper triangle, then the cross vector; feature 0 is the constant."""
    return [f"g{a}_{b}" for a in range(d + 1) for b in range(a, d + 1)] + [f"c{a}" for a in range(d + 1)]


def pair_moments(pairs: DataFrame, features: list[str], extra: list[str] | None = None, number: str = "decimal(38,0)") -> DataFrame:
    """n, gram (g0_0..), cross (c0..) and yy for each (extra, s1, s2); exact if features are integers.

    number is the type of the sums: decimal for integers of any count, double for real features.
    """
    xs = [F.lit(1).cast("long"), *(F.col(f) for f in features)]
    d = len(features)
    total = lambda c, name: F.sum(c.cast(number) if number != "long" else c).cast(number).alias(name)
    gram = [total(xs[a] * xs[b], f"g{a}_{b}") for a in range(d + 1) for b in range(a, d + 1)]
    cross = [total(xs[a] * F.col("y"), f"c{a}") for a in range(d + 1)]
    keys = [*(extra or []), "s1", "s2"]
    return canonical(pairs).groupBy(*keys).agg(F.count("*").alias("n"), *gram, *cross, total(F.col("y") * F.col("y"), "yy"))


def pair_moments_sql(source: str, d: int, extra: tuple[str, ...] = ()) -> str:
    xs = ["1", *(f"x{m}" for m in range(1, d + 1))]
    cols = [f"CAST(sum({xs[a]} * {xs[b]}) AS BIGINT) AS g{a}_{b}" for a in range(d + 1) for b in range(a, d + 1)] + [f"CAST(sum({xs[a]} * y) AS BIGINT) AS c{a}" for a in range(d + 1)]
    keys = ", ".join([*extra, "s1", "s2"])
    return f"SELECT {keys}, count(*) AS n, {', '.join(cols)}, CAST(sum(y * y) AS BIGINT) AS yy FROM ({source}) GROUP BY {keys}"


def pair_moments_arrow(pairs: DataFrame, features: list[str], extra: list[str] | None = None) -> DataFrame:
    """The same for very many features: products in numpy within tasks, sums by position after."""
    keys, d = [*(extra or []), "s1", "s2"], len(features)
    upper = np.triu_indices(d + 1)

    def partial(batches):
        held: dict[tuple, np.ndarray] = {}
        for b in batches:
            x = np.column_stack([np.ones(len(b)), *(b.column(f).to_numpy(zero_copy_only=False) for f in features)])
            y = b.column("y").to_numpy(zero_copy_only=False).astype(float)
            k = np.column_stack([b.column(c).to_numpy(zero_copy_only=False) for c in keys])
            groups, at = np.unique(k, axis=0, return_inverse=True)
            for g, key in enumerate(map(tuple, groups.tolist())):
                u, v = x[at.ravel() == g], y[at.ravel() == g]
                part = np.concatenate([(u.T @ u)[upper], u.T @ v, [len(v), v @ v]])
                held[key] = held.get(key, 0) + part
        for key, part in held.items():
            n = len(part)
            yield pa.RecordBatch.from_arrays([*(pa.array([v] * n, pa.int32()) for v in key), pa.array(range(n), pa.int32()), pa.array(part)], names=[*keys, "k", "v"])

    kinds = ", ".join(f"{c} int" for c in keys)
    parts = canonical(pairs).select(*(F.col(c).cast("int").alias(c) for c in keys), *features, "y").mapInArrow(partial, f"{kinds}, k int, v double")
    return parts.groupBy(*keys, "k").agg(F.sum("v").alias("v"))


@dataclass
class Block:
    """Moments of one fit on the driver: one row for each source pair, feature 0 the constant."""

    s1: np.ndarray
    s2: np.ndarray
    n: np.ndarray
    gram: np.ndarray
    cross: np.ndarray
    yy: np.ndarray

    @property
    def dims(self) -> int:
        return self.gram.shape[1]

    @property
    def sources(self) -> np.ndarray:
        return np.unique(np.concatenate([self.s1, self.s2]))

    def where(self, keep: np.ndarray) -> Block:
        return Block(self.s1[keep], self.s2[keep], self.n[keep], self.gram[keep], self.cross[keep], self.yy[keep])

    def minus(self, other: Block) -> Block:
        """Moments without those of other, whose pairs are among these: a fold's training moments."""
        out = Block(self.s1, self.s2, self.n.copy(), self.gram.copy(), self.cross.copy(), self.yy.copy())
        at = {p: i for i, p in enumerate(zip(self.s1.tolist(), self.s2.tolist(), strict=True))}
        for j, p in enumerate(zip(other.s1.tolist(), other.s2.tolist(), strict=True)):
            i = at[p]
            out.n[i] -= other.n[j]
            out.gram[i] -= other.gram[j]
            out.cross[i] -= other.cross[j]
            out.yy[i] -= other.yy[j]
        return out.where(out.n > 0)

    def transformed(self, t: np.ndarray) -> Block:
        """Moments of features T x, x with its constant first."""
        return Block(self.s1, self.s2, self.n, t @ self.gram @ t.T, self.cross @ t.T, self.yy)


def to_driver(moments: DataFrame, d: int, extra: list[str] | None = None, scale: float = 1.0) -> dict[tuple, Block]:
    """Blocks by the values of extra.  scale divides integer features.  Refuses what doesn't fit a driver."""
    width = (d + 1) * (d + 2) // 2 + d + 3
    rows = moments.limit(DRIVER_NUMBERS // width + 1).collect()
    if len(rows) > DRIVER_NUMBERS // width:
        raise ValueError("too many source pairs for the driver; solve on the cluster")
    unit = np.full(d + 1, 1 / scale)
    unit[0] = 1
    upper = np.triu_indices(d + 1)
    groups: dict[tuple, list] = {}
    for r in rows:
        groups.setdefault(tuple(r[c] for c in extra or []), []).append(r)
    out = {}
    for key, some in groups.items():
        some.sort(key=lambda r: (r.s1, r.s2))
        gram = np.zeros((len(some), d + 1, d + 1))
        for i, r in enumerate(some):
            gram[i][upper] = [float(r[f"g{a}_{b}"]) for a, b in zip(*upper, strict=True)]
        gram = gram + np.transpose(np.triu(gram, 1), (0, 2, 1))
        cross = np.array([[float(r[f"c{a}"]) for a in range(d + 1)] for r in some])
        ints = lambda c: np.array([int(r[c]) for r in some])
        out[key] = Block(ints("s1"), ints("s2"), ints("n"), gram * unit[:, None] * unit[None, :], cross * unit, np.array([float(r.yy) for r in some]))
    return out


def scaler(block: Block) -> np.ndarray:
    """T that makes the features of the block's rows of mean 0 and variance 1; a constant feature keeps scale 1."""
    n, total = block.n.sum(), block.gram.sum(0)
    mean = total[0] / n
    var = np.diag(total) / n - mean**2
    scale = np.where(var > 1e-12, np.sqrt(np.maximum(var, 1e-12)), 1.0)
    t = np.diag(1 / scale)
    t[1:, 0] = -mean[1:] / scale[1:]
    t[0] = 0
    t[0, 0] = 1
    return t
