"""Embedding near-duplicates by epsilon grid order.

Unit vectors with cosine >= c lie within epsilon = sqrt(2 - 2c) of each other.  Vectors are projected on their leading
principal dimensions, which never lengthens a distance, and sorted by the grid cells (of side epsilon) of the
projections.  The sorted sequence is joined with itself by recursion on its intervals: a pair of intervals is skipped where
the boxes around their projections are further apart than epsilon, else their parts are paired.  Down to blocks, intervals
are rows of tables and a step is a join on the intervals of the step before; a pair of blocks within reach is one task's
work and goes on in memory.  Of the pairs left, projected distances drop most before the cosine is computed in double
precision.  A block travels once for each block within reach, as the numbers that were given.

Equal vectors are one vector from the start.  A pair of blocks gives each vector's number of links and a spanning forest
of the links, so groups of near-copies aren't expanded into pairs.
"""

from __future__ import annotations

import math

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from offsetlink.llm import common
from offsetlink.llm.components import components

LEAST = 0.9
GRID_DIMS, FILTER_DIMS = 8, 24
#: Vectors in a block, and intervals that aren't cut further.
BLOCK, LEAF = 8192, 128
FAN_BITS = 3  # an interval has up to eight parts
SLACK = 1e-6


def normed(x: np.ndarray) -> np.ndarray:
    return x / np.linalg.norm(x, axis=-1, keepdims=True)


def _moments(batches, dims: int):
    """Count, sum and second moments of a task's vectors as one row."""
    n, s, m = 0, np.zeros(dims), np.zeros((dims, dims))
    for b in batches:
        x = _matrix(b.column("vec"), dims)
        n, s, m = n + len(x), s + x.sum(0), m + x.T @ x
    if n:
        yield pa.RecordBatch.from_arrays([pa.array([n]), pa.array([s.tolist()]), pa.array([m.ravel().tolist()])], names=["n", "s", "m"])


def _matrix(column: pa.Array, dims: int) -> np.ndarray:
    return column.flatten().to_numpy(zero_copy_only=False).astype(np.float64).reshape(-1, dims)


def principal_axes(vectors: DataFrame, dims: int, keep: int) -> np.ndarray:
    """The leading principal directions of all vectors (dims x keep), from summed moments; no row reaches the driver."""
    parts = vectors.select("vec").mapInArrow(lambda b: _moments(b, dims), "n long, s array<double>, m array<double>")
    sums = parts.select(F.posexplode("m").alias("k", "v")).groupBy("k").agg(F.sum("v").alias("v")).collect()
    if not sums:
        return np.eye(dims)[:, :keep]
    second = np.zeros(dims * dims)
    for r in sums:
        second[r.k] = r.v
    values, directions = np.linalg.eigh(second.reshape(dims, dims))
    return directions[:, np.argsort(-values, kind="stable")[:keep]]


def _projected(batches, dims: int, axes: np.ndarray, epsilon: float):
    for b in batches:
        x = normed(_matrix(b.column("vec"), dims))
        cells = np.floor(x @ axes[:, :GRID_DIMS] / epsilon).astype(np.int64)
        arrays = [b.column("rep"), b.column("copies"), pa.array([v.tobytes() for v in _given(b.column("vec"), dims)], pa.binary()), *(pa.array(c) for c in cells.T)]
        yield pa.RecordBatch.from_arrays(arrays, names=["rep", "copies", "vec", *(f"c{k}" for k in range(cells.shape[1]))])


def _given(column: pa.Array, dims: int) -> np.ndarray:
    """Vectors as they were given: in single precision where that holds all their values."""
    x = _matrix(column, dims)
    with np.errstate(over="ignore"):
        single = x.astype(np.float32)
    return single if np.array_equal(single, x) else x


def _unit(raw: bytes, dims: int, n: int) -> np.ndarray:
    """n vectors of length 1 in double precision, from given ones."""
    return normed(np.frombuffer(raw, np.float32 if len(raw) == 4 * n * dims else np.float64).reshape(n, dims).astype(np.float64))


def _blocks(batches, dims: int, axes: np.ndarray, block: int):
    """Cut a task's sorted run into packed blocks with the box around each block's projections."""
    from pyspark import TaskContext

    part, at = TaskContext.get().partitionId(), 0
    reps, copies, vectors = [], [], []

    def packed(k: int) -> pa.RecordBatch:
        size = max(map(len, vectors[:k]))
        wide = [v if len(v) == size else np.frombuffer(v, np.float32).astype(np.float64).tobytes() for v in vectors[:k]]
        raw = b"".join(wide)
        p = _unit(raw, dims, k) @ axes
        arrays = [pa.array([(part << 32) + at]), pa.array([np.array(reps[:k], np.int64).tobytes()]), pa.array([np.array(copies[:k], np.int64).tobytes()]), pa.array([raw], pa.binary()), pa.array([p.min(0).tolist()]), pa.array([p.max(0).tolist()])]
        return pa.RecordBatch.from_arrays(arrays, names=["block", "reps", "copies", "vectors", "low", "high"])

    for b in batches:
        reps += b.column("rep").to_pylist()
        copies += b.column("copies").to_pylist()
        vectors += b.column("vec").to_pylist()
        while len(reps) >= block:
            yield packed(block)
            at += 1
            del reps[:block], copies[:block], vectors[:block]
    if reps:
        yield packed(len(reps))


PACKED = "block long, reps binary, copies binary, vectors binary, low array<double>, high array<double>"


class PairJoin:
    """The recursive join of two sorted runs, or of one with itself.

    Links are counted as they are found and only a spanning forest of them is kept, so their number costs no memory.
    Vectors of the second run go by their place behind those of the first.
    """

    def __init__(self, x: np.ndarray, y: np.ndarray, axes: np.ndarray, least: float, weight: np.ndarray) -> None:
        self.x, self.y, self.least, self.limit, self.weight = x, y, least, 2 - 2 * least + SLACK, weight
        self.same = x is y
        self.behind = 0 if self.same else len(x)
        self.p = (x @ axes).astype(np.float32)
        self.q = self.p if self.same else (y @ axes).astype(np.float32)
        self.links, self.label, self.forest = np.zeros(len(weight)), np.arange(len(weight)), []
        self._join(0, len(x), 0, len(y))

    def _found(self, i: np.ndarray, j: np.ndarray) -> None:
        j = j + self.behind
        lo = min(i[0], int(j.min()))
        n = max(int(i[-1]), int(j.max())) + 1 - lo
        self.links[lo : lo + n] += np.bincount(i - lo, self.weight[j], n) + np.bincount(j - lo, self.weight[i], n)
        while len(i):
            apart = self.label[i] != self.label[j]
            i, j = i[apart], j[apart]
            if len(i):
                self.forest.append((int(i[0]), int(j[0])))
                self.label[self.label == self.label[j[0]]] = self.label[i[0]]

    def _join(self, a: int, b: int, c: int, d: int) -> None:
        if self.same and d <= a or a == b or c == d:
            return
        p, q = self.p[a:b], self.q[c:d]
        gap = np.maximum(0, np.maximum(p.min(0) - q.max(0), q.min(0) - p.max(0)))
        if float(gap @ gap) > self.limit + SLACK:
            return
        if b - a <= LEAF and d - c <= LEAF:
            near = (p * p).sum(1)[:, None] + (q * q).sum(1)[None, :] - 2 * (p @ q.T) <= self.limit + 1e-4
            i, j = np.nonzero(near)
            if self.same:
                ahead = i + a < j + c
                i, j = i[ahead], j[ahead]
            if len(i):
                i, j = i + a, j + c
                ok = np.einsum("ij,ij->i", self.x[i], self.y[j]) >= self.least
                if ok.any():
                    self._found(i[ok], j[ok])
            return
        if b - a >= d - c:
            m = (a + b) // 2
            self._join(a, m, c, d)
            self._join(m, b, c, d)
        else:
            m = (c + d) // 2
            self._join(a, b, c, m)
            self._join(a, b, m, d)


LINKS = "kind int, a long, b long"


def _joined(batches, dims: int, axes: np.ndarray, least: float):
    """Rows (0, rep, links) with each vector's number of links, and (1, rep, rep) with a forest of the links."""
    for b in batches:
        for row in b.to_pylist():
            reps, copies = np.frombuffer(row["reps"], np.int64), np.frombuffer(row["copies"], np.int64)
            x = _unit(row["vectors"], dims, len(reps))
            own = row["other_vectors"] is None
            reps2, copies2 = (reps, copies) if own else (np.frombuffer(row["other_reps"], np.int64), np.frombuffer(row["other_copies"], np.int64))
            y = x if own else _unit(row["other_vectors"], dims, len(reps2))
            ids, weight = (reps, copies) if own else (np.concatenate([reps, reps2]), np.concatenate([copies, copies2]))
            done = PairJoin(x, y, axes, least, weight.astype(float))
            if not done.forest:
                continue
            links, forest = done.links, done.forest
            some = np.flatnonzero(links)
            f = np.array(forest, np.int64).reshape(-1, 2)
            yield pa.RecordBatch.from_arrays(
                [pa.array(np.repeat([0, 1], [len(some), len(f)]).astype(np.int32)), pa.array(np.concatenate([ids[some], ids[f[:, 0]]])), pa.array(np.concatenate([links[some].astype(np.int64), ids[f[:, 1]]]))],
                names=["kind", "a", "b"],
            )


def _interval(block, level: int, block_levels: int):
    """The interval of a level that holds a block: runs of a partition's blocks at first, then runs of partitions."""
    if level <= block_levels:
        return F.shiftleft(F.shiftright(block, 32), 32) + F.shiftright(block.bitwiseAND((1 << 32) - 1), FAN_BITS * level)
    return F.shiftright(block, 32 + FAN_BITS * (level - block_levels))


def near_blocks(boxes: DataFrame, limit: float, dims: int) -> DataFrame:
    """Pairs (block, other) of blocks whose boxes are within reach, each block with itself too.

    Recursion from the whole sequence down: pairs of intervals within reach give the pairs of their parts.
    """
    most = boxes.agg(F.max(F.col("block").bitwiseAND((1 << 32) - 1)).alias("at"), F.max(F.shiftright("block", 32)).alias("part")).first()
    if most.at is None:
        return boxes.select("block", F.col("block").alias("other"))
    steps = lambda n: -(-int(n).bit_length() // FAN_BITS)
    block_levels = steps(most.at)
    edge = lambda side, of: F.array(*(of(F.get(side, F.lit(k))) for k in range(dims)))
    levels = [boxes.select(F.col("block").alias("node"), F.col("block").alias("least"), "low", "high")]
    for level in range(1, block_levels + steps(most.part) + 1):
        up = levels[-1].groupBy(_interval(F.col("least"), level, block_levels).alias("node")).agg(F.min("least").alias("least"), edge("low", F.min).alias("low"), edge("high", F.max).alias("high"))
        levels.append(common.cut(up, "intervals"))
    gaps = F.zip_with(F.zip_with("low", "high2", lambda a, b: a - b), F.zip_with("low2", "high", lambda a, b: a - b), lambda a, b: F.greatest(a, b, F.lit(0.0)))
    reach = F.aggregate(gaps, F.lit(0.0), lambda s, g: s + g * g) <= limit + SLACK
    top = levels[-1].select("node", F.col("node").alias("node2"))
    for level in range(len(levels) - 1, 0, -1):
        parts = levels[level - 1].withColumn("whole", _interval(F.col("least"), level, block_levels))
        other = parts.select(*(F.col(c).alias(f"{c}2") for c in parts.columns))
        pairs = top.withColumnsRenamed({"node": "whole", "node2": "whole2"}).join(parts, "whole").join(other, "whole2")
        top = pairs.where((F.col("node") <= F.col("node2")) & reach).select("node", "node2")
    return top.select(F.col("node").alias("block"), F.col("node2").alias("other"))


def join(embeddings: DataFrame, least: float = LEAST, block: int = BLOCK) -> DataFrame:
    """vec_id, n_links, component_id and kept of each row, linked where the cosine in double precision is >= least.

    Null, empty and zero vectors, and those with a null or non-finite component, link with nothing; so do vectors whose
    length differs from that of the most usual one.  Rows with equal vectors link with each other.  Rows that repeat a
    vec_id count as vectors of their own under that id.  A row with a null vec_id has null component and is not kept,
    but counts as a link of others.  Other columns are ignored.
    """
    spark = embeddings.sparkSession
    common.bound_batches(spark)
    rows = embeddings.select(F.col("vec_id").cast("long").alias("vec_id"), F.transform("embedding", lambda v: v.cast("double") + F.lit(0.0)).alias("vec"))
    finite = F.forall("vec", lambda v: v.isNotNull() & ~F.isnan(v) & (F.abs(v) < F.lit(float("inf"))))
    usable = F.coalesce(F.col("vec").isNotNull() & finite & F.exists("vec", lambda v: v != 0), F.lit(False))
    rows = common.cut(rows.withColumn("fp", F.when(usable, F.xxhash64("vec"))), "vectors")
    usual = rows.where("fp is not null").groupBy(F.size("vec").alias("d")).count().orderBy(F.desc("count"), "d").first()
    if usual is None:
        return rows.select("vec_id", F.lit(0).cast("long").alias("n_links"), F.col("vec_id").alias("component_id"), F.col("vec_id").isNotNull().alias("kept"))
    dims = usual.d
    fit = F.size("vec") == dims
    classes = common.cut(rows.where(F.col("fp").isNotNull() & fit).groupBy("fp", "vec").agg(F.min("vec_id").alias("low"), F.count("*").alias("copies")), "classes")
    # Classes go by the hash of their vector, so ids may repeat or be null; components are named by ids at the end.
    classes = classes.withColumn("rep", F.col("fp"))
    axes = principal_axes(classes, dims, min(dims, FILTER_DIMS))
    epsilon = math.sqrt(2 - 2 * least)
    cells = [f"c{k}" for k in range(min(GRID_DIMS, dims))]
    schema = "rep long, copies long, vec binary, " + ", ".join(f"{c} long" for c in cells)
    projected = classes.select("rep", "copies", "vec").mapInArrow(lambda b: _projected(b, dims, axes, epsilon), schema)
    # As many runs as make whole blocks of several: short runs would make many small blocks, and so many pairs.
    runs = max(1, min(common.partitions(spark), -(-classes.count() // (4 * block))))
    ordered = projected.repartitionByRange(runs, *cells, "rep").sortWithinPartitions(*cells, "rep").select("rep", "copies", "vec").coalesce(runs)
    blocks = common.cut(ordered.mapInArrow(lambda b: _blocks(b, dims, axes, block), PACKED), "blocks")
    pairs = near_blocks(blocks.select("block", "low", "high"), 2 - 2 * least, axes.shape[1])
    one, two = blocks.select("block", "reps", "copies", "vectors"), blocks.select(F.col("block").alias("other"), F.col("reps").alias("other_reps"), F.col("copies").alias("other_copies"), F.col("vectors").alias("other_vectors"))
    mine = pairs.where(F.col("block") == F.col("other")).join(one, "block").select("reps", "copies", "vectors", *(F.lit(None).cast("binary").alias(f"other_{n}") for n in ("reps", "copies", "vectors")))
    both = pairs.where(F.col("block") < F.col("other")).join(one, "block").join(two, "other").select("reps", "copies", "vectors", "other_reps", "other_copies", "other_vectors")
    links = common.cut(mine.unionByName(both).mapInArrow(lambda b: _joined(b, dims, axes, least), LINKS), "links")
    counts = links.where("kind = 0").groupBy(F.col("a").alias("rep")).agg(F.sum("b").alias("linked"))
    found = components(links.where("kind = 1").select("a", "b"))
    named = classes.select("fp", "vec", "rep", "copies", "low").join(counts, "rep", "left").join(found.select(F.col("node").alias("rep"), "component"), "rep", "left")
    named = named.withColumn("component", F.coalesce("component", "rep"))
    least_id = named.groupBy("component").agg(F.min("low").alias("name"))
    named = named.join(least_id, "component").select(F.col("fp").alias("fp_"), F.col("vec").alias("vec_"), "copies", F.coalesce("linked", F.lit(0)).alias("linked"), F.col("name").alias("component"))
    out = rows.join(named, (rows["fp"] == named["fp_"]) & (rows["vec"] == named["vec_"]), "left")
    component = F.when(F.col("vec_id").isNotNull(), F.coalesce("component", "vec_id"))
    return out.select("vec_id", F.coalesce(F.col("copies") - 1 + F.col("linked"), F.lit(0)).cast("long").alias("n_links"), component.alias("component_id"), F.coalesce(component == F.col("vec_id"), F.lit(False)).alias("kept"))


def op3_grid_join(spark, sf_dir: str) -> DataFrame:
    return join(common.read(spark, sf_dir, "embeddings"))


ORACLE_OP3 = r"""
WITH RECURSIVE v AS MATERIALIZED (
  SELECT vec_id, CAST(embedding AS DOUBLE[]) AS x FROM embeddings
  WHERE embedding IS NOT NULL AND len(list_filter(embedding, lambda c: c IS NULL OR NOT isfinite(c))) = 0 AND len(list_filter(embedding, lambda c: c <> 0)) > 0),
e AS MATERIALIZED (
  SELECT a.vec_id AS a, b.vec_id AS b FROM v a JOIN v b ON a.vec_id <> b.vec_id WHERE list_cosine_similarity(a.x, b.x) >= 0.9),
r(vec_id, reached) AS (
  SELECT vec_id, vec_id FROM embeddings UNION SELECT r.vec_id, e.b FROM r JOIN e ON e.a = r.reached),
c AS (SELECT vec_id, min(reached) AS component_id FROM r GROUP BY vec_id)
SELECT c.vec_id, (SELECT count(*) FROM e WHERE e.a = c.vec_id) AS n_links, c.component_id, c.vec_id = c.component_id AS kept FROM c"""
