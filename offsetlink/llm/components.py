"""Connected components by contraction: nodes hang on their least neighbour, trees become nodes, until no edge is left."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from offsetlink.llm import common


def _hung(edges: DataFrame) -> DataFrame:
    """node and the label it hangs on: its least neighbour's label if that is less than itself."""
    both = edges.unionByName(edges.select(F.col("b").alias("a"), F.col("a").alias("b")))
    up = common.cut(both.groupBy(F.col("a").alias("node")).agg(F.min("b").alias("low")).select("node", F.least("node", "low").alias("label")), "hung")
    further = up.select(F.col("node").alias("label"), F.col("label").alias("further"))
    out = common.cut(up.join(further, "label").select("node", F.col("further").alias("label")), "hung")
    common.drop(up)
    return out


def components(edges: DataFrame, rounds: int = 60) -> DataFrame:
    """node and component (the least node that it reaches) for every end of edges (a, b: long).

    Edges may repeat, point either way or join a node to itself; null ends are left out.  Each round at least halves the
    nodes that still have edges, so the rounds together handle few times as many rows as the first.  Joins are on keys
    that Spark can split, aggregates combine before the shuffle, and each round is written to the shared folder.
    """
    given = edges.where(F.col("a").isNotNull() & F.col("b").isNotNull())
    first = common.cut(given.select(F.least("a", "b").alias("a"), F.greatest("a", "b").alias("b")).distinct(), "edges")
    left, used = first, [first]
    loops = left.where("a = b").select(F.col("a").alias("node"), F.col("a").alias("label"))
    left = left.where("a < b")
    labels = []
    for _ in range(rounds):
        up = _hung(left)
        labels.append(up)
        used.append(up)
        one, two = up.select(F.col("node").alias("a"), F.col("label").alias("la")), up.select(F.col("node").alias("b"), F.col("label").alias("lb"))
        moved = left.join(one, "a").join(two, "b").where("la <> lb")
        left = common.cut(moved.select(F.least("la", "lb").alias("a"), F.greatest("la", "lb").alias("b")).distinct(), "edges")
        used.append(left)
        if left.isEmpty():
            break
    else:
        raise RuntimeError("components did not end")
    found = labels[0]
    for up in labels[1:]:
        of = up.select(F.col("node").alias("label"), F.col("label").alias("further"))
        found = found.join(of, "label", "left").select("node", F.coalesce("further", "label").alias("label"))
    alone = loops.join(found.select("node"), "node", "left_anti")
    out = common.cut(found.unionByName(alone).select("node", F.col("label").alias("component")), "components")
    common.drop(*used)
    return out
