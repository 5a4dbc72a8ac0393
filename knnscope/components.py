"""Connected components by contraction: every round merges each node with its smallest neighbour."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from knnscope.io import materialize


def _jump(parents: DataFrame, times: int) -> DataFrame:
    """Shorten chains of parents, each time to half their length."""
    for _ in range(times):
        up = parents.select(F.col("node").alias("parent"), F.col("parent").alias("grand"))
        parents = parents.join(up, "parent", "left").select("node", F.coalesce("grand", "parent").alias("parent"))
    return parents


def connected(edges: DataFrame, max_rounds: int = 60, jumps: int = 2) -> DataFrame:
    """``(node, component)`` for every endpoint of ``edges(u, v)``; component is the smallest id reachable.

    A node's parent is its smallest neighbour if that is smaller, so that chains of parents only descend and each tree
    is named by its smallest member. Contracting the trees leaves a graph of at most half the nodes, hence
    O(log n) rounds; each round reads and writes its tables in the shared folder, so lineage stays short.
    Rows with a NULL end and loops link nothing. An empty input gives an empty result.
    """
    left = materialize(
        edges.filter("u <> v").select(F.least("u", "v").alias("u"), F.greatest("u", "v").alias("v")).distinct(), "edges"
    )
    found = None
    for _ in range(max_rounds):
        if left.isEmpty():
            break
        both = left.unionByName(left.select(F.col("v").alias("u"), F.col("u").alias("v")))
        parents = both.groupBy(F.col("u").alias("node")).agg(F.least("u", F.min("v")).alias("parent"))
        parents = materialize(_jump(parents, jumps), "parents")
        moved = parents.select(F.col("node").alias("component"), F.col("parent").alias("to"))
        if found is None:
            found = parents.withColumnRenamed("parent", "component")
        else:
            found = materialize(
                found.join(moved, "component", "left").select("node", F.coalesce("to", "component").alias("component")),
                "components",
            )
        for end in ("u", "v"):
            names = parents.select(F.col("node").alias(end), "parent")
            left = left.join(names, end).drop(end).withColumnRenamed("parent", end)
        left = materialize(
            left.filter("u <> v").select(F.least("u", "v").alias("u"), F.greatest("u", "v").alias("v")).distinct(),
            "edges",
        )
    else:
        raise RuntimeError("components did not settle")
    if found is None:
        return left.select(F.col("u").alias("node"), F.col("v").alias("component"))
    return found
