"""The adaptive tree with full access to the points: what unlimited calls would make of it."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from knnscope.io import materialize


def full_tree(points: DataFrame, domain, min_pts: int, levels: int) -> DataFrame:
    """``level, cx, cy, near, state`` of all nodes below the root, for cells cut in four.

    ``near`` counts the points within half a diagonal of the node's centre; a node is split if there are ``min_pts`` and it
    isn't of the last level. One aggregation per level, over the points of nodes that are still cut.
    """
    x0, y0, side0 = domain
    spark = points.sparkSession
    open_ = spark.createDataFrame([(0, 0), (0, 1), (1, 0), (1, 1)], "cx long, cy long")
    found = None
    steps = [F.struct(F.lit(i).alias("i"), F.lit(j).alias("j")) for i in (-1, 0, 1) for j in (-1, 0, 1)]
    for level in range(1, levels + 1):
        side = side0 / 2**level
        at = lambda c, o: F.floor((F.col(c) - F.lit(o)) / F.lit(side)).cast("long")
        around = points.select("x", "y", at("x", x0).alias("px"), at("y", y0).alias("py"), F.explode(F.array(*steps)).alias("s"))
        around = around.select("x", "y", (F.col("px") + F.col("s.i")).alias("cx"), (F.col("py") + F.col("s.j")).alias("cy"))
        dx = F.col("x") - (F.lit(x0) + (F.col("cx") + 0.5) * F.lit(side))
        dy = F.col("y") - (F.lit(y0) + (F.col("cy") + 0.5) * F.lit(side))
        close = around.filter(dx * dx + dy * dy <= side * side / 2)
        counts = close.join(open_, ["cx", "cy"], "left_semi").groupBy("cx", "cy").agg(F.count(F.lit(1)).alias("near"))
        nodes = open_.join(counts, ["cx", "cy"], "left").select(
            F.lit(level).alias("level"), "cx", "cy", F.coalesce("near", F.lit(0)).cast("long").alias("near")
        )
        split = (F.col("near") >= min_pts) & F.lit(level < levels)
        nodes = materialize(nodes.withColumn("state", F.when(split, "split").when(F.col("near") >= min_pts, "maybe").otherwise("sparse")), "tree")
        found = nodes if found is None else found.unionByName(nodes)
        parts = F.explode(F.array(*(F.struct((F.col("cx") * 2 + i).alias("cx"), (F.col("cy") * 2 + j).alias("cy")) for i in (0, 1) for j in (0, 1))))
        open_ = nodes.filter("state = 'split'").select(parts.alias("n")).select("n.cx", "n.cy")
    return found
