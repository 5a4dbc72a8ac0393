"""Grid cells: counts, density, runs, and density clustering of cells."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from knnscope.components import connected

#: The origin lies this much below 0, so that no point with three decimals lies on an edge.
ORIGIN = -0.0005


def cell_of(df: DataFrame, side: float, dims: int = 2, origin: float = ORIGIN) -> DataFrame:
    """``df`` with the numbers of its half-open cells, ``cx`` and ``cy``."""
    for c, axis in (("cx", "x"), ("cy", "y"))[:dims]:
        df = df.withColumn(c, F.floor((F.col(axis) - F.lit(origin)) / F.lit(float(side))).cast("long"))
    return df


def cell_counts(df: DataFrame, side: float, dims: int = 2) -> DataFrame:
    """``cx[, cy], n``: one partial aggregation per task and a shuffle of cells, not of points."""
    return cell_of(df, side, dims).groupBy(*("cx", "cy")[:dims]).agg(F.count(F.lit(1)).alias("n"))


def dense_runs(df: DataFrame, side: float, min_pts: int) -> DataFrame:
    """``lo, hi``: maximal runs of dense cells on a line, which exhaustive boundary pursuit must find."""
    dense = cell_counts(df, side, 1).filter(F.col("n") >= min_pts)
    order = Window.orderBy("cx")  # as many rows as dense cells of a line
    marked = dense.withColumn("run", F.col("cx") - F.row_number().over(order))
    return marked.groupBy("run").agg(F.min("cx").alias("lo"), F.max("cx").alias("hi")).drop("run")


def grid_dbscan(df: DataFrame, side: float, min_pts: int, adjacency: int = 4) -> DataFrame:
    """``cx, cy, n, cluster_id``: dense cells, joined with the dense cells beside them (4) or also at corners (8).

    A cluster is named by its smallest cell code, (cx shifted left by 32) + cy.
    """
    dense = cell_counts(df, side).filter(F.col("n") >= min_pts)
    code = lambda x, y: F.shiftleft(x, 32) + y
    steps = [(0, 1), (1, 0)] + ([(1, 1), (1, -1)] if adjacency == 8 else [])
    moved = dense.select(
        code(F.col("cx"), F.col("cy")).alias("u"),
        F.explode(F.array(*(code(F.col("cx") + dx, F.col("cy") + dy) for dx, dy in steps))).alias("v"),
    )
    names = dense.select(code(F.col("cx"), F.col("cy")).alias("v"))
    found = connected(moved.join(names, "v").select("u", "v"))
    own = dense.withColumn("node", code(F.col("cx"), F.col("cy")))
    return own.join(found, "node", "left").select("cx", "cy", "n", F.coalesce("component", "node").alias("cluster_id"))
