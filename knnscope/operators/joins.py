"""Joins that the methods need and SQL has no operator for, built from equality joins and windows."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F


def asof_join(left: DataFrame, right: DataFrame, by: str, on: str, value: str) -> DataFrame:
    """``left`` with the ``value`` of the latest row of ``right`` of the same ``by`` at or before ``on``: a union and one
    window, so each key's rows are sorted once and nothing is multiplied."""
    keep = left.columns
    l_side = left.withColumns({"_v": F.lit(None).cast(right.schema[value].dataType), "_left": F.lit(1)})
    r_side = right.select(by, on, F.col(value).alias("_v")).withColumn("_left", F.lit(0))
    both = l_side.unionByName(r_side, allowMissingColumns=True)
    order = Window.partitionBy(by).orderBy(on, "_left").rowsBetween(Window.unboundedPreceding, Window.currentRow)
    return both.withColumn(f"{value}_asof", F.last("_v", ignorenulls=True).over(order)).filter("_left = 1").select(*keep, f"{value}_asof")


def range_join(points: DataFrame, ranges: DataFrame, on: str, width: float) -> DataFrame:
    """Rows of ``points`` with each range ``lo <= on <= hi``: a range is entered under every bin of ``width`` it meets."""
    bins = ranges.withColumn("_b", F.explode(F.sequence(F.floor(F.col("lo") / width), F.floor(F.col("hi") / width))))
    keyed = points.withColumn("_b", F.floor(F.col(on) / width))
    return keyed.join(bins, "_b").filter((F.col(on) >= F.col("lo")) & (F.col(on) <= F.col("hi"))).drop("_b")


def distance_join(a: DataFrame, b: DataFrame, eps: float) -> DataFrame:
    """``a_id, b_id, d2`` of pairs of ``(id, x, y)`` within eps: by equality on cells of side eps and their neighbours."""
    cell = lambda c: F.floor(F.col(c) / eps).cast("long")
    near = F.array(*(F.struct((cell("x") + i).alias("cx"), (cell("y") + j).alias("cy")) for i in (-1, 0, 1) for j in (-1, 0, 1)))
    left = a.select(F.col("id").alias("a_id"), F.col("x").alias("ax"), F.col("y").alias("ay"), cell("x").alias("cx"), cell("y").alias("cy"))
    right = b.select(F.col("id").alias("b_id"), F.col("x").alias("bx"), F.col("y").alias("by"), F.explode(near).alias("c")).select(
        "b_id", "bx", "by", "c.cx", "c.cy"
    )
    dx, dy = F.col("ax") - F.col("bx"), F.col("ay") - F.col("by")
    pairs = left.join(right, ["cx", "cy"]).withColumn("d2", dx * dx + dy * dy)
    return pairs.filter(F.col("d2") <= eps * eps).select("a_id", "b_id", "d2")
