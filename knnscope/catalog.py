"""All queries of the library by name, with the DuckDB SQL that gives the same rows."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from knnscope.plans import methods, relational
from knnscope.sources.views import plain, sql


def _relational(text: str):
    return lambda spark, sf_dir: sql(spark, sf_dir, text)


def flagship(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Sizes of the clusters that the budgeted two-dimensional clusterer finds in `shapes`; NULL is noise."""
    labels = methods.model2d("hilbert")(spark, sf_dir)
    return labels.groupBy("cluster_id").agg(F.count(F.lit(1)).alias("n"))


def queries() -> dict:
    return {n: _relational(relational.SPARK.get(n, t)) for n, t in relational.QUERIES.items()} | methods.queries()


def oracle_sql() -> dict:
    found = {}
    for name, text in relational.QUERIES.items():
        text = plain(text)
        for spark_says, other in relational.DIALECT.items():
            text = text.replace(spark_says, other)
        found[name] = relational.SWAPPED.get(name, text)
    return found | methods.oracle_sql()
