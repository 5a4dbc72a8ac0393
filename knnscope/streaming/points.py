"""New points as a stream: assignment, windows, deduplication, drift and a guard of the call rate."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from knnscope.operators.curve2d import ClusterModel


def point_stream(spark: SparkSession, path: str, schema, files_per_batch: int = 1) -> DataFrame:
    """Parquet files of points as they arrive; ``ts`` becomes a timestamp for watermarks."""
    stream = spark.readStream.schema(schema).option("maxFilesPerTrigger", files_per_batch).parquet(path)
    return stream.withColumn("ts", F.col("ts").cast("timestamp"))


def assign_stream(stream: DataFrame, model: ClusterModel) -> DataFrame:
    """Each arriving point with its cluster; no state."""
    return model.assign(stream)


def window_counts(stream: DataFrame, key: str, size: str, slide: str | None = None, late: str = "10 minutes") -> DataFrame:
    """Counts per key and tumbling or sliding window; rows later than the watermark are dropped."""
    w = F.window("ts", size, slide) if slide else F.window("ts", size)
    return stream.withWatermark("ts", late).groupBy(w.alias("w"), key).count().select(F.col("w.start").alias("start"), key, "count")


def session_counts(stream: DataFrame, key: str, gap: str, late: str = "10 minutes") -> DataFrame:
    w = F.session_window("ts", gap)
    return stream.withWatermark("ts", late).groupBy(w.alias("w"), key).count().select(F.col("w.start").alias("start"), F.col("w.end").alias("end"), key, "count")


def distinct_points(stream: DataFrame, ident: str = "event_id", late: str = "10 minutes") -> DataFrame:
    return stream.withWatermark("ts", late).dropDuplicatesWithinWatermark([ident])


def interval_join(points: DataFrame, calls: DataFrame, key: str, before: str = "5 minutes") -> DataFrame:
    """Points with the calls of the same key at most that long before them; both sides' state is bounded by watermarks."""
    p = points.withWatermark("ts", "10 minutes").alias("p")
    c = calls.withWatermark("ts", "10 minutes").alias("c")
    near = F.expr(f"p.{key} = c.{key} AND c.ts <= p.ts AND c.ts >= p.ts - interval {before}")
    return p.join(c, near)


def leaf_drift(stream: DataFrame, leaf: str, min_pts: int) -> DataFrame:
    """``leaf, n, dense`` after each batch for every leaf that got points: a running count that crosses min_pts is drift."""

    counts = stream.groupBy(leaf).agg(F.count(F.lit(1)).alias("n"))
    return counts.withColumn("dense", F.col("n") >= min_pts)


def over_rate(ledger: DataFrame, calls: int, size: str = "1 hour") -> DataFrame:
    """Windows of a stream of calls in which more were made than the service allows."""
    counts = ledger.withWatermark("ts", "1 hour").groupBy(F.window("ts", size).alias("w")).count()
    return counts.filter(F.col("count") > calls).select(F.col("w.start").alias("start"), "count")


def drain(stream: DataFrame, name: str, mode: str = "append", checkpoint: str | None = None) -> DataFrame:
    """Run a stream over what is there now and return its rows from a memory sink; for tests and small results."""
    spark = stream.sparkSession
    writer = stream.writeStream.format("memory").queryName(name).outputMode(mode).trigger(availableNow=True)
    query = (writer.option("checkpointLocation", checkpoint) if checkpoint else writer).start()
    query.awaitTermination()
    return spark.table(name)
