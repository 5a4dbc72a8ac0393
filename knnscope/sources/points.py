"""Points with a declared schema from files, and a layout in curve order for the provider."""

from __future__ import annotations

from dataclasses import dataclass, field

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from knnscope.functions import curves


@dataclass(frozen=True)
class PointSpec:
    """Which columns are the id and the coordinates; all others pass through."""

    id: str = "id"
    coords: tuple[str, ...] = ("x", "y")
    attrs: dict[str, str] = field(default_factory=dict)

    def schema(self) -> str:
        return ", ".join([f"{self.id} BIGINT", *(f"{c} DOUBLE" for c in self.coords), *(f"{k} {v}" for k, v in self.attrs.items())])

    def valid(self, df: DataFrame) -> DataFrame:
        """Rows whose coordinates are finite numbers; the service never answers with others."""
        for c in (self.id, *self.coords):
            if c not in df.columns:
                raise ValueError(f"no column {c}")
        bad = F.lit(False)
        for c in self.coords:
            x = F.col(c).cast("double")
            bad = bad | x.isNull() | F.isnan(x) | (F.abs(x) == float("inf"))
        return df.filter(~bad)


def read_points(spark: SparkSession, path: str, fmt: str, spec: PointSpec) -> DataFrame:
    """Points from Parquet, ORC, CSV (with a header) or JSON lines; malformed rows keep their text in ``_corrupt_record``."""
    if fmt in ("parquet", "orc"):
        return spark.read.format(fmt).load(path)
    schema = spec.schema() + ", _corrupt_record STRING"
    reader = spark.read.format(fmt).schema(schema).option("mode", "PERMISSIVE").option("columnNameOfCorruptRecord", "_corrupt_record")
    return (reader.option("header", True) if fmt == "csv" else reader).load(path)


def write_indexed(df: DataFrame, path: str, domain, order: int = 12, kind: str = "hilbert", coarse: int = 4, files: int = 64) -> None:
    """Write points ranged by curve key, one folder for each coarse cell: probes then prune folders and row groups."""
    x, y = curves.cell_columns(F.col("x"), F.col("y"), domain, curves.base(kind) ** order)
    keyed = df.withColumn("ckey", curves.key_column(kind, x, y, order))
    shift = (curves.base(kind) ** 2) ** (order - coarse)
    keyed = keyed.withColumn("coarse", F.floor(F.col("ckey") / shift).cast("long"))
    ranged = keyed.repartitionByRange(files, "ckey").sortWithinPartitions("ckey")
    ranged.write.partitionBy("coarse").mode("overwrite").parquet(path)


def geojson_lines(df: DataFrame, *properties: str) -> DataFrame:
    """One GeoJSON feature per row, for maps."""
    return df.select(
        F.to_json(
            F.struct(
                F.lit("Feature").alias("type"),
                F.struct(F.lit("Point").alias("type"), F.array("x", "y").alias("coordinates")).alias("geometry"),
                F.struct(*properties).alias("properties"),
            )
        ).alias("value")
    )
