"""Exchange formats with a declared schema."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

#: Text formats would else cut times to milliseconds.
TIMES = "yyyy-MM-dd'T'HH:mm:ss.SSSSSS"
SCHEMA = "fov_id long, video_id long, lat double, lon double, theta double, r_m double, alpha double, t timestamp_ntz"


def write(df: DataFrame, path: str, kind: str) -> None:
    """kind: csv, json, orc or parquet."""
    writer = df.write.mode("overwrite").format(kind)
    if kind in ("csv", "json"):
        writer = writer.option("timestampNTZFormat", TIMES).option("header", True)
    writer.save(path)


def read(spark: SparkSession, path: str, kind: str, schema: str = SCHEMA) -> DataFrame:
    reader = spark.read.schema(schema).format(kind)
    if kind in ("csv", "json"):
        reader = reader.option("timestampNTZFormat", TIMES).option("header", True)
    return reader.load(path)


def export_heatmap(bins: DataFrame, path: str, kind: str = "csv") -> None:
    """A heat map's bins in one format, ordered by row and column; ordered by ranges, so no task holds them all."""
    write(bins.orderBy("bin_y", "bin_x"), path, kind)


def export_top(top: DataFrame, path: str) -> None:
    """A top-k list as JSON lines in one file; it has k rows."""
    write(top.orderBy("rank").coalesce(1), path, "json")
