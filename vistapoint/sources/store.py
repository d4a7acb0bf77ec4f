"""The store of fields of view: Parquet by day, ordered along a Z-curve of tiles, with bounding boxes as plain columns.

Their row-group statistics do for a range query what a spatial index would: four pushed comparisons skip what cannot overlap.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions.geo import z_order
from ..operators.fov import with_mbr

TILE_DEGREES = 0.01


def tile_id(lat: Column, lon: Column) -> Column:
    """A Z-curve key of 0.01-degree tiles."""
    return z_order(F.floor((lon + 180.0) / TILE_DEGREES), F.floor((lat + 90.0) / TILE_DEGREES))


def laid_out(fovs: DataFrame) -> DataFrame:
    """With bounding box, tile_id and day."""
    return with_mbr(fovs).withColumns({"tile_id": tile_id(F.col("lat"), F.col("lon")), "day": F.to_date("t")})


def write(fovs: DataFrame, path: str, files: int | None = None, mode: str = "overwrite") -> None:
    """Range-partitioned by day and tile, so that each file covers a compact place; ``files`` of 256 MB or more are wanted at scale."""
    n = files or int(fovs.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    laid_out(fovs).repartitionByRange(n, "day", "tile_id").sortWithinPartitions("day", "tile_id").write.mode(mode).partitionBy("day").parquet(path)


def read(spark: SparkSession, path: str) -> DataFrame:
    return spark.read.parquet(path)


def jdbc_options(url: str, table: str, column: str, low: int, high: int, parts: int) -> dict[str, str]:
    """Options of spark.read.format('jdbc') for a partitioned read of fields of view that a relational store keeps. No driver comes with this library."""
    return {"url": url, "dbtable": table, "partitionColumn": column, "lowerBound": str(low), "upperBound": str(high), "numPartitions": str(parts)}
