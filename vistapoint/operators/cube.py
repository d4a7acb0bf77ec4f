"""An additive cube of intentions by cell and day: matrices add up over fields of view, hence over days.

It holds for one grid, model and pair of sigmas. A query over days then sums a few rows per cell and touches no field of view.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..plans.query import Query
from .matrix import exploded
from .retrieval import candidates


def build(fovs: DataFrame, query: Query, unit: str = "day") -> DataFrame:
    """day, cell_x, cell_y, ci_fixed."""
    dated = candidates(fovs, query).withColumn("day", F.date_trunc(unit, F.col("t").cast("timestamp")).cast("date"))
    return exploded(dated, query, ("day",)).groupBy("day", "cell_x", "cell_y").agg(F.sum("ci_fixed").alias("ci_fixed"))


def add(cube: DataFrame, more: DataFrame) -> DataFrame:
    """A cube with newly arrived rows."""
    return cube.unionByName(more).groupBy("day", "cell_x", "cell_y").agg(F.sum("ci_fixed").alias("ci_fixed"))


def over(cube: DataFrame, first: str | None = None, last: str | None = None) -> DataFrame:
    """The matrix of a range of days, both ends included."""
    rows = cube
    if first:
        rows = rows.where(F.col("day") >= F.lit(first).cast("date"))
    if last:
        rows = rows.where(F.col("day") <= F.lit(last).cast("date"))
    return rows.groupBy("cell_x", "cell_y").agg(F.sum("ci_fixed").alias("ci_fixed"))
