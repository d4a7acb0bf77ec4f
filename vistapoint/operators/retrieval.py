"""The range query: which fields of view overlap an area in a time interval."""

from __future__ import annotations

from functools import reduce
from operator import or_

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..functions import geo
from ..functions.intention import covers, off_axis
from ..plans.query import Area, Query, TimeRange


def overlaps(area: Area) -> Column:
    """Four comparisons on stored columns, so that Parquet statistics and pushed filters apply."""
    return (F.col("max_lat") >= area.min_lat) & (F.col("min_lat") <= area.max_lat) & (F.col("max_lon") >= area.min_lon) & (F.col("min_lon") <= area.max_lon)


def in_time(time: TimeRange, column: str = "t") -> Column:
    test = F.lit(True)
    if time.lo is not None:
        test = test & (F.col(column) >= F.lit(time.lo).cast("timestamp_ntz"))
    if time.hi is not None:
        test = test & (F.col(column) < F.lit(time.hi).cast("timestamp_ntz"))
    return test


def fovs_in_range(fovs: DataFrame, area: Area, time: TimeRange = TimeRange(), refine: bool = False) -> DataFrame:  # noqa: B008
    """Fields of view (with bounding boxes) that overlap the area. Where the store has a day column, its partitions are pruned.

    refine also drops those whose box overlaps, but whose pie or disc does not.
    """
    found = fovs.where(overlaps(area) & in_time(time))
    if "day" in fovs.columns and time.lo is not None:
        found = found.where(F.col("day") >= F.lit(time.lo.date()))
    if "day" in fovs.columns and time.hi is not None:
        found = found.where(F.col("day") <= F.lit(time.hi.date()))
    return found.where(shape_meets(area)) if refine else found


def shape_meets(area: Area) -> Column:
    """Whether a pie or disc and an upright box have a point in common, in the plane of the camera's latitude; exact.

    They do if the camera lies in the box, a corner of the box in the shape, one of the two straight borders crosses the
    box, or the arc crosses one of the four sides. For a disc, the point of the box nearest to the camera decides.
    """
    mx, my = geo.east_scale_at(F.col("lat")), F.lit(geo.METRES_PER_DEGREE)
    west, east = (F.lit(area.min_lon) - F.col("lon")) * mx, (F.lit(area.max_lon) - F.col("lon")) * mx
    south, north = (F.lit(area.min_lat) - F.col("lat")) * my, (F.lit(area.max_lat) - F.col("lat")) * my
    r, theta, alpha = F.col("r_m"), F.col("theta"), F.col("alpha")
    zero = F.lit(0.0)
    within = lambda x, y: (x >= west) & (x <= east) & (y >= south) & (y <= north)
    tests = [within(zero, zero), *[covers(x, y, theta, r, alpha) for x in (west, east) for y in (south, north)]]
    for turn in (-0.5, 0.5):
        azimuth = F.radians(theta + alpha * turn)
        ux, uy = F.sin(azimuth), F.cos(azimuth)
        # The part of the border inside each slab; a border along a slab is wholly in or out of it.
        lows, highs = [zero], [r]
        for u, lo, hi in ((ux, west, east), (uy, south, north)):
            flat, out = F.abs(u) < 1e-12, (lo > 0) | (hi < 0)
            safe = F.when(flat, 1.0).otherwise(u)
            lows.append(F.when(flat, F.when(out, r + 1).otherwise(zero)).otherwise(F.least(lo / safe, hi / safe)))
            highs.append(F.when(flat, r).otherwise(F.greatest(lo / safe, hi / safe)))
        tests.append(F.greatest(*lows) <= F.least(*highs))
    ahead = lambda x, y: off_axis(x, y, theta) <= alpha / 2
    for c in (west, east):
        for sign in (-1.0, 1.0):
            y = F.sqrt(F.greatest(r * r - c * c, zero)) * sign
            tests.append((F.abs(c) <= r) & (y >= south) & (y <= north) & ahead(c, y))
    for c in (south, north):
        for sign in (-1.0, 1.0):
            x = F.sqrt(F.greatest(r * r - c * c, zero)) * sign
            tests.append((F.abs(c) <= r) & (x >= west) & (x <= east) & ahead(x, c))
    near_x, near_y = F.greatest(F.least(zero, east), west), F.greatest(F.least(zero, north), south)
    return F.when(alpha >= 360.0, geo.distance(near_x, near_y) <= r).otherwise(reduce(or_, tests))


def candidates(fovs: DataFrame, query: Query) -> DataFrame:
    return fovs_in_range(fovs, query.area, query.time)


def latest_before(fovs: DataFrame, questions: DataFrame) -> DataFrame:
    """video_id, at, fov_id: each video's latest field of view at or before each asked time (video_id, at); null if it has none yet.

    One pass over both tables in the order of time, so no answer lies too far back to be found.
    """
    seen = fovs.select("video_id", F.col("t").alias("at"), "fov_id", F.lit(0).alias("asks"))
    asked = questions.select("video_id", "at", F.lit(None).cast("long").alias("fov_id"), F.lit(1).alias("asks"))
    so_far = Window.partitionBy("video_id").orderBy("at", "asks", "fov_id").rowsBetween(Window.unboundedPreceding, Window.currentRow)
    both = seen.unionByName(asked).withColumn("found", F.last("fov_id", ignorenulls=True).over(so_far))
    return both.where("asks = 1").select("video_id", "at", F.col("found").alias("fov_id"))
