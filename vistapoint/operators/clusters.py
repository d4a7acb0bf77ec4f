"""Clusters of camera positions, and the rectangles that stand for them."""

from __future__ import annotations

import numpy as np
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..functions.geo import METRES_PER_DEGREE, east_scale
from ..functions.noise import u01
from ..plans.query import Area, Query
from .retrieval import candidates

Centres = list[tuple[float, float]]
#: Points that are clustered on the driver, 32 bytes each.
DRIVER_ROWS = 200_000


def positions(fovs: DataFrame, query: Query, features: str = "camera") -> DataFrame:
    """fov_id, px, py: metres from the area's south-west corner, of the camera or of the bounding box's centre."""
    lat, lon = (F.col("lat"), F.col("lon")) if features == "camera" else ((F.col("min_lat") + F.col("max_lat")) / 2, (F.col("min_lon") + F.col("max_lon")) / 2)
    return fovs.withColumns({"px": (lon - query.area.min_lon) * F.lit(east_scale(query.lat0)), "py": (lat - query.area.min_lat) * F.lit(METRES_PER_DEGREE)})


def nearest(centres: Centres) -> Column:
    """The number of the centre nearest to (px, py); the first wins ties. There are few centres, so they are literals."""
    d = [F.struct(((F.col("px") - x) * (F.col("px") - x) + (F.col("py") - y) * (F.col("py") - y)).alias("d"), F.lit(i).alias("i")) for i, (x, y) in enumerate(centres)]
    return F.array_min(F.array(*d))["i"]


def first_centres(points: DataFrame, count: int, salt: str = "init") -> Centres:
    """The positions with the smallest hashes."""
    rows = points.orderBy(u01(salt, "fov_id"), "fov_id").limit(count).select("px", "py").collect()
    return [(r.px, r.py) for r in rows]


def lloyd_step(points: DataFrame, centres: Centres) -> Centres:
    """One round of k-means; a centre without points stays. Only as many rows as centres come back."""
    rows = points.groupBy(nearest(centres).alias("i")).agg(F.avg("px").alias("px"), F.avg("py").alias("py")).collect()
    moved = {r.i: (r.px, r.py) for r in rows}
    return [moved.get(i, c) for i, c in enumerate(centres)]


def kmeans(points: DataFrame, count: int, steps: int = 3, salt: str = "init") -> Centres:
    centres = first_centres(points, count, salt)
    for _ in range(steps if centres else 0):
        centres = lloyd_step(points, centres)
    return centres


def kmeans_with_radii(points: DataFrame, count: int, steps: int = 3, salt: str = "init", driver_rows: int | None = None) -> tuple[Centres, DataFrame | None, int]:
    """(centres, ``radii`` of the points, number of points) of ``kmeans``; no radii without points.

    Up to ``driver_rows`` points, two numbers each, are clustered on the driver in one job; more, by jobs. The steps are the same.
    """
    spark, most = points.sparkSession, DRIVER_ROWS if driver_rows is None else driver_rows
    rows = points.select("px", "py", u01(salt, "fov_id").alias("u"), "fov_id").limit(most + 1).toArrow()
    if rows.num_rows > most:
        centres = kmeans(points, count, steps, salt)
        return centres, radii(points, centres), points.count()
    if not rows.num_rows:
        return [], None, 0
    px, py, u, ids = (rows.column(i).to_numpy() for i in range(4))
    first = np.lexsort((ids, u))[:count]
    cx, cy = px[first].copy(), py[first].copy()

    def own() -> np.ndarray:
        return ((px[:, None] - cx) * (px[:, None] - cx) + (py[:, None] - cy) * (py[:, None] - cy)).argmin(axis=1)

    for _ in range(steps):
        at = own()
        n = np.bincount(at, minlength=len(cx))
        sums = [np.bincount(at, v, minlength=len(cx)) for v in (px, py)]
        cx, cy = (np.where(n > 0, s / np.maximum(n, 1), c) for s, c in zip(sums, (cx, cy), strict=True))
    at = own()
    n = np.bincount(at, minlength=len(cx))
    square = np.bincount(at, (px - cx[at]) * (px - cx[at]) + (py - cy[at]) * (py - cy[at]), minlength=len(cx))
    table = [(i, float(cx[i]), float(cy[i]), int(n[i]), float(np.sqrt(square[i] / n[i]))) for i in range(len(cx)) if n[i]]
    return list(zip(cx.tolist(), cy.tolist(), strict=True)), spark.createDataFrame(table, "cluster_id int, cx double, cy double, n long, rms_m double"), rows.num_rows


def kmeans_ml(points: DataFrame, count: int, max_iter: int = 20, seed: int = 1, sample: int = 5_000_000) -> Centres:
    """k-means|| by Spark's machine-learning library, on at most ``sample`` hashed rows, since only the centres are wanted."""
    from pyspark.ml.clustering import KMeans
    from pyspark.ml.feature import VectorAssembler

    n = points.count()
    some = points if n <= sample else points.where(u01("kmeans", "fov_id") < sample / n)
    model = KMeans(k=count, maxIter=max_iter, seed=seed).fit(VectorAssembler(inputCols=["px", "py"], outputCol="features").transform(some.select("px", "py")))
    return [(float(c[0]), float(c[1])) for c in model.clusterCenters()]


def radii(points: DataFrame, centres: Centres) -> DataFrame:
    """cluster_id, cx, cy, n, rms_m: the root mean squared distance of the members from their centre."""
    own = points.withColumn("cluster_id", nearest(centres))
    cx = F.element_at(F.array(*[F.lit(c[0]) for c in centres]), F.col("cluster_id") + 1)
    cy = F.element_at(F.array(*[F.lit(c[1]) for c in centres]), F.col("cluster_id") + 1)
    own = own.withColumns({"cx": cx, "cy": cy})
    square = (F.col("px") - F.col("cx")) * (F.col("px") - F.col("cx")) + (F.col("py") - F.col("cy")) * (F.col("py") - F.col("cy"))
    return own.groupBy("cluster_id").agg(F.first("cx").alias("cx"), F.first("cy").alias("cy"), F.count("*").alias("n"), F.sqrt(F.avg(square)).alias("rms_m"))


def rectangles(radii: DataFrame, query: Query) -> DataFrame:
    """Centre plus and minus the radius, clipped to the area (degrees), with its inclusive range of cells; empty ones go."""
    a, g = query.area, query.grid
    mx, my = F.lit(east_scale(query.lat0)), F.lit(METRES_PER_DEGREE)
    out = radii.withColumns(
        {
            "r_min_lon": F.greatest(F.lit(a.min_lon), F.lit(a.min_lon) + (F.col("cx") - F.col("rms_m")) / mx),
            "r_max_lon": F.least(F.lit(a.max_lon), F.lit(a.min_lon) + (F.col("cx") + F.col("rms_m")) / mx),
            "r_min_lat": F.greatest(F.lit(a.min_lat), F.lit(a.min_lat) + (F.col("cy") - F.col("rms_m")) / my),
            "r_max_lat": F.least(F.lit(a.max_lat), F.lit(a.min_lat) + (F.col("cy") + F.col("rms_m")) / my),
        }
    ).where("r_min_lon <= r_max_lon and r_min_lat <= r_max_lat")
    cell = lambda v, origin, n: F.least(F.greatest(F.floor((F.col(v) - origin) / g.cell), F.lit(0)), F.lit(n - 1)).cast("long")
    return out.withColumns({"cx0": cell("r_min_lon", a.min_lon, g.nx), "cx1": cell("r_max_lon", a.min_lon, g.nx), "cy0": cell("r_min_lat", a.min_lat, g.ny), "cy1": cell("r_max_lat", a.min_lat, g.ny)})


def members(fovs: DataFrame, rects: DataFrame) -> DataFrame:
    """Fields of view that overlap each rectangle; one may serve several. There are as many rectangles as clusters, so they are broadcast."""
    hit = (F.col("max_lat") >= F.col("r_min_lat")) & (F.col("min_lat") <= F.col("r_max_lat")) & (F.col("max_lon") >= F.col("r_min_lon")) & (F.col("min_lon") <= F.col("r_max_lon"))
    return fovs.join(F.broadcast(rects.select("cluster_id", "r_min_lon", "r_max_lon", "r_min_lat", "r_max_lat", "cx0", "cx1", "cy0", "cy1")), hit)


def in_area(fovs: DataFrame, query: Query) -> DataFrame:
    """Fields of view in range, with their positions."""
    return positions(candidates(fovs, query), query)


__all__ = ["Area", "Centres", "first_centres", "in_area", "kmeans", "kmeans_ml", "kmeans_with_radii", "lloyd_step", "members", "nearest", "positions", "radii", "rectangles"]
