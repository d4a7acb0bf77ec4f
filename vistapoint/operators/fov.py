"""Fields of view: validation, optics, bounding boxes, coverage, dataset variants, videos."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..functions import geo
from ..functions.intention import covers
from ..functions.noise import u01

# 20 mid-quantiles of the Gamma law (1.6, 0.4) cut at 2.
GAMMA20 = (0.052, 0.108, 0.156, 0.200, 0.243, 0.287, 0.331, 0.377, 0.424, 0.474, 0.528, 0.585, 0.648, 0.718, 0.798, 0.889, 1.000, 1.140, 1.335, 1.665)
VARIANTS = {"pie60": None, "mix30": 0.3, "mix70": 0.7}
COLUMNS = ("fov_id", "video_id", "lat", "lon", "theta", "r_m", "alpha", "t")


def visible_distance(focal: Column, height: Column, pixels: Column, image_height: float) -> Column:
    """How far a camera sees an object of a given height: focal length times height over image height of the object, which counts as 1/20 of the image at least."""
    return focal * height / F.greatest(pixels, F.lit(image_height / 20))


def visible_angle(sensor_width: Column, focal: Column) -> Column:
    return F.degrees(F.lit(2.0) * F.atan(sensor_width / (F.lit(2.0) * focal)))


def check_fov(fovs: DataFrame) -> DataFrame:
    """The rows that are no valid field of view, with the reason. An empty result means that the table is sound."""
    rules = {
        "id": F.col("fov_id").isNull(),
        "position": ~F.coalesce((F.abs("lat") <= 90) & (F.abs("lon") <= 180), F.lit(False)),
        "azimuth": ~F.coalesce((F.col("theta") >= 0) & (F.col("theta") < 360), F.lit(False)),
        "distance": ~F.coalesce((F.col("r_m") > 0) & (F.col("r_m") < float("inf")), F.lit(False)),
        "angle": ~F.coalesce((F.col("alpha") > 0) & (F.col("alpha") <= 360), F.lit(False)),
    }
    reason = F.coalesce(*[F.when(test, F.lit(name)) for name, test in rules.items()])
    wrong = fovs.withColumn("reason", reason).where("reason is not null").select("fov_id", "reason")
    double = fovs.where("fov_id is not null").groupBy("fov_id").count().where("count > 1").select("fov_id", F.lit("duplicate").alias("reason"))
    return wrong.union(double)


def extent(theta: Column, r_m: Column, alpha: Column) -> tuple[Column, Column, Column, Column]:
    """(west, east, south, north) of a pie or disc in metres from its camera: apex, both ends of the arc, and each of the four directions that the angle holds."""
    half = alpha / 2
    ends = [F.radians(theta - half), F.radians(theta + half)]
    xs = [F.lit(0.0), *[r_m * F.sin(e) for e in ends]]
    ys = [F.lit(0.0), *[r_m * F.cos(e) for e in ends]]
    whole = alpha >= 360.0
    holds = lambda azimuth: whole | (geo.angle_diff(theta, F.lit(azimuth)) <= half)
    west = F.when(holds(270.0), -r_m).otherwise(F.least(*xs))
    east = F.when(holds(90.0), r_m).otherwise(F.greatest(*xs))
    south = F.when(holds(180.0), -r_m).otherwise(F.least(*ys))
    north = F.when(holds(0.0), r_m).otherwise(F.greatest(*ys))
    return west, east, south, north


def with_mbr(fovs: DataFrame, mode: str = "exact") -> DataFrame:
    """min_lat, max_lat, min_lon, max_lon of each field of view, in the plane at its own latitude; mode circle takes the box of the whole disc."""
    r = F.col("r_m")
    west, east, south, north = extent(F.col("theta"), r, F.col("alpha")) if mode == "exact" else (-r, r, -r, r)
    mx, my = geo.east_scale_at(F.col("lat")), F.lit(geo.METRES_PER_DEGREE)
    return fovs.withColumns({"min_lat": F.col("lat") + south / my, "max_lat": F.col("lat") + north / my, "min_lon": F.col("lon") + west / mx, "max_lon": F.col("lon") + east / mx})


def sees(lat: Column, lon: Column) -> Column:
    """Whether each field of view covers a point, in the plane at the camera's latitude."""
    dx, dy = (lon - F.col("lon")) * geo.east_scale_at(F.col("lat")), (lat - F.col("lat")) * F.lit(geo.METRES_PER_DEGREE)
    return covers(dx, dy, F.col("theta"), F.col("r_m"), F.col("alpha"))


def range_of(noise: Column, scale: float = 0.35) -> Column:
    """A visible distance in metres from the quantile list of the Gamma law."""
    return F.lit(1000.0) * F.lit(scale) * F.element_at(F.array(*[F.lit(g) for g in GAMMA20]), (F.floor(noise * 20) + 1).cast("int"))


def assign_range(fovs: DataFrame, scale: float = 0.35, by: str = "video_id") -> DataFrame:
    return fovs.withColumn("r_m", range_of(u01("rad", by), scale))


def angle_of(variant: str, noise: Column) -> Column:
    """Visible angle of a dataset variant: always 60, or a share of 160 and the rest full circles."""
    share = VARIANTS[variant]
    return F.lit(60.0) if share is None else F.when(noise < share, 160.0).otherwise(360.0)


def assign_angle(fovs: DataFrame, variant: str, by: str = "fov_id") -> DataFrame:
    """by: fov_id draws for every field of view, video_id once for a video."""
    return fovs.withColumn("alpha", angle_of(variant, u01("ang", by)))


def sample_video(fovs: DataFrame, every: str = "second") -> DataFrame:
    """The first field of view of every second (or other unit) of each video."""
    w = Window.partitionBy("video_id", F.date_trunc(every, F.col("t").cast("timestamp"))).orderBy("t", "fov_id")
    return fovs.withColumn("_n", F.row_number().over(w)).where("_n = 1").drop("_n")


def trajectory(fovs: DataFrame) -> DataFrame:
    """fov_id, video_id, step (place in its video) and step_m (metres from the field of view before; null for the first)."""
    w = Window.partitionBy("video_id").orderBy("t", "fov_id")
    dx = (F.col("lon") - F.lag("lon").over(w)) * geo.east_scale_at(F.col("lat"))
    dy = (F.col("lat") - F.lag("lat").over(w)) * F.lit(geo.METRES_PER_DEGREE)
    return fovs.select("fov_id", "video_id", F.row_number().over(w).cast("long").alias("step"), geo.distance(dx, dy).alias("step_m"))


def range_histogram(fovs: DataFrame, landmarks: DataFrame, width_m: float = 50.0, far_m: float = 2000.0) -> DataFrame:
    """bucket, n: distances between landmarks (mark_id, mark_lat, mark_lon) and the fields of view that see them."""
    dx = (F.col("mark_lon") - F.col("lon")) * geo.east_scale_at(F.col("lat"))
    dy = (F.col("mark_lat") - F.col("lat")) * F.lit(geo.METRES_PER_DEGREE)
    d = geo.distance(dx, dy)
    near = fovs.join(F.broadcast(landmarks), (F.col("mark_lat") >= F.col("min_lat")) & (F.col("mark_lat") <= F.col("max_lat")) & (F.col("mark_lon") >= F.col("min_lon")) & (F.col("mark_lon") <= F.col("max_lon")))
    seen = near.where(covers(dx, dy, F.col("theta"), F.col("r_m"), F.col("alpha")) & (d < far_m))
    return seen.groupBy(F.floor(d / width_m).alias("bucket")).agg(F.count("*").alias("n"))
