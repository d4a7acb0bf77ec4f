"""Fields of view derived from the given tables, which have no coordinates of their own. All noise is deterministic."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions.geo import METRES_PER_DEGREE, east_scale
from ..functions.noise import u01
from ..operators.fov import angle_of, range_of

CENTRE = (10.0, 20.0)
NOISE_HALF = 0.175
# Twelve planted spots, degrees from the centre (lat, lon).
SPOTS = ((0.0, 0.0), (0.0021, -0.0018), (-0.0024, 0.0015), (0.012, 0.016), (-0.018, 0.009), (0.015, -0.02), (0.045, 0.03), (-0.04, -0.05), (0.03, -0.045), (0.12, 0.1), (-0.14, 0.06), (0.09, -0.15))
JITTER_M = 160.0


def _pick(values: list[float], at: Column) -> Column:
    return F.element_at(F.array(*[F.lit(v) for v in values]), (at + 1).cast("int"))


def _placed(rows: DataFrame, noisy: Column, variant: str, key: str = "fov_id", centre: tuple[float, float] = CENTRE, extra: tuple[str, ...] = ()) -> DataFrame:
    """From spot_lat, spot_lon, away_m, aim (degrees off the subject): camera, azimuth, distance, angle."""
    mx, my = F.lit(east_scale(centre[0])), F.lit(METRES_PER_DEGREE)
    brg = F.lit(360.0) * u01("brg", key)
    lat = F.when(noisy, F.lit(centre[0] - NOISE_HALF) + F.lit(2 * NOISE_HALF) * u01("y", key)).otherwise(F.col("spot_lat") + F.col("away_m") * F.cos(F.radians(brg)) / my)
    lon = F.when(noisy, F.lit(centre[1] - NOISE_HALF) + F.lit(2 * NOISE_HALF) * u01("x", key)).otherwise(F.col("spot_lon") + F.col("away_m") * F.sin(F.radians(brg)) / mx)
    theta = F.when(noisy, brg).otherwise(F.pmod(brg + 180.0 + F.col("aim"), F.lit(360.0)))
    return rows.select(F.col("fov_id"), "video_id", lat.alias("lat"), lon.alias("lon"), theta.alias("theta"), range_of(u01("rad", "video_id")).alias("r_m"), angle_of(variant, u01("ang", key)).alias("alpha"), "t", *extra)


def from_events(spark: SparkSession, sf_dir: str, variant: str = "pie60", jitter_m: float = JITTER_M, centre: tuple[float, float] = CENTRE) -> DataFrame:
    """One field of view per event; users are videos, event values the distance to one of twelve skewed spots, errors are noise."""
    return events_to_fovs(spark.read.parquet(f"{sf_dir}/events.parquet"), variant, jitter_m, centre)


def events_to_fovs(events: DataFrame, variant: str = "pie60", jitter_m: float = JITTER_M, centre: tuple[float, float] = CENTRE) -> DataFrame:
    mx, my = F.lit(east_scale(centre[0])), F.lit(METRES_PER_DEGREE)
    spot = F.floor(F.lit(12.0) * F.pow(u01("hot", "user_id"), F.lit(1.5)))
    aim = (F.get_json_object("props", "$.k").cast("int") - F.lit(49.5)) * F.lit(0.6)
    rows = events.select(
        F.col("event_id").cast("long").alias("fov_id"),
        F.col("user_id").cast("long").alias("video_id"),
        F.col("ts").alias("t"),
        (F.lit(centre[0]) + _pick([s[0] for s in SPOTS], spot) + (u01("jy", "user_id") - 0.5) * jitter_m / my).alias("spot_lat"),
        (F.lit(centre[1]) + _pick([s[1] for s in SPOTS], spot) + (u01("jx", "user_id") - 0.5) * jitter_m / mx).alias("spot_lon"),
        F.col("value").alias("away_m"),
        aim.alias("aim"),
        (F.col("event_type") == "error").alias("noisy"),
    )
    return _placed(rows, F.col("noisy"), variant, centre=centre)


def _lattice(rows: DataFrame) -> DataFrame:
    pitch = 0.06
    return rows.withColumns({"spot_lat": F.lit(CENTRE[0]) + (F.floor(F.col("nation") / 5) - 2) * F.lit(pitch), "spot_lon": F.lit(CENTRE[1]) + (F.col("nation") % 5 - 2) * F.lit(pitch)})


def from_orders(spark: SparkSession, sf_dir: str, variant: str = "pie60") -> DataFrame:
    """One field of view per order; customers are videos, nations a lattice of 25 spots. Region and nation stay as columns."""
    read = lambda name: spark.read.parquet(f"{sf_dir}/{name}.parquet")
    places = read("nation").join(read("region"), F.col("n_regionkey") == F.col("r_regionkey")).select("n_nationkey", "n_name", "r_name")
    rows = read("orders").join(read("customer").select("c_custkey", "c_nationkey"), F.col("o_custkey") == F.col("c_custkey")).join(F.broadcast(places), F.col("c_nationkey") == F.col("n_nationkey"))
    rows = rows.select(
        F.col("o_orderkey").cast("long").alias("fov_id"),
        F.col("o_custkey").cast("long").alias("video_id"),
        F.col("o_orderdate").cast("timestamp_ntz").alias("t"),
        F.col("c_nationkey").cast("long").alias("nation"),
        (1.0 + 0.0002 * F.col("o_totalprice").cast("double")).alias("away_m"),
        ((u01("aim", "o_orderkey") - 0.5) * 60.0).alias("aim"),
        (F.col("o_orderpriority") == "5-LOW").alias("noisy"),
        F.col("n_name").alias("nation_name"),
        F.col("r_name").alias("region_name"),
    )
    return _placed(_lattice(rows), F.col("noisy"), variant, extra=("nation_name", "region_name"))


def from_lineitem(spark: SparkSession, sf_dir: str, variant: str = "pie60") -> DataFrame:
    """One field of view per order line, whose id is hashed from its four keys."""
    read = lambda name: spark.read.parquet(f"{sf_dir}/{name}.parquet")
    orders = read("orders").select("o_orderkey", "o_custkey", "o_orderpriority").join(read("customer").select("c_custkey", "c_nationkey"), F.col("o_custkey") == F.col("c_custkey"))
    rows = read("lineitem").join(orders, F.col("l_orderkey") == F.col("o_orderkey"))
    key = F.concat_ws(":", *[F.col(c).cast("string") for c in ("l_orderkey", "l_partkey", "l_suppkey", "l_linenumber")])
    rows = rows.select(
        F.conv(F.substring(F.md5(key.cast("binary")), 1, 13), 16, 10).cast("long").alias("fov_id"),
        F.col("o_custkey").cast("long").alias("video_id"),
        F.col("l_shipdate").cast("timestamp_ntz").alias("t"),
        F.col("c_nationkey").cast("long").alias("nation"),
        (3.0 * F.col("l_quantity").cast("double")).alias("away_m"),
        ((F.col("l_discount").cast("double") - 0.05) * 600.0).alias("aim"),
        (F.col("o_orderpriority") == "5-LOW").alias("noisy"),
    )
    return _placed(_lattice(rows), F.col("noisy"), variant)


def spots(spark: SparkSession) -> DataFrame:
    """The planted spots: mark_id, mark_lat, mark_lon."""
    return spark.createDataFrame([(i, CENTRE[0] + a, CENTRE[1] + b) for i, (a, b) in enumerate(SPOTS)], "mark_id long, mark_lat double, mark_lon double")
