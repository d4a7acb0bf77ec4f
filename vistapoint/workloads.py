"""All registered queries of the library, on the given tables, and the SQL that each must equal where SQL can express it."""

from __future__ import annotations

import datetime as dt
from collections.abc import Callable
from dataclasses import replace

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from . import oracles as O
from .functions import geo
from .functions import intention as I
from .functions.noise import u01, u01_sql
from .operators import clusters, cube, fov, matrix, measures, retrieval, sampler, sampling
from .operators.detect import detect
from .plans.query import Area, ClusterOptions, Query, TimeRange
from .session import kept, ship
from .sources import carriers

#: Half sides, in degrees, of the target regions around the centre.
REGIONS = {"t0": 0.0015, "t1": 0.004, "t2": 0.025, "t3": 0.06, "t4": 0.175}
QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {}
SQL: dict[str, str] = {}


def region(name: str, **options) -> Query:
    return Query(Area.around(*carriers.CENTRE, REGIONS[name]), **options)


T0, T1, T2, T3, T4 = (region(f"t{i}") for i in range(5))


def register(name: str, run: Callable[[SparkSession, str], DataFrame], sql: str | None = None) -> None:
    def shipped(spark: SparkSession, sf_dir: str) -> DataFrame:
        ship(spark)
        return run(spark, sf_dir)

    QUERIES[name] = shipped
    if sql is not None:
        SQL[name] = sql


def events(spark: SparkSession, sf_dir: str, variant: str = "pie60", centre: tuple[float, float] = carriers.CENTRE) -> DataFrame:
    """Fields of view with their boxes, stored, as a table of them would be: derived anew, a position is an expression of
    hashes, which predicates would repeat until the generated code is too long to be compiled. Events are few bytes and much
    work each, so they are spread over the tasks and not left in a file's few splits."""
    spread = table(spark, sf_dir, "events").repartition("event_id")
    return kept(fov.with_mbr(carriers.events_to_fovs(spread, variant, centre=centre)))


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def rounded(df: DataFrame, digits: int = 6) -> DataFrame:
    return df.select([F.round(c, digits).alias(c) if t == "double" else F.col(c) for c, t in df.dtypes])


def rounded_sql(sql: str, columns: str, doubles: str) -> str:
    plain = ", ".join(c for c in columns.split() if c)
    return f"SELECT {plain}{', ' if plain else ''}{', '.join(f'round({c}, 6) AS {c}' for c in doubles.split())} FROM ({sql})"


# --- geometry and preparation -------------------------------------------------------------------------------------------

FOV_E, FOV_O, FOV_L = O.fov_events(), O.fov_orders(), O.fov_lineitem()
SHAPE = "lat lon theta r_m alpha"
register("q_fov_events", lambda s, d: rounded(carriers.from_events(s, d)), rounded_sql(FOV_E, "fov_id video_id t", SHAPE))
register("q_fov_orders", lambda s, d: rounded(carriers.from_orders(s, d)), rounded_sql(FOV_O, "fov_id video_id t nation_name region_name", SHAPE))
register("q_fov_lineitem", lambda s, d: rounded(carriers.from_lineitem(s, d)), rounded_sql(FOV_L, "fov_id video_id t", SHAPE))


def _local(s, d):
    x, y = geo.to_local(F.col("lat"), F.col("lon"), *carriers.CENTRE, 10.0)
    return carriers.from_events(s, d).select("fov_id", x.alias("east_m"), y.alias("north_m"))


LOCAL = f"SELECT fov_id, (lon - 20.0::DOUBLE) * {O.MX} AS east_m, (lat - 10.0::DOUBLE) * {O.MY} AS north_m, theta FROM ({FOV_E})"
register("q_project", lambda s, d: rounded(_local(s, d)), rounded_sql(LOCAL, "fov_id", "east_m north_m"))
register("q_bearing", lambda s, d: rounded(_local(s, d).select("fov_id", geo.bearing(F.col("east_m"), F.col("north_m")).alias("azimuth"))), f"SELECT fov_id, round({O.pmod360('degrees(atan2(east_m, north_m))')}, 6) AS azimuth FROM ({LOCAL})")
register("q_angle_diff", lambda s, d: rounded(carriers.from_events(s, d).select("fov_id", geo.angle_diff(F.col("theta"), F.lit(350.0)).alias("off"))), f"SELECT fov_id, round({O.angle_diff('theta', '350.0::DOUBLE')}, 6) AS off FROM ({FOV_E})")
register(
    "q_distance",
    lambda s, d: rounded(carriers.from_events(s, d).select("fov_id", geo.haversine(F.col("lat"), F.col("lon"), F.lit(10.0), F.lit(20.0)).alias("great_circle_m")).join(_local(s, d).select("fov_id", geo.distance(F.col("east_m"), F.col("north_m")).alias("local_m")), "fov_id"), 4),
    f"SELECT fov_id, round({O.haversine('lat', 'lon', '10.0::DOUBLE', '20.0::DOUBLE')}, 4) AS great_circle_m, round(sqrt(east_m * east_m + north_m * north_m), 4) AS local_m FROM ({FOV_E}) JOIN (SELECT fov_id, east_m, north_m FROM ({LOCAL})) USING (fov_id)",
)
register("q_visible_distance", lambda s, d: rounded(table(s, d, "part").select("p_partkey", fov.visible_distance(F.lit(35.0), F.col("p_size") / 2, F.col("p_size") % 7 * 10.0, 480.0).alias("r_m"))), "SELECT p_partkey, round(35.0::DOUBLE * (p_size / 2.0::DOUBLE) / greatest(p_size % 7 * 10.0::DOUBLE, 24.0::DOUBLE), 6) AS r_m FROM part")
register("q_visible_angle", lambda s, d: rounded(table(s, d, "part").select("p_partkey", fov.visible_angle(F.lit(36.0), F.col("p_size") + 15.0).alias("alpha"))), "SELECT p_partkey, round(degrees(2.0::DOUBLE * atan(36.0::DOUBLE / (2.0::DOUBLE * (p_size + 15.0::DOUBLE)))), 6) AS alpha FROM part")
BOX = "min_lat max_lat min_lon max_lon"
for _v in fov.VARIANTS:
    register(f"q_fov_mbr_{_v}", lambda s, d, v=_v: rounded(events(s, d, v).select("fov_id", *BOX.split()), 9), f"SELECT fov_id, {', '.join(f'round({c}, 9) AS {c}' for c in BOX.split())} FROM ({O.fov_with_mbr(_v)})")
register("q_fov_mbr_circle", lambda s, d: rounded(fov.with_mbr(carriers.from_events(s, d), "circle").select("fov_id", *BOX.split()), 9), f"SELECT fov_id, {', '.join(f'round({c}, 9) AS {c}' for c in BOX.split())} FROM ({O.mbr(FOV_E, 'circle')})")
REL = f"(SELECT *, (20.0::DOUBLE - lon) * {O.OWN} AS dx, (10.0::DOUBLE - lat) * {O.MY} AS dy FROM ({O.fov_with_mbr('mix30')}))"
OFF = f"CASE WHEN dx = 0 AND dy = 0 THEN 0.0::DOUBLE ELSE {O.angle_diff(O.pmod360('degrees(atan2(dx, dy))'), 'theta')} END"
register("q_fov_covers", lambda s, d: events(s, d, "mix30").where(fov.sees(F.lit(10.0), F.lit(20.0))).select("fov_id", "alpha"), f"SELECT fov_id, alpha FROM {REL} WHERE sqrt(dx * dx + dy * dy) <= r_m AND (alpha >= 360 OR ({OFF}) <= alpha / 2)")
register("q_check_fov", lambda s, d: fov.check_fov(carriers.from_events(s, d).union(carriers.from_events(s, d).where("fov_id % 100 = 0"))), "SELECT event_id AS fov_id, 'duplicate' AS reason FROM events WHERE event_id % 100 = 0")
register("q_assign_range", lambda s, d: rounded(fov.assign_range(carriers.from_events(s, d).drop("r_m"), 0.5).select("fov_id", "r_m")), f"SELECT event_id AS fov_id, round(1000.0::DOUBLE * 0.5::DOUBLE * {O._list(fov.GAMMA20)}[floor({u01_sql('rad', 'user_id')} * 20)::INT + 1], 6) AS r_m FROM events")
register("q_assign_angle", lambda s, d: fov.assign_angle(carriers.from_events(s, d).drop("alpha"), "mix70", "video_id").groupBy("alpha").agg(F.count("*").alias("n")), f"SELECT alpha, count(*) AS n FROM (SELECT {O.alpha('mix70', u01_sql('ang', 'user_id'))} AS alpha FROM events) GROUP BY alpha")
register("q_u01", lambda s, d: table(s, d, "events").select("event_id", F.round(u01("probe", "event_id", "user_id"), 12).alias("u")), f"SELECT event_id, round({u01_sql('probe', 'event_id', 'user_id')}, 12) AS u FROM events")
register("q_frame_thinning", lambda s, d: fov.sample_video(carriers.from_events(s, d), "hour").groupBy("video_id").agg(F.count("*").alias("n"), F.sum("fov_id").alias("ids")), "SELECT user_id AS video_id, count(*) AS n, sum(event_id)::BIGINT AS ids FROM (SELECT *, row_number() OVER (PARTITION BY user_id, date_trunc('hour', ts) ORDER BY ts, event_id) AS r FROM events) WHERE r = 1 GROUP BY user_id")
register(
    "q_trajectory",
    lambda s, d: rounded(fov.trajectory(carriers.from_events(s, d)), 4),
    f"SELECT fov_id, video_id, row_number() OVER w AS step, round(sqrt(pow((lon - lag(lon) OVER w) * {O.OWN}, 2) + pow((lat - lag(lat) OVER w) * {O.MY}, 2)), 4) AS step_m FROM ({FOV_E}) WINDOW w AS (PARTITION BY video_id ORDER BY t, fov_id)",
)
MARKS = "(VALUES " + ", ".join(f"({i}::BIGINT, {10.0 + a!r}::DOUBLE, {20.0 + b!r}::DOUBLE)" for i, (a, b) in enumerate(carriers.SPOTS)) + ") AS marks(mark_id, mark_lat, mark_lon)"
SEEN = f"SELECT *, sqrt(dx * dx + dy * dy) AS d FROM (SELECT *, (mark_lon - lon) * {O.OWN} AS dx, (mark_lat - lat) * {O.MY} AS dy FROM ({O.fov_with_mbr('mix30')}), {MARKS}) WHERE sqrt(dx * dx + dy * dy) <= r_m AND (alpha >= 360 OR ({OFF}) <= alpha / 2)"
register("q_range_histogram", lambda s, d: fov.range_histogram(events(s, d, "mix30"), carriers.spots(s)), f"SELECT floor(d / 50.0::DOUBLE)::BIGINT AS bucket, count(*) AS n FROM ({SEEN}) WHERE d < 2000 GROUP BY 1")
register("q_landmark_views", lambda s, d: events(s, d, "mix30").join(F.broadcast(carriers.spots(s)), fov.sees(F.col("mark_lat"), F.col("mark_lon"))).groupBy("mark_id").agg(F.count("*").alias("views"), F.countDistinct("video_id").alias("videos")), f"SELECT mark_id, count(*) AS views, count(DISTINCT video_id) AS videos FROM ({SEEN}) GROUP BY mark_id")

# --- intention models ---------------------------------------------------------------------------------------------------

register("q_ci_angle", lambda s, d: rounded(carriers.from_events(s, d, "mix30").select("fov_id", I.ci_angle(geo.angle_diff(F.col("theta"), F.lit(0.0)), F.col("alpha")).alias("ci")), 12), f"SELECT fov_id, round(CASE WHEN alpha >= 360 THEN 1.0::DOUBLE WHEN a <= alpha / 2 THEN exp(-(a * a) / 450.0::DOUBLE) * {O.PEAKS[15.0]!r}::DOUBLE ELSE 0.0::DOUBLE END, 12) AS ci FROM (SELECT *, {O.angle_diff('theta', '0.0::DOUBLE')} AS a FROM ({O.fov_events('mix30')}))")
register("q_ci_dist", lambda s, d: rounded(table(s, d, "events").select("event_id", I.ci_dist(F.col("value"), F.lit(100.0)).alias("ci")), 12), f"SELECT event_id, round(CASE WHEN value <= 100 THEN exp(-(value * value) / 1250.0::DOUBLE) * {O.PEAKS[25.0]!r}::DOUBLE ELSE 0.0::DOUBLE END, 12) AS ci FROM events")


def _ci_pairs(s, d):
    dx, dy = (F.lit(20.0) - F.col("lon")) * geo.east_scale_at(F.col("lat")), (F.lit(10.0) - F.col("lat")) * F.lit(geo.METRES_PER_DEGREE)
    return events(s, d, "mix30").select("fov_id", F.round(I.fixed(I.intention(dx, dy, F.col("theta"), F.col("r_m"), F.col("alpha"))) / I.FIXED, 9).alias("ci")).where("ci > 0")


register("q_ci_pairs", _ci_pairs, f"SELECT * FROM (SELECT fov_id, round(({O.ci_columns(T1)}) / 1e12::DOUBLE, 9) AS ci FROM {REL}) WHERE ci > 0")

# --- detection ----------------------------------------------------------------------------------------------------------


def top(s, d, query, variant="pie60", method="optimized", **options):
    return detect(events(s, d, variant), query, method, **options)


JANUARY = TimeRange(dt.datetime(2024, 1, 8), dt.datetime(2024, 1, 15))
JANUARY_SQL = "t >= TIMESTAMP '2024-01-08' AND t < TIMESTAMP '2024-01-15'"
register("q_topk_optimized", lambda s, d: top(s, d, T1), O.top_of(T1, "pie60"))
register("q_topk_naive", lambda s, d: top(s, d, T0, method="naive"), O.top_of(T0, "pie60"))
for _v in fov.VARIANTS:
    register(f"q_topk_naive_t1_{_v}", lambda s, d, v=_v: top(s, d, T1, v, "naive"), O.top_of(T1, _v))
    register(f"q_topk_tiled_{_v}", lambda s, d, v=_v: matrix.top_cells(matrix.tiled(events(s, d, v), T1, 32), 5), O.top_of(T1, _v))
register("q_fovs_in_range", lambda s, d: retrieval.fovs_in_range(events(s, d), T2.area, JANUARY).select("fov_id", "t"), f"SELECT fov_id, t FROM ({O.in_range(O.fov_with_mbr('pie60'), T2.area, JANUARY_SQL)})")
FULL, LINE, GAUSS = (replace(T1, model=I.Model(kind="full_coverage")), replace(T1, model=I.Model(kind="center_line")), replace(T1, model=I.Model(circular="gaussian")))
register("q_topk_full_coverage", lambda s, d: top(s, d, FULL), O.top_of(FULL, "pie60"))
register("q_topk_center_line", lambda s, d: top(s, d, LINE), O.top_of(LINE, "pie60"))
register("q_topk_circular_gaussian", lambda s, d: top(s, d, GAUSS, "mix30"), O.top_of(GAUSS, "mix30"))
REACH = replace(T1, model=I.Model(reach=6.0))
register("q_topk_reach", lambda s, d: top(s, d, REACH, "mix30"), O.top_of(REACH, "mix30"))
for _n, _c in (("55m", 0.0005), ("111m", 0.001)):
    register(f"q_topk_cells_{_n}", lambda s, d, c=_c: top(s, d, replace(T1, cell=c)), O.top_of(replace(T1, cell=_c), "pie60"))
M1 = O.matrix(O.in_range(O.fov_with_mbr("pie60"), T1.area), T1)
register("q_ci_normalised", lambda s, d: rounded(matrix.normalised(matrix.optimized(events(s, d), T1))), f"SELECT cell_x, cell_y, round(ci_fixed / (max(ci_fixed) OVER ())::DOUBLE, 6) AS gamma FROM ({M1})")
register("q_heatmap", lambda s, d: measures.heatmap(matrix.optimized(events(s, d), T1), 4), f"SELECT floor(cell_x / 4)::BIGINT AS bin_x, floor(cell_y / 4)::BIGINT AS bin_y, round(max(ci_fixed) / any_value(top)::DOUBLE, 6) AS gamma FROM (SELECT *, max(ci_fixed) OVER () AS top FROM ({M1})) GROUP BY 1, 2")


def _sampled(s, d, query, variant="pie60", method="optimized"):
    return matrix.top_cells(matrix.matrix(sampling.by_fraction(events(s, d, variant), 0.3), query, method), query.k)


S30 = f"{u01_sql('s0', 'fov_id')} < 0.3"
register("q_topk_single_sample", lambda s, d: _sampled(s, d, T1), O.top_of(T1, "pie60", S30))
register("q_topk_naive_sample", lambda s, d: _sampled(s, d, T0, method="naive"), O.top_of(T0, "pie60", S30))
IN1 = O.in_range(O.fov_with_mbr("pie60"), T1.area)
register("q_sample_exact", lambda s, d: sampling.exact_size(matrix.candidates(events(s, d), T1), 0.1).select("fov_id"), f"SELECT fov_id FROM ({IN1}) ORDER BY {u01_sql('s0', 'fov_id')}, fov_id LIMIT (SELECT ceil(round(0.1 * count(*), 9))::BIGINT FROM ({IN1}))")
register("q_topk_exact_sample", lambda s, d: top(s, d, T1, method="single_sample", fraction=0.3), O.top(O.matrix(f"SELECT * FROM ({IN1}) ORDER BY {u01_sql('s0', 'fov_id')}, fov_id LIMIT (SELECT ceil(round(0.3 * count(*), 9))::BIGINT FROM ({IN1}))", T1), 5))
register("q_sample_batches", lambda s, d: sampling.batches(events(s, d), 20, "video_id").select("fov_id", "video_id", F.col("batch").cast("long")), f"SELECT fov_id, video_id, ntile(20) OVER (PARTITION BY video_id ORDER BY {u01_sql('s0', 'fov_id')}, fov_id) AS batch FROM ({FOV_E})")
register("q_sample_batches_hash", lambda s, d: sampling.batches(events(s, d), 20, mode="hash").groupBy("batch").agg(F.count("*").alias("n")), f"SELECT (floor({u01_sql('s0', 'event_id')} * 20) + 1)::INT AS batch, count(*) AS n FROM events GROUP BY 1")
register("q_remaining_fovs", lambda s, d: sampling.remaining(sampling.batches(events(s, d), 20, mode="hash"), 15).select("fov_id"), f"SELECT event_id AS fov_id FROM events WHERE floor({u01_sql('s0', 'event_id')} * 20) + 1 > 15")
register("q_topk_camera_cells", lambda s, d: matrix.top_cells(matrix.camera_cells(events(s, d), T1), 5), O.top(f"SELECT * FROM (SELECT floor((lon - {T1.area.min_lon!r}::DOUBLE) / 0.0001::DOUBLE)::BIGINT AS cell_x, floor((lat - {T1.area.min_lat!r}::DOUBLE) / 0.0001::DOUBLE)::BIGINT AS cell_y, count(*) * 1000000000000::BIGINT AS ci_fixed FROM ({IN1}) GROUP BY 1, 2) WHERE cell_x BETWEEN 0 AND 79 AND cell_y BETWEEN 0 AND 79", 5))
register("q_auto_small", lambda s, d: top(s, d, T1, method="auto"), f"SELECT *, 'optimized' AS method, false AS sampled FROM ({O.top_of(T1, 'pie60')})")
register("q_cube_topk", lambda s, d: matrix.top_cells(cube.over(cube.build(events(s, d), T1), "2024-01-08", "2024-01-14"), 5), O.top_of(T1, "pie60", JANUARY_SQL))

# --- clustering and clustered incremental sampling ----------------------------------------------------------------------

OPT = ClusterOptions()
register("q_lloyd_step", lambda s, d: _centres(s, d, 1), O.clustered("pie60", T1, replace(OPT, lloyd_steps=1, salt=""), "SELECT i, round(cx, 4) AS cx, round(cy, 4) AS cy FROM c1"))
register("q_kmeans_3_steps", lambda s, d: _centres(s, d, 3), O.clustered("pie60", T1, replace(OPT, salt=""), "SELECT i, round(cx, 4) AS cx, round(cy, 4) AS cy FROM c3"))


def _centres(s, d, steps):
    points = clusters.in_area(events(s, d), T1).where(u01("cluster", "fov_id") < 0.5)
    return s.createDataFrame([(i, float(x), float(y)) for i, (x, y) in enumerate(clusters.kmeans(points, 6, steps, "init"))], "i long, cx double, cy double").select("i", F.round("cx", 4).alias("cx"), F.round("cy", 4).alias("cy"))


def _rects(s, d, query=T1):
    return sampler.prepare(events(s, d), query, OPT).rects


register("q_cluster_radius", lambda s, d: _rects(s, d).select(F.col("cluster_id").cast("long"), "n", F.round("rms_m", 4).alias("rms_m")), O.clustered("pie60", T1, OPT, "SELECT cluster_id, n, round(rms_m, 4) AS rms_m FROM ranges"))
register("q_cluster_rect", lambda s, d: _rects(s, d).select(F.col("cluster_id").cast("long"), *[F.round(c, 8).alias(c) for c in ("r_min_lon", "r_max_lon", "r_min_lat", "r_max_lat")]), O.clustered("pie60", T1, OPT, "SELECT cluster_id, round(r_min_lon, 8) AS r_min_lon, round(r_max_lon, 8) AS r_max_lon, round(r_min_lat, 8) AS r_min_lat, round(r_max_lat, 8) AS r_max_lat FROM ranges"))
register("q_cell_range", lambda s, d: _rects(s, d).select(F.col("cluster_id").cast("long"), "cx0", "cx1", "cy0", "cy1"), O.clustered("pie60", T1, OPT, "SELECT cluster_id, cx0, cx1, cy0, cy1 FROM ranges"))
register("q_cluster_fovs", lambda s, d: sampler.prepare(events(s, d), T1, OPT).members.select("fov_id", F.col("cluster_id").cast("long"), F.col("batch").cast("long")), O.clustered("pie60", T1, OPT, "SELECT fov_id, cluster_id, batch FROM mem"))
TOP = "SELECT row_number() OVER (ORDER BY ci_fixed DESC, cell_y, cell_x) AS rank, cell_x, cell_y, round(ci_fixed / 1e12::DOUBLE, 6) AS ci FROM merged ORDER BY ci_fixed DESC, cell_y, cell_x LIMIT 5"
for _m in ("raw", "rescaled", "relative", "rescaled_relative"):
    register(f"q_clis_prefix_{_m}", lambda s, d, m=_m: sampler.prefix(events(s, d), T1, replace(OPT, measure=m))[0], O.clustered("pie60", T1, replace(OPT, measure=_m), TOP))
register("q_clis_topk", lambda s, d: sampler.run(events(s, d), T1, OPT)[0], O.clustered("pie60", T1, OPT, TOP))
register("q_clis_driver_loop", lambda s, d: sampler.driver_loop(events(s, d), T1, OPT)[0], O.clustered("pie60", T1, OPT, TOP))
register("q_clis_cap_10", lambda s, d: sampler.prefix(events(s, d), T1, replace(OPT, rule="none", max_iterations=10))[0], O.clustered("pie60", T1, replace(OPT, rule="none", max_iterations=10), TOP))
register("q_clis_merge", lambda s, d: sampler.prefix(events(s, d, "mix30"), T1, OPT)[0], O.clustered("mix30", T1, OPT, TOP))
register("q_stop_max_change", lambda s, d: _trace(s, d, T1).select("cluster_id", "iter", F.round("p", 6).alias("p"), F.round("d_max", 6).alias("d_max"), "stop"), O.clustered("pie60", T1, OPT, "SELECT cluster_id, iter, round(p, 6) AS p, round(d_max, 6) AS d_max, stop FROM moves JOIN stops USING (cluster_id)"))
register("q_processed_fovs", lambda s, d: _trace(s, d, T1).where("iter = stop").agg(F.sum("seen").alias("processed")), O.clustered("pie60", T1, OPT, "SELECT sum(seen)::BIGINT AS processed FROM stops JOIN shares ON shares.cluster_id = stops.cluster_id AND iter = stop"))
register("q_iterations", lambda s, d: _trace(s, d, T1).where("iter = stop").select("cluster_id", "iter"), O.clustered("pie60", T1, OPT, "SELECT cluster_id, stop AS iter FROM stops"))


def _trace(s, d, query, options=OPT, variant="pie60"):
    rows = sampler.trace(sampler.prepare(events(s, d, variant), query, options), query, options)
    return rows.withColumn("cluster_id", F.col("cluster_id").cast("long")).withColumn("iter", F.col("iter").cast("long")).withColumn("stop", F.col("stop").cast("long"))


register("q_stop_topk_shift", lambda s, d: _trace(s, d, T1).select("cluster_id", "iter", F.round("d_topk", 4).alias("d_topk")), O.clustered("pie60", T1, OPT, "SELECT cluster_id, iter, round(d_topk, 4) AS d_topk FROM steps", True))
for _r in ("topk_shift", "any_of", "all_of"):
    register(f"q_clis_{_r}", lambda s, d, r=_r: sampler.run(events(s, d), T1, replace(OPT, rule=r))[0], O.clustered("pie60", T1, replace(OPT, rule=_r), TOP))


# --- measures -----------------------------------------------------------------------------------------------------------

register("q_diff_sum", lambda s, d: measures.diff(top(s, d, T1), _sampled(s, d, T1), T1), O.greedy(O.top_of(T1, "pie60"), O.top_of(T1, "pie60", S30), T1))
register("q_diff_naive_optimized", lambda s, d: measures.diff(top(s, d, T1, "mix30"), top(s, d, T1, "mix30", "naive"), T1), O.greedy(O.top_of(T1, "mix30"), O.top(O.naive(O.in_range(O.fov_with_mbr("mix30"), T1.area), T1), 5), T1))
register("q_truth_error", lambda s, d: measures.truth_error(top(s, d, T1, "mix30"), carriers.spots(s), T1), f"SELECT rank, arg_min(mark_id, (e, mark_id)) AS mark_id, round(min(e), 6) AS error_m FROM (SELECT rank, mark_id, sqrt(pow(({T1.area.min_lon!r}::DOUBLE + (cell_x + 0.5::DOUBLE) * 0.0001::DOUBLE - mark_lon) * {O.MX}, 2) + pow(({T1.area.min_lat!r}::DOUBLE + (cell_y + 0.5::DOUBLE) * 0.0001::DOUBLE - mark_lat) * {O.MY}, 2)) AS e FROM ({O.top_of(T1, 'mix30')}), {MARKS}) GROUP BY rank")
for _t, _q in (("t1", T1), ("t2", T2), ("t3", T3), ("t4", T4)):
    _in = O.in_range(O.fov_with_mbr("pie60"), _q.area)
    register(f"q_region_stats_{_t}", lambda s, d, q=_q: measures.region_stats(events(s, d), q), f"SELECT {O.side(_q) ** 2}::BIGINT AS n_cells, count(*) AS n_fovs, {round(_q.area.km2(), 6)!r}::DOUBLE AS area_km2 FROM ({_in})")
    for _v in fov.VARIANTS:
        _sp = O.span(O.in_range(O.fov_with_mbr(_v), _q.area), _q)
        register(f"q_cells_per_mbr_{_t}_{_v}", lambda s, d, q=_q, v=_v: measures.cells_per_mbr(events(s, d, v), q), f"SELECT count(*) AS n_fovs, sum(c)::BIGINT AS cell_visits, round(avg(c), 6) AS mean_cells FROM (SELECT (x1 - x0 + 1) * (y1 - y0 + 1) AS c FROM ({_sp}))")
register("q_cost_model", lambda s, d: measures.cost_model(events(s, d), T2), f"SELECT count(*) * {O.side(T2) ** 2} AS naive_pairs, sum(c)::BIGINT AS optimized_pairs, round(count(*) * {O.side(T2) ** 2} / sum(c)::DOUBLE, 6) AS ratio FROM (SELECT (x1 - x0 + 1) * (y1 - y0 + 1) AS c FROM ({O.span(O.in_range(O.fov_with_mbr('pie60'), T2.area), T2)}))")
register("q_topk_common", lambda s, d: top(s, d, T1).select("cell_x", "cell_y").intersect(_sampled(s, d, T1).select("cell_x", "cell_y")), f"SELECT cell_x, cell_y FROM ({O.top_of(T1, 'pie60')}) INTERSECT SELECT cell_x, cell_y FROM ({O.top_of(T1, 'pie60', S30)})")
register("q_topk_missed", lambda s, d: top(s, d, T1).select("cell_x", "cell_y").exceptAll(_sampled(s, d, T1).select("cell_x", "cell_y")), f"SELECT cell_x, cell_y FROM ({O.top_of(T1, 'pie60')}) EXCEPT SELECT cell_x, cell_y FROM ({O.top_of(T1, 'pie60', S30)})")

# --- kinds of content, time and place ---------------------------------------------------------------------------------------

register("q_w13_range", lambda s, d: carriers.from_events(s, d).groupBy(F.width_bucket("r_m", F.lit(0.0), F.lit(700.0), F.lit(14)).alias("bucket")).agg(F.count("*").alias("n"), F.countDistinct("video_id").alias("videos")), f"SELECT floor(r_m / 50.0::DOUBLE)::BIGINT + 1 AS bucket, count(*) AS n, count(DISTINCT video_id) AS videos FROM ({FOV_E}) GROUP BY 1")


def _per_group(s, d, unit, source):
    fovs = source(s, d)
    dated = retrieval.fovs_in_range(fovs, T1.area).withColumn("period", F.date_trunc(unit, F.col("t").cast("timestamp")).cast("date"))
    sums = matrix.exploded(dated, T1, ("period",)).groupBy("period", "cell_x", "cell_y").agg(F.sum("ci_fixed").alias("ci_fixed"))
    return matrix.top_per_group(sums, "period", 5)


def _per_group_sql(unit: str, source: str) -> str:
    dated = f"SELECT *, date_trunc('{unit}', t)::DATE AS period FROM ({O.in_range(source, T1.area)})"
    sums = f"SELECT period, cell_x, cell_y, sum(ci_fixed)::BIGINT AS ci_fixed FROM ({O.pairs(dated, T1, 'period')}) GROUP BY ALL"
    return f"SELECT period, rank, cell_x, cell_y, round(ci_fixed / 1e12::DOUBLE, 6) AS ci FROM (SELECT *, row_number() OVER (PARTITION BY period ORDER BY ci_fixed DESC, cell_y, cell_x) AS rank FROM ({sums})) WHERE rank <= 5"


register("q_w17_weekly", lambda s, d: _per_group(s, d, "week", events), _per_group_sql("week", O.fov_with_mbr("pie60")))
register("q_w17_yearly", lambda s, d: _per_group(s, d, "year", lambda s, d: kept(fov.with_mbr(carriers.from_orders(s, d)))), _per_group_sql("year", O.mbr(FOV_O)))


def _areas(s):
    return s.createDataFrame([(i, 10.0 + a - 0.002, 10.0 + a + 0.002, 20.0 + b - 0.002, 20.0 + b + 0.002) for i, (a, b) in enumerate(carriers.SPOTS)] + [(99, 40.0, 40.1, 40.0, 40.1)], "area_id long, a_min_lat double, a_max_lat double, a_min_lon double, a_max_lon double")


AREAS = "(VALUES " + ", ".join(f"({i}::BIGINT, {10.0 + a - 0.002!r}::DOUBLE, {10.0 + a + 0.002!r}::DOUBLE, {20.0 + b - 0.002!r}::DOUBLE, {20.0 + b + 0.002!r}::DOUBLE)" for i, (a, b) in enumerate(carriers.SPOTS)) + ", (99::BIGINT, 40.0::DOUBLE, 40.1::DOUBLE, 40.0::DOUBLE, 40.1::DOUBLE)) AS areas(area_id, a_min_lat, a_max_lat, a_min_lon, a_max_lon)"
IN_AREA = "max_lat >= a_min_lat AND min_lat <= a_max_lat AND max_lon >= a_min_lon AND min_lon <= a_max_lon"


def _areas_outer(s, d):
    """How many fields of view each area has, none included. The areas are broadcast, to be counted in; an outer join without
    equal keys would gather all fields of view on the driver instead."""
    counts = events(s, d).join(F.broadcast(_areas(s)), F.expr(IN_AREA)).groupBy("area_id").agg(F.count("fov_id").alias("n"))
    return _areas(s).select("area_id").join(counts, "area_id", "left").select("area_id", F.coalesce("n", F.lit(0)).alias("n"))


register("q_areas_outer", _areas_outer, f"SELECT area_id, count(fov_id) AS n FROM {AREAS} LEFT JOIN ({O.fov_with_mbr('pie60')}) f ON {IN_AREA} GROUP BY area_id")


def _many_areas(s, d):
    """Top-3 cells of the common grid in each of many areas at once; overlapping fields of view are evaluated once for each area."""
    inside = matrix.with_span(events(s, d).join(F.broadcast(_areas(s)), F.expr(IN_AREA)), T4)
    g = T4.grid
    cell = lambda v, o, f: f((F.col(v) - o) / g.cell).cast("long")
    bounds = inside.withColumns({"bx0": cell("a_min_lon", g.area.min_lon, F.ceil), "bx1": cell("a_max_lon", g.area.min_lon, F.floor), "by0": cell("a_min_lat", g.area.min_lat, F.ceil), "by1": cell("a_max_lat", g.area.min_lat, F.floor)})
    sums = matrix.exploded(bounds, T4, ("area_id",), ("bx0", "bx1", "by0", "by1")).groupBy("area_id", "cell_x", "cell_y").agg(F.sum("ci_fixed").alias("ci_fixed"))
    return matrix.top_per_group(sums, "area_id", 3)


def _many_areas_sql() -> str:
    near = f"SELECT * FROM ({O.fov_with_mbr('pie60')}) f, {AREAS} WHERE {IN_AREA}"
    a, c = T4.area, "0.0001::DOUBLE"
    cell = lambda v, origin, f: f"{f}(({v} - {origin!r}::DOUBLE) / {c})::BIGINT"
    limits = f"greatest(x0, {cell('a_min_lon', a.min_lon, 'ceil')}) AS x0, least(x1, {cell('a_max_lon', a.min_lon, 'floor')}) AS x1, greatest(y0, {cell('a_min_lat', a.min_lat, 'ceil')}) AS y0, least(y1, {cell('a_max_lat', a.min_lat, 'floor')}) AS y1"
    sums = f"SELECT area_id, cell_x, cell_y, sum(ci_fixed)::BIGINT AS ci_fixed FROM ({O.pairs(near, T4, 'area_id', limits)}) GROUP BY ALL"
    return f"SELECT area_id, rank, cell_x, cell_y, round(ci_fixed / 1e12::DOUBLE, 6) AS ci FROM (SELECT *, row_number() OVER (PARTITION BY area_id ORDER BY ci_fixed DESC, cell_y, cell_x) AS rank FROM ({sums})) WHERE rank <= 3"


register("q_w18_areas", _many_areas, _many_areas_sql())

# --- other latitudes ------------------------------------------------------------------------------------------------------

#: Where the same events are laid out again: a centre, and a region of 80 by 80 cells around it.
ELSEWHERE = {"48n": (48.0, 11.0), "34s": (-34.0, 151.0)}


def _there(name: str, half: str = "t1") -> Query:
    return Query(Area.around(*ELSEWHERE[name], REGIONS[half]))


def _moved(s, d, name, variant="pie60"):
    return events(s, d, variant, ELSEWHERE[name])


for _p, _c in ELSEWHERE.items():
    register(f"q_fov_mbr_{_p}", lambda s, d, p=_p: rounded(_moved(s, d, p, "mix30").select("fov_id", *BOX.split()), 9), f"SELECT fov_id, {', '.join(f'round({c}, 9) AS {c}' for c in BOX.split())} FROM ({O.fov_with_mbr('mix30', _c)})")
    register(f"q_fovs_in_range_{_p}", lambda s, d, p=_p: retrieval.fovs_in_range(_moved(s, d, p, "mix30"), _there(p, "t2").area).select("fov_id", "t"), f"SELECT fov_id, t FROM ({O.in_range(O.fov_with_mbr('mix30', _c), _there(_p, 't2').area)})")
    register(f"q_topk_naive_{_p}", lambda s, d, p=_p: detect(_moved(s, d, p, "mix30"), _there(p), "naive"), O.top(O.naive(O.in_range(O.fov_with_mbr("mix30", _c), _there(_p).area), _there(_p)), 5))
    register(f"q_fov_covers_{_p}", lambda s, d, p=_p: _moved(s, d, p, "mix30").where(fov.sees(F.lit(ELSEWHERE[p][0]), F.lit(ELSEWHERE[p][1]))).select("fov_id", "alpha"), f"SELECT fov_id, alpha FROM (SELECT *, ({_c[1]!r}::DOUBLE - lon) * {O.OWN} AS dx, ({_c[0]!r}::DOUBLE - lat) * {O.MY} AS dy FROM ({O.fov_with_mbr('mix30', _c)})) WHERE sqrt(dx * dx + dy * dy) <= r_m AND (alpha >= 360 OR ({OFF}) <= alpha / 2)")
    for _v in fov.VARIANTS:
        register(f"q_topk_{_p}_{_v}", lambda s, d, p=_p, v=_v: detect(_moved(s, d, p, v), _there(p), "optimized"), O.top_of(_there(_p), _v, centre=_c))
        register(f"q_topk_tiled_{_p}_{_v}", lambda s, d, p=_p, v=_v: detect(_moved(s, d, p, v), _there(p), "tiled"), O.top_of(_there(_p), _v, centre=_c))


def _plane_error(s, d):
    """The largest relative error of distances in the plane of the largest region, against great circles, by centre.

    All cameras against all planted spots, which lie up to 0.15 degrees from the centre; pairs nearer than a metre are left out.
    """
    parts = []
    for name, centre in {"10n": carriers.CENTRE, **ELSEWHERE}.items():
        q = Query(Area.around(*centre, REGIONS["t4"]))
        marks = s.createDataFrame([(i, centre[0] + a, centre[1] + b) for i, (a, b) in enumerate(carriers.SPOTS)], "mark_id long, mark_lat double, mark_lon double")
        pairs = carriers.from_events(s, d, centre=centre).crossJoin(F.broadcast(marks))
        dx, dy = (F.col("mark_lon") - F.col("lon")) * geo.east_scale(q.lat0), (F.col("mark_lat") - F.col("lat")) * geo.METRES_PER_DEGREE
        plane, great = geo.distance(dx, dy), geo.haversine(F.col("lat"), F.col("lon"), F.col("mark_lat"), F.col("mark_lon"))
        worst = pairs.select(plane.alias("plane"), great.alias("great")).where("great > 1").agg(F.max(F.abs(F.col("plane") / F.col("great") - 1)).alias("e"))
        parts.append(worst.select(F.lit(name).alias("centre"), F.round("e", 6).alias("error"), (F.col("e") < 0.005).alias("below_half_percent")))
    return stack(parts)


def _plane_error_sql() -> str:
    parts = []
    for name, c in {"10n": carriers.CENTRE, **ELSEWHERE}.items():
        marks = "(VALUES " + ", ".join(f"({c[0] + a!r}::DOUBLE, {c[1] + b!r}::DOUBLE)" for a, b in carriers.SPOTS) + ") AS marks(mark_lat, mark_lon)"
        both = f"SELECT sqrt(pow((mark_lon - lon) * {O.mx(c[0])}, 2) + pow((mark_lat - lat) * {O.MY}, 2)) AS plane, {O.haversine('lat', 'lon', 'mark_lat', 'mark_lon')} AS great FROM ({O.fov_events('pie60', c)}), {marks}"
        parts.append(f"SELECT '{name}' AS centre, round(max(abs(plane / great - 1)), 6) AS error, max(abs(plane / great - 1)) < 0.005 AS below_half_percent FROM ({both}) WHERE great > 1")
    return " UNION ALL ".join(parts)


register("q_plane_error", _plane_error, _plane_error_sql())


def _meets_sql() -> str:
    """Exact overlap of pie or disc and T0, written out for DuckDB from the geometry."""
    a = T0.area
    box = f"SELECT *, ({a.min_lon!r}::DOUBLE - lon) * {O.OWN} AS w, ({a.max_lon!r}::DOUBLE - lon) * {O.OWN} AS e, ({a.min_lat!r}::DOUBLE - lat) * {O.MY} AS s, ({a.max_lat!r}::DOUBLE - lat) * {O.MY} AS n FROM ({O.in_range(O.fov_with_mbr('mix30'), a)})"
    off = lambda x, y: O.angle_diff(O.pmod360(f"degrees(atan2({x}, {y}))"), "theta")
    corner = " OR ".join(f"(sqrt({x} * {x} + {y} * {y}) <= r_m AND {off(x, y)} <= alpha / 2)" for x in "we" for y in "sn")
    arcs = [f"(abs({c}) <= r_m AND {sign}sqrt(greatest(r_m * r_m - {c} * {c}, 0)) BETWEEN {lo} AND {hi} AND {off(*((c, f'{sign}sqrt(greatest(r_m * r_m - {c} * {c}, 0))') if upright else (f'{sign}sqrt(greatest(r_m * r_m - {c} * {c}, 0))', c)))} <= alpha / 2)" for c, lo, hi, upright in (("w", "s", "n", True), ("e", "s", "n", True), ("s", "w", "e", False), ("n", "w", "e", False)) for sign in ("", "-")]
    edge = lambda turn: f"greatest(0, least(w / sin(radians(theta {turn} alpha / 2)), e / sin(radians(theta {turn} alpha / 2))), least(s / cos(radians(theta {turn} alpha / 2)), n / cos(radians(theta {turn} alpha / 2)))) <= least(r_m, greatest(w / sin(radians(theta {turn} alpha / 2)), e / sin(radians(theta {turn} alpha / 2))), greatest(s / cos(radians(theta {turn} alpha / 2)), n / cos(radians(theta {turn} alpha / 2))))"
    disc = "sqrt(pow(greatest(w, least(0, e)), 2) + pow(greatest(s, least(0, n)), 2)) <= r_m"
    return f"SELECT fov_id FROM ({box}) WHERE CASE WHEN alpha >= 360 THEN {disc} ELSE (w <= 0 AND e >= 0 AND s <= 0 AND n >= 0) OR {corner} OR {' OR '.join(arcs)} OR ({edge('-')}) OR ({edge('+')}) END"


register("q_fovs_refined", lambda s, d: retrieval.fovs_in_range(events(s, d, "mix30"), T0.area, refine=True).select("fov_id"), _meets_sql())


def stack(parts: list[DataFrame]) -> DataFrame:
    out = parts[0]
    for p in parts[1:]:
        out = out.unionByName(p)
    return out


def queries() -> dict[str, Callable[[SparkSession, str], DataFrame]]:
    from . import experiments, surroundings  # noqa: F401  register their own

    return dict(QUERIES)


def oracle_sql() -> dict[str, str]:
    from . import experiments, surroundings  # noqa: F401

    return dict(SQL)

