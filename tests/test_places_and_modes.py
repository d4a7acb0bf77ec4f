"""Other latitudes, exact overlap, exact deals, dense rounds, plug-ins, the result cache, as-of answers and states of streams."""

import math
import random
import time
from dataclasses import replace

import pytest
from pyspark.sql import functions as F

from vistapoint import workloads as W
from vistapoint.functions.intention import Model, useful_radius
from vistapoint.operators import clusters, fov, matrix, retrieval, sampler, sampling
from vistapoint.operators.detect import ResultCache, detect
from vistapoint.plans import stopping
from vistapoint.plans.query import Area, ClusterOptions, GridSpec, Query
from vistapoint.sources import carriers
from vistapoint.streaming import ingest, stateful

DIR = "/root/testdata/sf0.001"
ROW = "fov_id long, video_id long, lat double, lon double, theta double, r_m double, alpha double"


@pytest.fixture(scope="module")
def mix(spark):
    return W.events(spark, DIR, "mix30")


@pytest.mark.parametrize("lat", [48.0, -34.0, 0.0])
def test_boxes_hold_what_a_camera_sees_on_the_sphere(spark, lat):
    """Points of the arc by great circles lie in the box, and the box is no wider than them, within half a percent of the radius."""
    r = fov.with_mbr(spark.createDataFrame([(1, 1, lat, 20.0, 80.0, 400.0, 160.0)], ROW)).first()
    rho = 400.0 / 6_371_008.8
    lons = []
    for i in range(201):
        b = math.radians(80.0 + 160.0 * (i / 200 - 0.5))
        phi = math.asin(math.sin(math.radians(lat)) * math.cos(rho) + math.cos(math.radians(lat)) * math.sin(rho) * math.cos(b))
        lons.append(20.0 + math.degrees(math.atan2(math.sin(b) * math.sin(rho) * math.cos(math.radians(lat)), math.cos(rho) - math.sin(math.radians(lat)) * math.sin(phi))))
    assert r.max_lon - 20.0 == pytest.approx(max(lons) - 20.0, rel=0.005)


def test_a_query_is_judged_at_its_own_latitude():
    assert Query(Area.around(48.0, 11.0, 0.01)).lat0 == pytest.approx(48.0) and Query(Area.around(-34.0, 11.0, 0.01)).lat0 == pytest.approx(-34.0)


def test_no_part_of_an_area_is_left_out():
    assert GridSpec(Area(0.0, 0.00125, 0.0, 0.00101)).nx == 11 and GridSpec(Area(0.0, 0.00125, 0.0, 0.00101)).ny == 13
    assert GridSpec(Area.around(10.0, 20.0, 0.175)).cells == 3500 * 3500


def test_exact_forms_agree_far_north(spark):
    fovs, q = W._moved(spark, DIR, "48n", "mix30"), W._there("48n")
    as_dict = lambda df: {(r.cell_x, r.cell_y): r.ci_fixed for r in df.collect()}
    a, b, c = as_dict(matrix.naive(fovs, q)), as_dict(matrix.optimized(fovs, q)), as_dict(matrix.tiled(fovs, q, 32))
    assert a and a == b and a.keys() == c.keys() and max(abs(a[k] - c[k]) for k in a) <= 5


def test_cutting_spans_where_nothing_is_changes_no_sum(mix, monkeypatch):
    cut = sorted(map(tuple, matrix.optimized(mix, W.T1).collect()))
    visits = matrix.pair_count(mix, W.T1)[1]
    monkeypatch.setattr(matrix, "useful_radius", lambda *a: math.inf)
    assert sorted(map(tuple, matrix.optimized(mix, W.T1).collect())) == cut and visits < 0.6 * matrix.pair_count(mix, W.T1)[1]
    assert useful_radius(Model(kind="full_coverage"), True) == math.inf and 150 < useful_radius(Model(), False) < useful_radius(Model(), True) < 180


def test_overlap_of_shapes_and_boxes_is_exact(spark):
    """Against points laid densely over each shape: what they hit must be kept; what is kept must come within a hair of the box."""
    rng = random.Random(5)
    rows = [(i, 1, 48.0 + rng.uniform(-0.006, 0.006), 11.0 + rng.uniform(-0.008, 0.008), rng.uniform(0, 360), rng.uniform(30, 600), rng.choice([10.0, 60.0, 160.0, 250.0, 360.0])) for i in range(400)]
    area = Area(48.0, 48.0004, 11.0, 11.003)
    kept = {r.fov_id for r in spark.createDataFrame(rows, ROW).where(retrieval.shape_meets(area)).select("fov_id").collect()}
    for i, _, lat, lon, theta, r_m, alpha in rows:
        mx = 111_320 * math.cos(math.radians(lat))
        w, e, s, n = (area.min_lon - lon) * mx, (area.max_lon - lon) * mx, (area.min_lat - lat) * 111_320, (area.max_lat - lat) * 111_320
        nearest = min(math.hypot(max(w - x, 0, x - e), max(s - y, 0, y - n)) for k in range(161) for m in range(61) for x, y in [(r_m * m / 60 * math.sin(math.radians(theta + alpha * (k / 160 - 0.5))), r_m * m / 60 * math.cos(math.radians(theta + alpha * (k / 160 - 0.5))))])
        assert i in kept if nearest == 0 else i not in kept or nearest < 15


def test_deals_are_alike_for_any_number_of_sorts(mix):
    rows = mix.withColumn("g", F.col("fov_id") % 3)
    whole = {(r.fov_id, r.batch) for r in sampling.batches(rows, 7, "g").select("fov_id", "batch").collect()}
    assert {(r.fov_id, r.batch) for r in sampling.batches(rows, 7, "g", parts=5).select("fov_id", "batch").collect()} == whole
    assert {(r.fov_id, r.batch) for r in sampling.batches(rows.limit(4), 7, "g", parts=3).select("fov_id", "batch").collect()} == {(r.fov_id, r.batch) for r in sampling.batches(rows.limit(4), 7, "g").select("fov_id", "batch").collect()}


@pytest.mark.parametrize("fraction", [0.0, 0.001, 0.1, 0.5, 1.0])
def test_sample_sizes_are_exact_without_a_big_sort(mix, monkeypatch, fraction):
    expected = [r.fov_id for r in mix.orderBy(sampling.u01("s0", "fov_id"), "fov_id").limit(math.ceil(round(fraction * mix.count(), 9))).collect()]
    monkeypatch.setattr(sampling, "CUT_ROWS", 3), monkeypatch.setattr(sampling, "PARTS", 4)
    assert sorted(r.fov_id for r in sampling.exact_size(mix, fraction).collect()) == sorted(expected)


def test_rounds_in_dense_blocks_give_the_same_list(mix):
    o = replace(W.OPT, clusters=3)
    ready = sampler.prepare(mix, W.T1, o)
    a = sampler.driver_loop(mix, W.T1, o, ready)[0].collect()
    b = sampler.driver_loop(mix, W.T1, o, ready, blocks_from=0)[0].collect()
    assert a and a == b


def test_rules_and_samplers_of_the_callers_own(mix):
    stopping.add_rule("at_once", lambda o, d_max, d_topk: d_max >= 0)
    sampling.add_sampler("odd", lambda fovs, count, by, noise: fovs.withColumn("batch", (F.col("fov_id") % count + 1).cast("int")))
    o = replace(W.OPT, clusters=2, rule="at_once", sampler="odd")
    lists = [[tuple(r) for r in run(mix, W.T1, o)[0].collect()] for run in (sampler.prefix, sampler.per_cluster_task, sampler.driver_loop)]
    assert lists[0] and lists[0] == lists[1] == lists[2]
    with pytest.raises(ValueError):
        replace(W.OPT, rule="unknown")


def test_videos_are_spread_over_batches(mix):
    rows = sampling.batches(mix.withColumn("cluster_id", F.lit(0)), 4, mode="by_video").groupBy("video_id", "batch").count().collect()
    sizes = {}
    for r in rows:
        sizes.setdefault(r.video_id, []).append(r["count"])
    assert all(max(v) - min(v) <= 1 for v in sizes.values())


def test_advised_options():
    assert ClusterOptions.advised(5).within_advice(5) and ClusterOptions.advised(4, threshold=0.2).threshold == 0.2
    assert ClusterOptions().within_advice(5) and not ClusterOptions(clusters=20).within_advice(5) and not ClusterOptions(cluster_fraction=0.9).within_advice(5)


def test_clusters_are_alike_on_the_driver_and_in_jobs(mix):
    points = clusters.in_area(mix, W.T1)
    a, b = clusters.kmeans_with_radii(points, 4), clusters.kmeans_with_radii(points, 4, driver_rows=3)
    assert all(p == pytest.approx(q) for p, q in zip(a[0], b[0], strict=True)) and a[2] == b[2] == points.count()
    for x, y in zip(a[1].orderBy("cluster_id").collect(), b[1].orderBy("cluster_id").collect(), strict=True):
        assert (x.cluster_id, x.n) == (y.cluster_id, y.n) and x.rms_m == pytest.approx(y.rms_m)
    assert clusters.kmeans_with_radii(points.where("false"), 4)[0] == []


def test_library_k_means_on_a_sample_finds_the_same_places(mix):
    points = clusters.in_area(mix, W.T4)
    whole, part = clusters.kmeans_ml(points, 3), clusters.kmeans_ml(points, 3, sample=300)
    assert len(whole) == len(part) == 3
    assert all(min(math.dist(a, b) for b in whole) < 4_000 for a in part)


def test_auto_says_how_it_answered(spark, mix, monkeypatch):
    assert {(r.method, r.sampled) for r in detect(mix, W.T1, "auto").collect()} == {("optimized", False)}
    monkeypatch.setattr("vistapoint.operators.detect.EXACT_CELLS", 10)
    assert {(r.method, r.sampled) for r in detect(mix, W.T1, "auto", replace(W.OPT, clusters=2)).collect()} == {("clustered", True)}


def test_equal_queries_are_answered_once(spark, mix, tmp_path):
    cache = ResultCache(str(tmp_path))
    first = cache.detect(mix, "v1", W.T1, "optimized").collect()
    assert first and cache.detect(mix.where("false"), "v1", W.T1, "optimized").collect() == first
    assert cache.detect(mix.where("false"), "v2", W.T1, "optimized").collect() == [] and cache.path("v1", W.T1, "optimized") != cache.path("v1", replace(W.T1, k=6), "optimized")


def test_latest_before_looks_back_any_time(spark):
    fovs = spark.createDataFrame([(1, 7, "2001-01-01"), (2, 7, "2024-01-05"), (3, 8, "2024-01-09")], "fov_id long, video_id long, day string").withColumn("t", F.col("day").cast("timestamp_ntz"))
    asked = spark.createDataFrame([(7, "2024-01-01"), (7, "2024-01-05"), (8, "2024-01-01"), (9, "2024-01-01")], "video_id long, day string").select("video_id", F.col("day").cast("timestamp_ntz").alias("at"))
    assert sorted((r.video_id, r["at"].day, r.fov_id) for r in retrieval.latest_before(fovs, asked).collect()) == [(7, 1, 1), (7, 5, 2), (8, 1, None), (9, 1, None)]


def test_late_rows_are_left_out_and_counted(spark, tmp_path):
    source = f"{tmp_path}/in"
    events = spark.read.parquet(f"{DIR}/events.parquet")
    # Files are read in the order of their times; rows are late by the watermark that the batch before began with.
    for part in ("ts >= timestamp_ntz'2024-01-20'", "ts >= timestamp_ntz'2024-01-10' and ts < timestamp_ntz'2024-01-20'", "ts < timestamp_ntz'2024-01-05'"):
        events.where(part).coalesce(1).write.mode("append").parquet(source)
        time.sleep(1.2)
    fovs = ingest.timed(carriers.events_to_fovs(ingest.event_stream(spark, source, 1)), "1 day")
    counts = fovs.groupBy(F.window("t", "1 day").alias("w")).agg(F.count("*").alias("n"))
    query = counts.writeStream.format("memory").queryName("late").outputMode("update").trigger(availableNow=True).option("checkpointLocation", f"{tmp_path}/ck").start()
    query.awaitTermination()
    late = events.where("ts < timestamp_ntz'2024-01-05'").count()
    assert late > 0 and stateful.late_rows(query) > 0 and spark.sql("select min(w.start) as s from late").first().s.day >= 10
