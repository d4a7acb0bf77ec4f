import math

import pytest
from pyspark.sql import functions as F

from vistapoint.functions import geo
from vistapoint.functions import intention as I
from vistapoint.operators import fov, matrix, measures
from vistapoint.plans.query import Area, GridSpec, Query

ROW = "fov_id long, video_id long, lat double, lon double, theta double, r_m double, alpha double, t timestamp_ntz"


def one(spark, *columns):
    return spark.range(1).select(*columns).first()


def test_circular_difference_and_bearing(spark):
    r = one(spark, geo.angle_diff(F.lit(350.0), F.lit(10.0)).alias("d"), geo.bearing(F.lit(1.0), F.lit(0.0)).alias("e"), geo.bearing(F.lit(0.0), F.lit(-1.0)).alias("s"))
    assert (r.d, r.e, r.s) == (20.0, 90.0, 180.0)


def test_axis_cell_is_the_product_of_both_densities(spark):
    for d in (0.0, 10.0, 49.0):
        got = one(spark, I.intention(F.lit(0.0), F.lit(d), F.lit(0.0), F.lit(50.0), F.lit(60.0)).alias("c")).c
        assert got == pytest.approx(math.exp(-d * d / 1250) / (25 * math.sqrt(2 * math.pi)) / (15 * math.sqrt(2 * math.pi)), rel=1e-12)
    assert one(spark, I.intention(F.lit(0.0), F.lit(-5.0), F.lit(0.0), F.lit(50.0), F.lit(60.0)).alias("c")).c == 0


def test_borders_count(spark):
    r = one(spark, I.ci_angle(F.lit(30.0), F.lit(60.0)).alias("a"), I.ci_angle(F.lit(30.0001), F.lit(60.0)).alias("b"), I.ci_dist(F.lit(50.0), F.lit(50.0)).alias("c"), I.ci_dist(F.lit(50.01), F.lit(50.0)).alias("d"))
    assert r.a > 0 and r.b == 0 and r.c > 0 and r.d == 0


def test_full_circle_is_symmetric_and_constant_in_angle(spark):
    vals = {round(one(spark, I.intention(F.lit(20 * math.sin(a)), F.lit(20 * math.cos(a)), F.lit(0.0), F.lit(50.0), F.lit(360.0)).alias("c")).c, 15) for a in (0.1, 2.0, 4.0)}
    assert len(vals) == 1


@pytest.mark.parametrize("theta", [0.0, 30.0, 45.0, 90.0, 180.0, 315.0])
@pytest.mark.parametrize("alpha", [60.0, 160.0, 200.0, 360.0])
def test_box_is_tight(spark, theta, alpha):
    r = one(spark, *[c.alias(n) for n, c in zip("wesn", fov.extent(F.lit(theta), F.lit(100.0), F.lit(alpha)), strict=True)])
    pts = [(0.0, 0.0)] + [(100 * math.sin(math.radians(theta + alpha * (i / 2000 - 0.5))), 100 * math.cos(math.radians(theta + alpha * (i / 2000 - 0.5)))) for i in range(2001)]
    assert r.w == pytest.approx(min(p[0] for p in pts), abs=1e-2) and r.e == pytest.approx(max(p[0] for p in pts), abs=1e-2)
    assert r.s == pytest.approx(min(p[1] for p in pts), abs=1e-2) and r.n == pytest.approx(max(p[1] for p in pts), abs=1e-2)


def test_validation_names_each_fault(spark):
    rows = [(1, 1, 10.0, 20.0, 0.0, 5.0, 60.0, None), (2, 1, 95.0, 20.0, 0.0, 5.0, 60.0, None), (3, 1, 10.0, 20.0, 360.0, 5.0, 60.0, None), (4, 1, 10.0, 20.0, 0.0, 0.0, 60.0, None), (5, 1, 10.0, 20.0, 0.0, 5.0, 361.0, None), (1, 1, 10.0, 20.0, 0.0, 5.0, 60.0, None)]
    assert {(r.fov_id, r.reason) for r in fov.check_fov(spark.createDataFrame(rows, ROW)).collect()} == {(2, "position"), (3, "azimuth"), (4, "distance"), (5, "angle"), (1, "duplicate")}


def test_empty_input_and_more_places_than_cells(spark):
    q = Query(Area.around(10.0, 20.0, 0.0015))
    none = fov.with_mbr(spark.createDataFrame([], ROW))
    for method in ("naive", "optimized", "tiled"):
        assert matrix.top_cells(matrix.matrix(none, q, method), 5).count() == 0
    single = fov.with_mbr(spark.createDataFrame([(1, 1, 10.0, 20.0, 0.0, 40.0, 60.0, None)], ROW))
    assert 0 < matrix.top_cells(matrix.optimized(single, q), 500).count() < 30


def test_greedy_pairing_is_not_the_best_assignment(spark):
    q = Query(Area.around(10.0, 20.0, 0.0015), k=2)
    as_top = lambda cells: spark.createDataFrame([(i + 1, x, y, 0.0) for i, (x, y) in enumerate(cells)], "rank int, cell_x long, cell_y long, ci double")
    w, _ = measures.cell_metres(q)
    got = measures.diff(as_top([(0, 0), (3, 0)]), as_top([(2, 0), (10, 0)]), q).first()
    assert got.diff_m == pytest.approx(1 * w + 10 * w, abs=1e-5)
    assert measures.diff(as_top([(0, 0), (3, 0)]), as_top([(0, 0), (3, 0)]), q).first().diff_m == 0


def test_areas_that_cannot_be_projected_are_refused():
    with pytest.raises(ValueError):
        Area(10.0, 20.0, 170.0, -170.0)
    assert GridSpec(Area.around(10.0, 20.0, 0.004)).cells == 6400
