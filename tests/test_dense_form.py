"""The dense form: what a task evaluates, and what leaves it."""

import math
from dataclasses import replace

import numpy as np
import pytest

from vistapoint import experiments as X
from vistapoint import workloads as W
from vistapoint.functions.intention import FIXED, Model, density_scale
from vistapoint.operators import kernel, matrix
from vistapoint.plans.query import Area, Query

DIR = "/root/testdata/sf0.001"
rows_of = lambda df: [tuple(r) for r in df.collect()]


def by_hand(query, fov, cell_x, cell_y):
    """The fixed-point intention of one pair, number by number."""
    lat, lon, theta, r_m, alpha = fov
    m = query.model
    dx = (query.area.min_lon + (cell_x + 0.5) * query.cell - lon) * kernel.east_scale(query.lat0)
    dy = (query.area.min_lat + (cell_y + 0.5) * query.cell - lat) * kernel.METRES_PER_DEGREE
    d = math.hypot(dx, dy)
    off = abs((math.degrees(math.atan2(dx, dy)) % 360 - theta + 180) % 360 - 180) if d else 0.0
    if d > (min(r_m, m.reach * m.sigma_distance) if m.reach and m.kind == "probabilistic" else r_m):
        return 0
    if m.kind == "center_line":
        t = math.radians(theta)
        return int(FIXED) * (dx * math.sin(t) + dy * math.cos(t) >= 0 and abs(dx * math.cos(t) - dy * math.sin(t)) <= m.line_width_m / 2)
    plain = alpha >= 360 and (m.circular == "constant" or m.kind == "full_coverage")
    if not plain and off > alpha / 2:
        return 0
    if m.kind == "full_coverage":
        return int(FIXED)
    density = lambda v, s: math.exp(-v * v / (2 * s * s)) * density_scale(s)
    return math.floor((1.0 if plain else density(off, m.sigma_angle)) * density(d, m.sigma_distance) * FIXED + 0.5)


@pytest.mark.parametrize("model", [Model(), Model(circular="gaussian"), Model(reach=1.5), Model(kind="full_coverage"), Model(kind="center_line")])
def test_sums_of_blocks_are_those_of_pairs_one_by_one(model):
    query = replace(Query(Area(10.0, 10.002, 20.0, 20.003)), model=model)
    rng, n = np.random.default_rng(7), 60
    shapes = [(10 + 0.002 * a, 20 + 0.003 * b, 360 * c, r, al) for a, b, c, r, al in zip(*rng.random((3, n)), rng.choice([5.0, 40.0, 400.0], n), rng.choice([60.0, 160.0, 360.0], n), strict=True)]
    shapes += [(10.00105, 20.00105, 0.0, 50.0, 60.0), (10.00105, 20.00105, 360.0, math.inf, 360.0), (10.001, 20.001, -30.0, 60.0, 60.0)]
    spans = np.array([(a - 3, a + w, b - 2, b + h) for a, b, w, h in rng.integers((0, 0, 0, 0), (28, 18, 21, 19), (len(shapes), 4))])
    x_first, y_first, block = 4, 3, np.zeros((14, 20), np.int64)
    kernel.add_fovs(block, x_first, y_first, query, [*np.array(shapes).T, *spans.T])
    wanted = np.zeros_like(block)
    for fov, (x0, x1, y0, y1) in zip(shapes, spans.tolist(), strict=True):
        for y in range(max(y0, y_first), min(y1, y_first + 13) + 1):
            for x in range(max(x0, x_first), min(x1, x_first + 19) + 1):
                wanted[y - y_first, x - x_first] += by_hand(query, fov, x, y)
    assert wanted.any() and np.abs(block - wanted).max() <= len(shapes)


def test_largest_cells_with_a_known_least_sum_are_the_same():
    block = np.random.default_rng(3).integers(0, 9, (30, 40))
    full = kernel.largest_cells(block, 2, 5, 7)
    assert kernel.largest_cells(block, 2, 5, 7, full[-1][2]) == kernel.largest_cells(block, 2, 5, 7, 5) == full and len(full) == 7
    assert kernel.largest_cells(np.zeros((3, 3), np.int64), 0, 0, 7) == []


@pytest.mark.parametrize("work", [matrix.LEAST_WORK, 1_000])
def test_whole_tiles_name_their_largest_cells_only(spark, monkeypatch, work):
    monkeypatch.setattr(matrix, "LEAST_WORK", work)
    fovs = W.events(spark, DIR, "mix30")
    every, few = matrix.tiled(fovs, W.T1, 16), matrix.tiled(fovs, W.T1, 16, best=5)
    assert rows_of(matrix.top_cells(few, 5)) == rows_of(matrix.top_cells(every, 5))
    assert few.count() <= 5 * 25 < every.count() if work > 1_000 else 5 * 25 < few.count() <= every.count()


def test_datasets_of_the_comparison_are_those_of_the_events(spark):
    for variant, fovs in X._datasets(spark, DIR).items():
        wanted = W.events(spark, DIR, variant)
        assert fovs.count() == wanted.count() and not fovs.select(wanted.columns).exceptAll(wanted).head(1)


def test_accuracy_does_not_count_what_only_the_overall_table_shows(spark, monkeypatch):
    asked = []
    monkeypatch.setattr(X, "_methods_of", lambda fovs, q, t, v, served=True: asked.append(served) or spark.createDataFrame([(t, v, m, 5) for m in ("clustered", "single")], "region string, dataset string, method string, within long"))
    assert {r.share_found for r in W.queries()["q_w12_accuracy"](spark, DIR).collect()} == {1.0}
    W.queries()["q_w11_overall"](spark, DIR)
    assert asked == [False] * 12 + [True] * 12
