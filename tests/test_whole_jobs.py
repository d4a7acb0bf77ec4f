"""Queries that once did a part of their job only, held against the whole."""

import threading
from dataclasses import replace

import duckdb
import pytest

from vistapoint import experiments as X
from vistapoint import workloads as W
from vistapoint.operators import matrix, sampler
from vistapoint.operators.detect import detect
from vistapoint.session import side_by_side
from vistapoint.sources import synthetic

DIR = "/root/testdata/sf0.001"


def cells_by_hand(rows, grid):
    """fov_id -> cells of the box inside the grid, counted one by one."""
    out, eps, a = {}, 1e-6, grid.area
    for r in rows:
        xs = [x for x in range(grid.nx) if (r.min_lon - a.min_lon) / grid.cell - eps < x + 1 and x <= (r.max_lon - a.min_lon) / grid.cell + eps]
        ys = [y for y in range(grid.ny) if (r.min_lat - a.min_lat) / grid.cell - eps < y + 1 and y <= (r.max_lat - a.min_lat) / grid.cell + eps]
        if xs and ys:
            out[r.fov_id] = sum(1 for _ in xs for _ in ys)
    return out


def test_udtf_runs_over_all_fields_of_view(spark):
    got = {r.fov_id: r.cells for r in W.queries()["q_udtf_cells"](spark, DIR).collect()}
    assert got == cells_by_hand(W.events(spark, DIR).collect(), W.T0.grid) and any(i % 50 for i in got)
    db = duckdb.connect()
    db.execute(f"create view events as select * from '{DIR}/events.parquet'")
    for t in ("nation", "customer", "region", "supplier"):
        db.execute(f"create view {t} as select * from '{DIR}/{t}.parquet'")
    assert dict(db.execute(f"select fov_id, cells from ({W.oracle_sql()['q_udtf_cells']})").fetchall()) == got


def test_clusters_beyond_one_task_are_answered(spark, monkeypatch):
    fovs, o = W.events(spark, DIR, "mix30"), replace(W.OPT, clusters=3)
    small = [tuple(r) for r in detect(fovs, W.T1, "clustered", o).collect()]
    listed = [tuple(r) for r in W.queries()["q_clis_topk"](spark, DIR).collect()]
    monkeypatch.setattr(sampler, "ONE_TASK", 10)
    assert small and [tuple(r) for r in detect(fovs, W.T1, "clustered", o).collect()] == small
    assert listed and [tuple(r) for r in W.queries()["q_clis_topk"](spark, DIR).collect()] == listed


def test_areas_are_counted_without_broadcasting_fields_of_view(spark):
    df = W.queries()["q_areas_outer"](spark, DIR)
    assert "BroadcastNestedLoopJoin BuildRight, LeftOuter" not in df._jdf.queryExecution().executedPlan().toString()
    db = duckdb.connect()
    db.execute(f"create view events as select * from '{DIR}/events.parquet'")
    got = {r.area_id: r.n for r in df.collect()}
    assert got == dict(db.execute(f"select area_id, n from ({W.oracle_sql()['q_areas_outer']})").fetchall()) and got[99] == 0


def test_naive_takes_any_number_of_fields_of_view(spark, monkeypatch):
    as_dict = lambda m: {(r.cell_x, r.cell_y): r.ci_fixed for r in m.collect()}
    fovs = W.events(spark, DIR, "mix30")
    many = W.kept(fovs.crossJoin(spark.range(700).select()))
    assert matrix.candidates(many, W.T0).count() > 200_000
    once = as_dict(matrix.naive(fovs, W.T0))
    assert once and as_dict(matrix.naive(many, W.T0)) == {k: 700 * v for k, v in once.items()}
    monkeypatch.setattr(matrix, "NAIVE_CELLS", 10)
    assert as_dict(matrix.naive(fovs, W.T0)) == once == as_dict(matrix.optimized(fovs, W.T0))


def test_naive_meets_large_grids_block_by_block(spark, monkeypatch):
    as_dict = lambda m: {(r.cell_x, r.cell_y): r.ci_fixed for r in m.collect()}
    fovs = W.events(spark, DIR, "mix30")
    some = W.kept(matrix.cells(spark, W.T1.grid).where("(cell_x + cell_y) % 7 = 0"))
    pairwise = {q: as_dict(matrix.naive(fovs, q)) for q in (W.T1, W.FULL, W.LINE)}
    monkeypatch.setattr(matrix, "NAIVE_CELLS", 10)
    for sides in ((64, 8), (16, 4, 2), (3,), (200,)):
        monkeypatch.setattr(matrix, "BLOCKS", sides)
        assert as_dict(matrix.naive(fovs, W.T1)) == pairwise[W.T1], sides
    assert as_dict(matrix.naive(fovs, W.T1, cells_of=some)) == {k: v for k, v in pairwise[W.T1].items() if sum(k) % 7 == 0}
    assert all(v and as_dict(matrix.naive(fovs, q)) == v for q, v in pairwise.items())
    assert "CartesianProduct" not in matrix.naive(fovs, W.T3)._jdf.queryExecution().executedPlan().toString()


def _answered(sql):
    db = duckdb.connect()
    db.execute(f"create view events as select * from '{DIR}/events.parquet'")
    return db.execute(sql).fetchall()


def test_blocks_of_the_sql_leave_no_pair_out():
    for q, wide in ((W.T1, 7), (W.T1, 200), (W.T2, 50)):
        inside = W.O.in_range(W.O.fov_with_mbr("mix30"), q.area)
        by_blocks, pairwise = W.O.naive_by_blocks("SELECT * FROM f", q, wide), W.O.naive("SELECT * FROM f", q)
        assert _answered(f"WITH f AS MATERIALIZED ({inside}), a AS MATERIALIZED ({by_blocks}), b AS MATERIALIZED ({pairwise}) SELECT (SELECT count(*) FROM a), (SELECT count(*) FROM b), count(*) FROM a JOIN b USING (cell_x, cell_y, ci_fixed)") in [[(n, n, n)] for n in range(1, q.grid.cells)]


def test_methods_are_compared_on_all_cells(spark, monkeypatch):
    columns = ("region", "naive_pairs", "optimized_pairs", "fewer", "compared", "max_gap", "diff_m", "within")
    got = sorted(tuple(r[c] for c in columns) for r in W.queries()["q_w2_table"](spark, DIR).collect())
    assert [r[4] for r in got] == [80**2, 500**2, 1200**2, 3500**2]
    assert got == sorted(_answered(f"SELECT {', '.join(columns)} FROM ({W.oracle_sql()['q_w2_table']})"))
    at = next(i for i in range(250_000) if not _answered(f"SELECT {W.O.u01_sql('cells', str(i))} < 0.008")[0][0])
    optimized = matrix.optimized
    extra = lambda m: m.union(spark.sql(f"SELECT {at % 500}L AS cell_x, {at // 500}L AS cell_y, 1000000000000L AS ci_fixed"))
    monkeypatch.setattr(matrix, "optimized", lambda *a, **b: matrix.summed(extra(optimized(*a, **b))))
    monkeypatch.setattr(X, "TARGETS", {"t2": W.T2})
    assert [(r.max_gap, r.diff_m > 0) for r in W.queries()["q_w2_table"](spark, DIR).collect()] == [(1.0, True)]


def test_boxes_of_some_cells_are_those_of_all(spark):
    fovs, some = W.events(spark, DIR, "mix30"), W.kept(matrix.cells(spark, W.T1.grid).where("(cell_x + cell_y) % 7 = 0"))
    few = {(r.cell_x, r.cell_y): r.ci_fixed for r in matrix.optimized(fovs, W.T1, cells_of=some).collect()}
    assert few and few == {(r.cell_x, r.cell_y): r.ci_fixed for r in matrix.optimized(fovs, W.T1).collect() if (r.cell_x + r.cell_y) % 7 == 0}


def test_auto_names_the_method_and_not_its_physical_form(spark, monkeypatch):
    small = [tuple(r) for r in W.queries()["q_auto_small"](spark, DIR).collect()]
    monkeypatch.setattr(matrix, "plan", lambda *a: "tiled")
    assert small and [tuple(r) for r in W.queries()["q_auto_small"](spark, DIR).collect()] == small


def test_made_up_fields_of_view_are_those_of_the_events(spark):
    events = spark.read.parquet(f"{DIR}/events.parquet")
    got = {r.fov_id: tuple(r) for r in W.queries()["q_source_synthetic"](spark, DIR).collect()}
    assert {k: v[1] for k, v in got.items()} == {r.event_id: r.user_id for r in events.collect()} and len(got) == events.count()
    spark.dataSource.register(synthetic.SyntheticFovs)
    made = spark.read.format("synthetic_fov").option("rows", 50).load().collect()
    assert len(made) == 50 and all(got[r.fov_id][2:] == tuple(r)[2:] for r in made if r.fov_id in got) and made[0].fov_id in got


class Stopped(Exception):
    pass


def test_experiments_name_their_regions(spark, monkeypatch):
    asked = []

    def recorded(fovs, query, options):
        asked.append(query)
        raise Stopped

    monkeypatch.setattr(sampler, "prepare", recorded)
    monkeypatch.setattr(X, "detect", lambda fovs, query, *a, **b: spark.range(0))
    for name in ("q_w8_grid", "q_threshold_sweep", "q_w10_sweep"):
        with pytest.raises(Stopped):
            W.queries()[name](spark, DIR)
    assert asked == [W.T4] * 3


def test_overall_covers_regions_and_datasets(spark, monkeypatch):
    nothing = sampler.Prepared(spark.range(0), spark.createDataFrame([], "fov_id long, cluster_id long, batch long"), {}, {})
    monkeypatch.setattr(sampler, "prepare", lambda *a, **b: nothing)
    monkeypatch.setattr(sampler, "per_cluster_task", lambda *a, **b: (spark.range(0), spark.createDataFrame([(1, 1, 1)], "cluster_id long, iter long, seen long")))
    monkeypatch.setattr(X, "detect", lambda *a, **b: spark.range(0))
    monkeypatch.setattr(X, "kept", lambda df: df)
    monkeypatch.setattr(X.matrix, "candidates", lambda *a: spark.range(1))
    monkeypatch.setattr(X.measures, "diff", lambda *a: spark.range(1).selectExpr("0.0D as diff_m", "5L as within"))
    got = {(r.region, r.dataset, r.method) for r in W.queries()["q_w12_accuracy"](spark, DIR).collect()}
    assert got == {(t, v, m) for t in ("t1", "t2", "t3", "t4") for v in W.fov.VARIANTS for m in ("clustered", "single")}


def test_overall_runs_its_regions_side_by_side(spark, monkeypatch):
    met, asked = threading.Barrier(2), []

    def meeting(fovs, query, options):
        asked.append(query)
        met.wait(60)
        raise Stopped

    monkeypatch.setattr(sampler, "prepare", meeting)
    monkeypatch.setattr(X, "detect", lambda *a, **b: spark.range(0))
    with pytest.raises(Stopped):
        W.queries()["q_w11_overall"](spark, DIR)
    assert len(asked) >= 2 and asked[0] == W.T4


def test_side_by_side_keeps_order_and_the_job_group(spark):
    spark.sparkContext.setJobGroup("all", "of them")
    got = side_by_side(spark, lambda i: (i, spark.range(i).count(), spark.sparkContext.getLocalProperty("spark.jobGroup.id")), range(5), 3)
    assert got == [(i, i, "all") for i in range(5)]


def test_single_samples_of_many_pairs_are_summed_in_blocks(spark, monkeypatch):
    fovs, taken = W.events(spark, DIR, "mix30"), []
    small = [tuple(r) for r in detect(fovs, W.T1, "single_sample", fraction=0.5).collect()]
    tiled = matrix.tiled
    monkeypatch.setattr(matrix, "tiled", lambda *a, **b: taken.append(a) or tiled(*a, **b))
    monkeypatch.setattr(matrix, "plan", lambda *a: "tiled")
    assert small and [tuple(r) for r in detect(fovs, W.T1, "single_sample", fraction=0.5).collect()] == small and taken


def test_little_work_takes_few_tasks(spark):
    few = matrix.dense(matrix.candidates(W.events(spark, DIR), W.T1), W.T1, tasks=64)
    assert "REPARTITION_BY_NUM, [plan_id" in (text := few._jdf.queryExecution().executedPlan().toString()) and ", 64), REPARTITION" not in text
