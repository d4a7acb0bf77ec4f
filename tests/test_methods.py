from dataclasses import replace

import duckdb
import pytest

from vistapoint import workloads as W
from vistapoint.functions.intention import FIXED, Model, reach_error_bound
from vistapoint.operators import cube, matrix, sampler

DIR = "/root/testdata/sf0.001"


@pytest.fixture(scope="module")
def fovs(spark):
    return {v: W.events(spark, DIR, v).cache() for v in ("pie60", "mix30", "mix70")}


def as_dict(df):
    return {(r.cell_x, r.cell_y): r.ci_fixed for r in df.collect()}


@pytest.mark.parametrize("variant", ["pie60", "mix30", "mix70"])
def test_three_exact_forms_agree(fovs, variant):
    a, b = as_dict(matrix.naive(fovs[variant], W.T1)), as_dict(matrix.optimized(fovs[variant], W.T1))
    assert a == b
    c = as_dict(matrix.tiled(fovs[variant], W.T1, 32, 3))
    assert a.keys() == c.keys() and max(abs(a[k] - c[k]) for k in a) <= 5


def test_published_fixture_answers(spark):
    expected = {
        "pie60": [(18, 57, 18010604457), (46, 46, 16479541990), (35, 44, 16429721135), (20, 57, 16344197942), (38, 41, 16231017275)],
        "mix30": [(37, 42, 2787741013802), (38, 42, 2774685638787), (37, 43, 2753987871529), (38, 43, 2703532572943), (36, 43, 2678803883441)],
    }
    for variant, cells in expected.items():
        m = matrix.optimized(W.events(spark, "/root/testdata/sf0.01", variant), W.T1)
        got = [(r.cell_x, r.cell_y, r.ci_fixed) for r in m.orderBy(m.ci_fixed.desc(), "cell_y", "cell_x").limit(5).collect()]
        assert [g[:2] for g in got] == [c[:2] for c in cells] and all(abs(g[2] - c[2]) <= 5 for g, c in zip(got, cells, strict=True))


@pytest.mark.parametrize("measure", ["relative", "rescaled"])
def test_modes_of_clustered_sampling_agree(fovs, measure):
    o = replace(W.OPT, measure=measure, clusters=3)
    lists = [[tuple(r) for r in mode(fovs["mix30"], W.T1, o)[0].collect()] for mode in (sampler.prefix, sampler.per_cluster_task, sampler.driver_loop)]
    assert lists[0] == lists[1] == lists[2]


def test_whole_sample_in_one_batch_is_exact_inside_the_rectangles(fovs):
    o = replace(W.OPT, clusters=1, cluster_fraction=1.0, batch_fraction=1.0)
    top, rows = sampler.prefix(fovs["mix30"], W.T1, o)
    assert rows.collect()[0].p == 1.0
    exact = as_dict(matrix.optimized(fovs["mix30"], W.T1))
    assert all(round(exact[(r.cell_x, r.cell_y)] / FIXED, 6) >= r.ci for r in top.collect())


def test_batches_are_disjoint_and_cover(fovs):
    ready = sampler.prepare(fovs["pie60"], W.T1, W.OPT)
    rows = ready.members.select("cluster_id", "fov_id", "batch").collect()
    assert len({(r.cluster_id, r.fov_id) for r in rows}) == len(rows) == sum(ready.sizes.values())
    assert {r.batch for r in rows} <= set(range(1, 21))


def test_cube_over_all_days_is_the_matrix(fovs):
    assert as_dict(cube.over(cube.build(fovs["pie60"], W.T1))) == as_dict(matrix.optimized(fovs["pie60"], W.T1))


def test_reach_error_stays_below_its_bound(fovs):
    model = Model(reach=2.0)
    cut, full = as_dict(matrix.optimized(fovs["mix30"], replace(W.T1, model=model))), as_dict(matrix.optimized(fovs["mix30"], W.T1))
    n = fovs["mix30"].count()
    assert max(full[k] - cut.get(k, 0) for k in full) / FIXED <= reach_error_bound(model, n)


def test_naive_refuses_what_it_may_not_broadcast(fovs):
    with pytest.raises(ValueError):
        matrix.naive(fovs["pie60"], W.T1, limit=10)


def test_plans(fovs):
    text = matrix.top_cells(matrix.optimized(fovs["pie60"], W.T1), 5)._jdf.queryExecution().executedPlan().toString()
    assert "CartesianProduct" not in text and "BroadcastNestedLoopJoin" not in text and "TakeOrderedAndProject" in text


@pytest.mark.parametrize("name", ["q_topk_optimized", "q_fov_orders", "q_fov_lineitem", "q_clis_prefix_relative", "q_diff_sum", "q_trajectory", "q_w17_yearly"])
def test_oracles(spark, name):
    db = duckdb.connect()
    for t in "region nation customer supplier part orders lineitem events".split():
        db.execute(f"create view {t} as select * from '{DIR}/{t}.parquet'")
    out = db.execute(W.oracle_sql()[name])
    columns = sorted(c[0] for c in out.description)
    theirs = sorted(repr([r[[c[0] for c in out.description].index(k)] for k in columns]) for r in out.fetchall())
    df = W.queries()[name](spark, DIR)
    assert sorted(df.columns) == columns
    assert sorted(repr([r[k] for k in columns]) for r in df.collect()) == theirs
