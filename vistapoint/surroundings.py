"""Queries around the methods: scans, formats, joins, aggregates, windows, functions, and SQL surfaces on fields of view."""

from __future__ import annotations

import uuid
from dataclasses import replace

import numpy as np
import pandas as pd
from pyspark.sql import Window
from pyspark.sql import functions as F

from . import oracles as O
from .functions import geo
from .functions.noise import u01_sql

from .operators import matrix, measures, retrieval, sampler
from .operators.detect import ResultCache
from .operators.kernel import add_fovs, largest_cells
from .session import kept, shared_folder
from .sources import carriers, formats, store, synthetic
from .streaming import ingest, stateful
from . import experiments  # noqa: F401  registers what some names stand for
from .workloads import FOV_E, FOV_O, IN_AREA, M1, OPT, QUERIES, SQL, T0, T1, T2, T4, _areas, events, register, rounded, rounded_sql, table, top

IN_MIX = O.in_range(O.fov_with_mbr("mix30"), T1.area)
NOISE = u01_sql("s0", "fov_id")

E_SQL = O.fov_with_mbr("pie60")


def _scratch(spark) -> str:
    """A new folder in the folder that driver and executors share."""
    return f"{shared_folder(spark, 'scratch')}/{uuid.uuid4().hex}"


def _taken(df, *paths: str):
    """``df`` computed and stored as a checkpoint, after which the folders that it was read from are removed."""
    spark, out = df.sparkSession, kept(df)
    for path in paths:
        folder = spark._jvm.org.apache.hadoop.fs.Path(path)
        folder.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(folder, True)
    return out


register("q_scan_events", lambda s, d: table(s, d, "events").where("event_type = 'view' and value > 100").select("event_id", "value"), "SELECT event_id, value FROM events WHERE event_type = 'view' AND value > 100")


def _round_trip(kind):
    def run(s, d):
        path = _scratch(s)
        formats.write(carriers.from_events(s, d), path, kind)
        return _taken(rounded(formats.read(s, path, kind)), path)

    return run


for _k in ("csv", "json", "orc"):
    register(f"q_roundtrip_{_k}", _round_trip(_k), rounded_sql(FOV_E, "fov_id video_id t", "lat lon theta r_m alpha"))


def _store(s, d):
    path = _scratch(s)
    store.write(carriers.from_events(s, d), path, 4)
    found = retrieval.fovs_in_range(store.read(s, path), T2.area)
    return _taken(found.groupBy("day").agg(F.count("*").alias("n"), F.sum("fov_id").alias("ids")), path)


register("q_store_readback", _store, f"SELECT t::DATE AS day, count(*) AS n, sum(fov_id)::BIGINT AS ids FROM ({O.in_range(E_SQL, T2.area)}) GROUP BY 1")


def _synthetic(s, d):
    """A made-up field of view for each event."""
    return synthetic.over(table(s, d, "events").select(F.col("event_id").alias("fov_id"), F.col("user_id").alias("video_id")))


register("q_source_synthetic", _synthetic)


def _view(s, d):
    events(s, d).createOrReplaceTempView("fov")
    return s.sql("select video_id, count(*) as n, round(avg(r_m), 6) as r_m from fov group by video_id")


register("q_sql_view", _view, f"SELECT video_id, count(*) AS n, round(avg(r_m), 6) AS r_m FROM ({FOV_E}) GROUP BY video_id")
register("q_project_struct", lambda s, d: carriers.from_events(s, d).select("fov_id", F.struct("theta", "alpha").alias("s")).select("fov_id", F.round("s.theta", 6).alias("theta"), "s.alpha"), rounded_sql(FOV_E, "fov_id alpha", "theta"))
register("q_join_hints", lambda s, d: table(s, d, "lineitem").hint("merge").join(table(s, d, "orders").hint("shuffle_hash"), F.col("l_orderkey") == F.col("o_orderkey")).groupBy("o_orderpriority").agg(F.count("*").alias("n")), "SELECT o_orderpriority, count(*) AS n FROM lineitem JOIN orders ON l_orderkey = o_orderkey GROUP BY 1")

RECTS = carriers.SPOTS[:6]
RECT_SQL = "(VALUES " + ", ".join(f"({i}::BIGINT, {10.0 + a - 0.001!r}::DOUBLE, {10.0 + a + 0.001!r}::DOUBLE, {20.0 + b - 0.001!r}::DOUBLE, {20.0 + b + 0.001!r}::DOUBLE)" for i, (a, b) in enumerate(RECTS)) + ") AS rects(rect_id, a0, a1, b0, b1)"
HIT = "max_lat >= a0 AND min_lat <= a1 AND max_lon >= b0 AND min_lon <= b1"


def _rects(s):
    return s.createDataFrame([(i, 10.0 + a - 0.001, 10.0 + a + 0.001, 20.0 + b - 0.001, 20.0 + b + 0.001) for i, (a, b) in enumerate(RECTS)], "rect_id long, a0 double, a1 double, b0 double, b1 double")


def _tiled_join(s, d, degrees=0.01):
    """A range join as an equi-join on tiles with the exact test behind it: the form for many rectangles; both sides are exploded to the tiles they touch."""
    cut = lambda df, lo, hi, name: df.withColumn(name, F.explode(F.sequence(F.floor(F.col(lo) / degrees), F.floor(F.col(hi) / degrees))))
    left = cut(cut(events(s, d), "min_lat", "max_lat", "ty"), "min_lon", "max_lon", "tx")
    right = cut(cut(_rects(s), "a0", "a1", "ty"), "b0", "b1", "tx")
    return left.join(right, ["tx", "ty"]).where(HIT).select("rect_id", "fov_id").distinct()


register("q_range_join_tiled", _tiled_join, f"SELECT rect_id, fov_id FROM ({E_SQL}), {RECT_SQL} WHERE {HIT}")
register("q_dense_fovs", lambda s, d: events(s, d).join(F.broadcast(_rects(s)), F.expr(HIT), "left_semi").select("fov_id"), f"SELECT fov_id FROM ({E_SQL}) WHERE EXISTS (SELECT 1 FROM {RECT_SQL} WHERE {HIT})")
register("q_sparse_fovs", lambda s, d: events(s, d).join(F.broadcast(_rects(s)), F.expr(HIT), "left_anti").select("fov_id"), f"SELECT fov_id FROM ({E_SQL}) WHERE NOT EXISTS (SELECT 1 FROM {RECT_SQL} WHERE {HIT})")
register("q_interval_join", lambda s, d: carriers.from_events(s, d).join(F.broadcast(s.sql("select cast(i as bigint) as week_no, timestamp_ntz'2024-01-01' + make_interval(0, 0, i) as lo from range(5) as t(i)").withColumn("hi", F.expr("lo + interval 7 days"))), F.expr("t >= lo and t < hi")).groupBy("week_no").agg(F.count("*").alias("n")), "SELECT i AS week_no, count(*) AS n FROM events, range(5) r(i) WHERE ts >= TIMESTAMP '2024-01-01' + to_days((7 * i)::INT) AND ts < TIMESTAMP '2024-01-08' + to_days((7 * i)::INT) GROUP BY i")


def _as_of(s, d):
    """The latest field of view of each video at or before noon of each day, however long ago."""
    noons = s.sql("select timestamp_ntz'2024-01-01 12:00:00' + make_dt_interval(i) as at from (select explode(sequence(0, 29)) as i)")
    fovs = carriers.from_events(s, d).select("video_id", "t", "fov_id")
    asked = fovs.select("video_id").distinct().crossJoin(F.broadcast(noons))
    return retrieval.latest_before(fovs, asked).where("fov_id is not null").withColumnRenamed("at", "noon")


register("q_asof_video", _as_of, "SELECT user_id AS video_id, noon, arg_max(event_id, (ts, event_id)) AS fov_id FROM events, (SELECT TIMESTAMP '2024-01-01 12:00:00' + to_days(i::INT) AS noon FROM range(30) r(i)) WHERE ts <= noon GROUP BY 1, 2")
register("q_users_per_cell", lambda s, d: _cells(s, d).groupBy("cell_x", "cell_y").agg(F.countDistinct("video_id").alias("videos")), f"SELECT floor((lon - {T2.area.min_lon!r}::DOUBLE) / 0.001::DOUBLE)::BIGINT AS cell_x, floor((lat - {T2.area.min_lat!r}::DOUBLE) / 0.001::DOUBLE)::BIGINT AS cell_y, count(DISTINCT video_id) AS videos FROM ({O.in_range(E_SQL, T2.area)}) GROUP BY 1, 2")
register("q_users_approx", lambda s, d: _cells(s, d).groupBy("cell_y").agg(F.approx_count_distinct("video_id").alias("videos")))


def _cells(s, d):
    x, y = F.floor((F.col("lon") - T2.area.min_lon) / 0.001), F.floor((F.col("lat") - T2.area.min_lat) / 0.001)
    return retrieval.fovs_in_range(events(s, d), T2.area).select(x.alias("cell_x"), y.alias("cell_y"), "video_id")


register("q_best_cell", lambda s, d: matrix.optimized(events(s, d), T1).groupBy(F.floor(F.col("cell_y") / 10).alias("band")).agg(F.max(F.struct("ci_fixed", -F.col("cell_x"), -F.col("cell_y"))).alias("m")).select("band", F.round(F.col("m.ci_fixed") / 1e12, 6).alias("ci")), f"SELECT floor(cell_y / 10)::BIGINT AS band, round(max(ci_fixed) / 1e12::DOUBLE, 6) AS ci FROM ({M1}) GROUP BY 1")
register("q_range_percentiles", lambda s, d: carriers.from_events(s, d).agg(*[F.round(F.percentile("r_m", p), 6).alias(f"p{int(100 * p)}") for p in (0.1, 0.5, 0.9)]), f"SELECT {', '.join(f'round(quantile_cont(r_m, {p}), 6) AS p{int(100 * p)}' for p in (0.1, 0.5, 0.9))} FROM ({FOV_E})")

for _n, _f in (("rollup_place", "rollup"), ("cube_place_month", "cube")):
    _cols = ["region_name", "nation_name"] if _f == "rollup" else ["region_name", "month"]
    _sel = "region_name, nation_name" if _f == "rollup" else "region_name, month"
    register(f"q_{_n}", lambda s, d, f=_f, c=_cols: getattr(carriers.from_orders(s, d).withColumn("month", F.month("t")), f)(*c).agg(F.count("*").alias("n"), F.sum(F.floor("r_m")).alias("r_sum")), f"SELECT {_sel}, count(*) AS n, sum(floor(r_m))::BIGINT AS r_sum FROM (SELECT *, month(t)::INT AS month FROM ({FOV_O})) GROUP BY {_f.upper()} ({_sel})")


def _sets(s, d):
    carriers.from_orders(s, d).createOrReplaceTempView("fov_o")
    return s.sql("select region_name, nation_name, count(*) as n from fov_o group by grouping sets ((region_name), (nation_name), ())")


register("q_grouping_sets", _sets, f"SELECT region_name, nation_name, count(*) AS n FROM ({FOV_O}) GROUP BY GROUPING SETS ((region_name), (nation_name), ())")
register("q_pivot_variant", lambda s, d: carriers.from_events(s, d, "mix30").groupBy("video_id").pivot("alpha", [160.0, 360.0]).agg(F.count(F.lit(1))).select("video_id", F.coalesce("`160.0`", F.lit(0)).alias("pies"), F.coalesce("`360.0`", F.lit(0)).alias("discs")), f"SELECT video_id, count(*) FILTER (alpha = 160) AS pies, count(*) FILTER (alpha = 360) AS discs FROM ({O.fov_events('mix30')}) GROUP BY 1")
_W = "OVER (PARTITION BY video_id ORDER BY floor(r_m), fov_id % 10)"
register("q_window_ranks", lambda s, d: _ranks(s, d), f"SELECT fov_id, rank() {_W} AS rank, dense_rank() {_W} AS dense FROM ({FOV_E})")


def _ranks(s, d):
    w = Window.partitionBy("video_id").orderBy(F.floor("r_m"), F.col("fov_id") % 10)
    return carriers.from_events(s, d).select("fov_id", F.rank().over(w).cast("long").alias("rank"), F.dense_rank().over(w).cast("long").alias("dense"))


def _range_frame(s, d):
    w = Window.partitionBy("video_id").orderBy("sec").rangeBetween(-3600 * 24, 0)
    return carriers.from_events(s, d).withColumn("sec", F.unix_seconds(F.col("t").cast("timestamp"))).select("fov_id", F.count("*").over(w).alias("last_day"))


register("q_range_frame", _range_frame, "SELECT event_id AS fov_id, count(*) OVER (PARTITION BY user_id ORDER BY floor(epoch(ts))::BIGINT RANGE BETWEEN 86400 PRECEDING AND CURRENT ROW) AS last_day FROM events")
register("q_dedup", lambda s, d: carriers.from_events(s, d).union(carriers.from_events(s, d)).dropDuplicates(["fov_id"]).agg(F.count("*").alias("n"), F.sum("fov_id").alias("ids")), "SELECT count(*) AS n, sum(event_id)::BIGINT AS ids FROM events")
register("q_native_sample", lambda s, d: carriers.from_events(s, d).sample(0.1, 7).select("fov_id"))
register("q_union_carriers", lambda s, d: carriers.from_events(s, d).select("video_id").unionByName(carriers.from_orders(s, d).select("video_id")).unionByName(carriers.from_lineitem(s, d).select("video_id")).agg(F.count("*").alias("n"), F.countDistinct("video_id").alias("videos")), "SELECT count(*) AS n, count(DISTINCT v) AS videos FROM (SELECT user_id AS v FROM events UNION ALL SELECT o_custkey FROM orders JOIN customer ON o_custkey = c_custkey UNION ALL SELECT o_custkey FROM lineitem JOIN orders ON l_orderkey = o_orderkey JOIN customer ON o_custkey = c_custkey)")
register("q_cell_label", lambda s, d: matrix.top_cells(matrix.optimized(events(s, d), T1), 5).select("rank", F.format_string("cell-%05d-%05d", "cell_x", "cell_y").alias("label")), f"SELECT rank, printf('cell-%05d-%05d', cell_x, cell_y) AS label FROM ({O.top_of(T1, 'pie60')})")
register("q_json_props", lambda s, d: table(s, d, "events").select("event_id", F.from_json("props", "k int")["k"].alias("k")), "SELECT event_id, (props::JSON->>'$.k')::INT AS k FROM events")
register("q_zorder", lambda s, d: table(s, d, "events").select("event_id", geo.z_order(F.col("user_id"), F.col("event_id"), 16).alias("z")), "SELECT event_id, list_sum(list_transform(range(16), lambda b: (((user_id >> b) & 1) << (2 * b)) + (((event_id >> b) & 1) << (2 * b + 1))))::BIGINT AS z FROM events")
register("q_cells_map", lambda s, d: matrix.top_cells(matrix.optimized(events(s, d), T1), 5).groupBy(F.lit(1).alias("g")).agg(F.map_from_entries(F.collect_list(F.struct("rank", "cell_x"))).alias("m")).select(F.map_filter("m", lambda k, v: k <= 3).alias("m")).select(F.explode("m").alias("rank", "cell_x")), f"SELECT rank, cell_x FROM ({O.top_of(T1, 'pie60')}) WHERE rank <= 3")
DAY = "date_trunc('day', ts)"
register("q_window_tumbling", lambda s, d: ingest.window_counts(carriers.from_events(s, d)), f"SELECT {DAY} AS win_start, {DAY} + INTERVAL 1 DAY AS win_end, count(*) AS n FROM events GROUP BY 1, 2")
register("q_window_sliding", lambda s, d: ingest.window_counts(carriers.from_events(s, d), "sliding"), "SELECT w AS win_start, w + INTERVAL 1 DAY AS win_end, count(*) AS n FROM (SELECT time_bucket(INTERVAL 6 HOUR, ts, TIMESTAMP '1970-01-01') - INTERVAL 6 HOUR * i AS w FROM events, range(4) r(i)) GROUP BY 1, 2")
register("q_window_session", lambda s, d: ingest.window_counts(carriers.from_events(s, d), "session"), "SELECT user_id AS video_id, min(ts) AS win_start, max(ts) + INTERVAL 6 HOUR AS win_end, count(*) AS n FROM (SELECT *, sum(fresh) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS g FROM (SELECT *, CASE WHEN ts - lag(ts) OVER (PARTITION BY user_id ORDER BY ts, event_id) < INTERVAL 6 HOUR THEN 0 ELSE 1 END AS fresh FROM events)) GROUP BY user_id, g")


def _sql_ci(s, d):
    s.sql("create or replace temporary function ci_of(off double, alpha double, d double, r double) returns double return (case when alpha >= 360 then 1 when off <= alpha / 2 then exp(-off * off / 450) / (15 * sqrt(2 * pi())) else 0 end) * (case when d <= r then exp(-d * d / 1250) / (25 * sqrt(2 * pi())) else 0 end)")
    table(s, d, "events").createOrReplaceTempView("ev")
    return s.sql("select event_id, round(ci_of(event_id % 40, if(event_id % 3 = 0, 360, 60), value, 100), 9) as ci from ev")


register("q_sql_ci", _sql_ci, "SELECT event_id, round((CASE WHEN event_id % 3 = 0 THEN 1.0 WHEN o <= 30 THEN exp(-o * o / 450.0::DOUBLE) / (15 * sqrt(2 * pi())) ELSE 0 END) * (CASE WHEN value <= 100 THEN exp(-value * value / 1250.0::DOUBLE) / (25 * sqrt(2 * pi())) ELSE 0 END), 9) AS ci FROM (SELECT *, (event_id % 40)::DOUBLE AS o FROM events)")


def _udaf(s, d):
    @F.pandas_udf("long")
    def second_largest(v: pd.Series) -> int:
        return int(v.nlargest(2).iloc[-1])

    return matrix.optimized(events(s, d), T0).groupBy("cell_y").agg(second_largest("ci_fixed").alias("second")).select("cell_y", F.round(F.col("second") / 1e12, 6).alias("ci"))


register("q_udaf_topk", _udaf, f"SELECT cell_y, round((CASE WHEN count(*) > 1 THEN list_sort(list(ci_fixed), 'DESC')[2] ELSE max(ci_fixed) END) / 1e12::DOUBLE, 6) AS ci FROM ({O.matrix(O.in_range(E_SQL, T0.area), T0)}) GROUP BY cell_y")


def _udaf_cells(s, d):
    """The three largest cells of each row of T0 by an aggregate function over columns."""

    @F.pandas_udf("array<long>")
    def topk_cells(cell_x: pd.Series, ci: pd.Series) -> list:
        return pd.DataFrame({"x": cell_x, "ci": -ci}).sort_values(["ci", "x"])["x"].head(3).tolist()

    rows = matrix.optimized(events(s, d), T0).groupBy("cell_y").agg(topk_cells("cell_x", "ci_fixed").alias("cells"))
    return rows.select("cell_y", F.posexplode("cells").alias("place", "cell_x")).select("cell_y", (F.col("place") + 1).cast("long").alias("rank"), "cell_x")


register("q_udaf_topk_cells", _udaf_cells, f"SELECT cell_y, rank, cell_x FROM (SELECT *, row_number() OVER (PARTITION BY cell_y ORDER BY ci_fixed DESC, cell_x) AS rank FROM ({O.matrix(O.in_range(E_SQL, T0.area), T0)})) WHERE rank <= 3")


def _udtf(s, d):
    from pyspark.sql.functions import udtf

    @udtf(returnType="cell_x bigint, cell_y bigint")
    class FovCells:
        """The cells of a span."""

        def eval(self, x0: int, x1: int, y0: int, y1: int):
            for y in range(y0, y1 + 1):
                for x in range(x0, x1 + 1):
                    yield x, y

    s.udtf.register("fov_cells", FovCells)
    matrix.with_span(matrix.candidates(events(s, d), T0), T0).createOrReplaceTempView("spans")
    return s.sql("select fov_id, count(*) as cells from spans, lateral fov_cells(x0, x1, y0, y1) group by fov_id")


register("q_udtf_cells", _udtf, f"SELECT fov_id, (x1 - x0 + 1) * (y1 - y0 + 1) AS cells FROM ({O.span(O.in_range(E_SQL, T0.area), T0)})")
SPAN_COLUMNS = ("lat", "lon", "theta", "r_m", "alpha", "x0", "x1", "y0", "y1")


def _udtf_intentions(s, d):
    """The matrix of T0 by a table function that yields the cells of a field of view with their intentions."""
    from pyspark.sql.functions import udtf

    @udtf(returnType="cell_x bigint, cell_y bigint, ci_fixed bigint")
    class FovIntentions:
        def eval(self, lat, lon, theta, r_m, alpha, x0, x1, y0, y1):
            block = np.zeros((y1 - y0 + 1, x1 - x0 + 1), np.int64)
            add_fovs(block, x0, y0, T0, [np.array([v]) for v in (lat, lon, theta, r_m, alpha, x0, x1, y0, y1)])
            for y, x in zip(*np.nonzero(block), strict=True):
                yield int(x) + x0, int(y) + y0, int(block[y, x])

    s.udtf.register("fov_intentions", FovIntentions)
    matrix.with_span(matrix.candidates(events(s, d), T0), T0, clip=True).createOrReplaceTempView("clipped_spans")
    cells = s.sql(f"select c.* from clipped_spans, lateral fov_intentions({', '.join(SPAN_COLUMNS)}) as c")
    return matrix.summed(cells).select("cell_x", "cell_y", F.round(F.col("ci_fixed") / 1e12, 6).alias("ci"))


register("q_udtf_intentions", _udtf_intentions, f"SELECT cell_x, cell_y, round(ci_fixed / 1e12::DOUBLE, 6) AS ci FROM ({O.matrix(O.in_range(E_SQL, T0.area), T0)})")


def _udtf_hotspots(s, d):
    """The top-3 cells of many small areas by a table function over a partitioned table; a partition holds its area's sums only."""
    from pyspark.sql.functions import udtf

    @udtf(returnType="area_id bigint, rank bigint, cell_x bigint, cell_y bigint, ci double")
    class Hotspots:
        def __init__(self):
            self.block = self.area = None

        def eval(self, row, k: int):
            self.k = k
            if self.block is None:
                self.area, self.x0, self.y0 = row["area_id"], row["bx0"], row["by0"]
                self.block = np.zeros((max(row["by1"] - row["by0"] + 1, 0), max(row["bx1"] - row["bx0"] + 1, 0)), np.int64)
            add_fovs(self.block, self.x0, self.y0, T4, [np.array([row[c]]) for c in SPAN_COLUMNS])

        def terminate(self):
            if self.block is not None:
                for i, (x, y, v) in enumerate(largest_cells(self.block, self.x0, self.y0, self.k)):
                    yield self.area, i + 1, x, y, round(v / 1e12, 6)

    s.udtf.register("hotspots", Hotspots)
    inside = matrix.with_span(events(s, d).join(F.broadcast(_areas(s)), F.expr(IN_AREA)), T4, clip=True)
    cell = lambda v, o, f: f((F.col(v) - o) / T4.cell).cast("long")
    a = T4.area
    bounds = inside.withColumns({"bx0": cell("a_min_lon", a.min_lon, F.ceil), "bx1": cell("a_max_lon", a.min_lon, F.floor), "by0": cell("a_min_lat", a.min_lat, F.ceil), "by1": cell("a_max_lat", a.min_lat, F.floor)})
    bounds.select("area_id", "bx0", "bx1", "by0", "by1", *SPAN_COLUMNS).createOrReplaceTempView("area_spans")
    return s.sql("select * from hotspots(table(area_spans) partition by (area_id), 3)")


register("q_udtf_hotspots", _udtf_hotspots, SQL["q_w18_areas"])


def _recursive(s, d):
    """The greedy pairing of two top-k lists as a recursive query that walks the pairs in the order of their distance."""
    w, h = measures.cell_metres(T1)
    one, two = top(s, d, T1), top(s, d, T1, method="single_sample", fraction=0.3)
    far = F.sqrt(F.pow((F.col("ax") - F.col("bx")) * F.lit(w), F.lit(2.0)) + F.pow((F.col("ay") - F.col("by")) * F.lit(h), F.lit(2.0)))
    pairs = one.select(F.col("rank").alias("i"), F.col("cell_x").alias("ax"), F.col("cell_y").alias("ay")).crossJoin(two.select(F.col("rank").alias("j"), F.col("cell_x").alias("bx"), F.col("cell_y").alias("by"))).withColumn("d", far)
    kept(pairs.select(F.row_number().over(Window.orderBy("d", "i", "j")).alias("n"), "i", "j", "d")).createOrReplaceTempView("ordered_pairs")  # k * k rows
    return s.sql(
        """with recursive walk(n, used_i, used_j, total) as (
             select 0, cast(array() as array<bigint>), cast(array() as array<bigint>), cast(0 as double)
             union all
             select p.n, if(free, array_append(used_i, p.i), used_i), if(free, array_append(used_j, p.j), used_j), if(free, total + d, total)
             from (select w.*, p.n as next, p.i, p.j, p.d, not array_contains(w.used_i, p.i) and not array_contains(w.used_j, p.j) as free from walk w join ordered_pairs p on p.n = w.n + 1) p
           ) select round(max_by(total, n), 6) as diff_m from walk""".replace("select p.n, if", "select p.next, if")
    )


IN_T1 = O.in_range(E_SQL, T1.area)
DRAWN = O.top(O.matrix(f"SELECT * FROM ({IN_T1}) ORDER BY {NOISE}, fov_id LIMIT (SELECT ceil(round(0.3 * count(*), 9))::BIGINT FROM ({IN_T1}))", T1), 5)
register("q_diff_sum_recursive", _recursive, f"SELECT diff_m FROM ({O.greedy(O.top_of(T1, 'pie60'), DRAWN, T1)})")


def _export(s, d):
    path = _scratch(s)
    formats.export_heatmap(measures.heatmap(matrix.optimized(events(s, d), T1), 4), path)
    return _taken(formats.read(s, path, "csv", "bin_x long, bin_y long, gamma double"), path)


register("q_export_heatmap", _export, SQL["q_heatmap"])


def _export_top(s, d):
    path = _scratch(s)
    formats.export_top(top(s, d, T1), path)
    return _taken(formats.read(s, path, "json", "rank long, cell_x long, cell_y long, ci double"), path)


register("q_export_topk", _export_top, O.top_of(T1, "pie60"))


def _result_cache(s, d):
    """The same query twice through the result cache: the second answer is read, and the table behind it is not asked."""
    folder = _scratch(s)
    cache = ResultCache(folder)
    cache.detect(events(s, d), "v1", T1, "optimized")
    return _taken(cache.detect(s.createDataFrame([], events(s, d).schema), "v1", T1, "optimized"), folder)


register("q_result_cache", _result_cache, O.top_of(T1, "pie60"))


def _stream_ingest(s, d):
    """The events as a stream into the store, boxes at ingestion, and the store read back."""
    path, marks = _scratch(s), _scratch(s)
    ingest.ingest(ingest.event_stream(s, f"{d}/events.parque[t]"), path, marks).awaitTermination()
    found = retrieval.fovs_in_range(store.read(s, path), T2.area)
    return _taken(found.groupBy("day").agg(F.count("*").alias("n"), F.sum("fov_id").alias("ids")), path, marks)


register("q_stream_ingest", _stream_ingest, SQL["q_store_readback"])


def _stream_tiles(s, d):
    """Running totals of each tile by a stateful processor whose timers report a tile when its events have passed the watermark."""
    path, marks = _scratch(s), _scratch(s)
    fovs = carriers.events_to_fovs(ingest.event_stream(s, f"{d}/events.parque[t]"))
    stateful.report_tiles(fovs, path, marks)
    return _taken(stateful.latest_reports(s.read.parquet(path)), path, marks)


register("q_stream_tiles", _stream_tiles, f"SELECT tile_x, tile_y, count(*) AS n, count(DISTINCT video_id) AS videos FROM (SELECT *, floor(lon / 0.1::DOUBLE)::BIGINT AS tile_x, floor(lat / 0.1::DOUBLE)::BIGINT AS tile_y FROM ({FOV_E})) GROUP BY 1, 2")
register("q_sample_by", lambda s, d: carriers.from_events(s, d, "mix30").sampleBy("alpha", {160.0: 1.0, 360.0: 0.0}, 7).select("fov_id", "alpha"), f"SELECT fov_id, alpha FROM ({O.fov_events('mix30')}) WHERE alpha = 160")


def _table_sample(s, d):
    carriers.from_events(s, d).createOrReplaceTempView("fov_all")
    return s.sql("select fov_id from fov_all tablesample (10 percent) repeatable (7)")


register("q_tablesample", _table_sample)


# --- further measures, and the names under which the blueprint lists some queries -----------------------------------------


def _processed_cells(s, d):
    """grid_cells of all cluster rectangles, and cell_visits: pairs evaluated for the fields of view seen when each cluster stopped."""
    ready = sampler.prepare(events(s, d), T1, OPT)
    stops = sampler.trace(ready, T1, OPT).where("iter = stop").select("cluster_id", "stop")
    grid = ready.rects.agg(F.sum((F.col("cx1") - F.col("cx0") + 1) * (F.col("cy1") - F.col("cy0") + 1)).alias("grid_cells"))
    spans = matrix.with_span(ready.members, T1).join(F.broadcast(stops), "cluster_id").where("batch <= stop")
    w = F.greatest(F.least("x1", "cx1") - F.greatest("x0", "cx0") + 1, F.lit(0)) * F.greatest(F.least("y1", "cy1") - F.greatest("y0", "cy0") + 1, F.lit(0))
    return grid.crossJoin(spans.agg(F.sum(w).alias("cell_visits")))


register(
    "q_processed_cells",
    _processed_cells,
    O.clustered("pie60", T1, OPT, f"SELECT (SELECT sum((cx1 - cx0 + 1) * (cy1 - cy0 + 1))::BIGINT FROM ranges) AS grid_cells, sum(greatest(least(x1, cx1) - greatest(x0, cx0) + 1, 0) * greatest(least(y1, cy1) - greatest(y0, cy0) + 1, 0))::BIGINT AS cell_visits FROM ({O.span('SELECT * FROM mem', T1)}) JOIN stops USING (cluster_id) WHERE batch <= stop"),
)
COARSE = replace(T1, cell=0.0005)


def _coarse(s, d):
    """The summed distance between the fine list and the coarse one, whose cells count by their middle fine cell."""
    fine, coarse = top(s, d, T1), top(s, d, COARSE)
    return measures.diff(fine, coarse.withColumns({"cell_x": F.col("cell_x") * 5 + 2, "cell_y": F.col("cell_y") * 5 + 2}), T1)


register("q_coarse_vs_fine", _coarse, O.greedy(O.top_of(T1, "pie60"), f"SELECT rank, cell_x * 5 + 2 AS cell_x, cell_y * 5 + 2 AS cell_y FROM ({O.top_of(COARSE, 'pie60')})", T1))
register("q_diff_within_20m", lambda s, d: measures.diff(top(s, d, T1, "mix30"), top(s, d, T1, "mix30", "single_sample", fraction=0.5), T1).select("within"), f"SELECT within FROM ({O.greedy(O.top_of(T1, 'mix30'), O.top(O.matrix(f'SELECT * FROM ({IN_MIX}) ORDER BY {NOISE}, fov_id LIMIT (SELECT ceil(round(0.5 * count(*), 9))::BIGINT FROM ({IN_MIX}))', T1), 5), T1)})")
for _alias, _name in {"q_fov_mbr": "q_fov_mbr_pie60", "q_region_stats": "q_region_stats_t1", "q_cells_per_mbr": "q_cells_per_mbr_t1_pie60", "q_clis_prefix": "q_clis_prefix_relative", "q_topk_tiled": "q_topk_tiled_pie60", "q_topk_per_week": "q_w17_weekly", "q_w10_sweep": "q_threshold_sweep", "q_udtf_cells_all": "q_udtf_cells"}.items():
    QUERIES[_alias] = QUERIES[_name]
    SQL[_alias] = SQL[_name]
