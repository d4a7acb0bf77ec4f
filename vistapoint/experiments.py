"""The experiments of the methods, on whole regions: what each method finds, and what it looks at. Times are bench.py's."""

from __future__ import annotations

from dataclasses import replace

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from . import oracles as O
from .functions.noise import u01
from .operators import clusters, fov, matrix, measures, sampler
from .operators.detect import detect
from .plans import stopping
from .session import kept, side_by_side
from .sources import carriers
from .workloads import FULL, LINE, M1, MARKS, OPT, T1, T2, T3, T4, events, region, register, stack, table, top

TARGETS = {"t1": T1, "t2": T2, "t3": T3, "t4": T4}
#: Cells that the naive method is tried on where not all are asked for: about so many, by hash.
NAIVE_CELLS = 2_000
#: Regions and datasets of the overall comparison whose jobs run side by side.
AT_ONCE = 4

# --- every method's list, by region and dataset -----------------------------------------------------------------------------

for _w, _k, _v in (("w1", 5, "pie60"), ("w2", 10, "pie60"), ("w3", 5, "mix30"), ("w4", 5, "mix70")):
    for _t in TARGETS:
        _q = region(_t, k=_k)
        register(f"q_{_w}_{_t}", lambda s, d, q=_q, v=_v, m="tiled" if _t in ("t3", "t4") else "optimized": top(s, d, q, v, m), O.top_of(_q, _v))


# --- naive against optimized ------------------------------------------------------------------------------------------------


def _naive_table(s, d, variant: str, k: int, whole: bool = False) -> DataFrame:
    """By region: both methods' work, and how far their sums and lists are apart: on all cells if ``whole`` is asked for, else
    on all cells of the smallest region and on a hashed sample of the cells of the others."""
    fovs, parts = events(s, d, variant), []
    for t in TARGETS:
        q = region(t, k=k)
        some, only = matrix.cells(s, q.grid), None
        if not whole:
            if t != "t1":
                some = some.where(u01("cells", F.col("cell_y") * q.grid.nx + F.col("cell_x")) < NAIVE_CELLS / q.grid.cells)
            some = only = kept(some)
        all_pairs = kept(matrix.naive(fovs, q, cells_of=only))
        boxes = kept(matrix.optimized(fovs, q, cells_of=only))
        gap = measures.largest_gap(boxes, all_pairs).select("max_gap")
        lists = measures.diff(matrix.top_cells(boxes, k), matrix.top_cells(all_pairs, k), q).select("diff_m", "within")
        work = measures.cost_model(fovs, q).select("naive_pairs", "optimized_pairs", F.col("ratio").alias("fewer"))
        parts.append(work.crossJoin(gap).crossJoin(lists).crossJoin(some.agg(F.count("*").alias("compared"))).withColumn("region", F.lit(t)))
    return stack(parts)


def _naive_table_sql(variant: str, k: int, whole: bool = False) -> str:
    parts = []
    for t in TARGETS:
        q = region(t, k=k)
        n = O.side(q)
        some = "true" if whole or t == "t1" else f"{O.u01_sql('cells', 'i')} < {NAIVE_CELLS / (n * n)!r}::DOUBLE"
        inside = O.in_range(O.fov_with_mbr(variant), q.area)
        pairs_of = f"SELECT a.rank AS i, b.rank AS j, a.cell_x AS ax, a.cell_y AS ay, b.cell_x AS bx, b.cell_y AS by_, 1 AS one FROM ({O.top('SELECT * FROM boxes', k)}) a, ({O.top('SELECT * FROM everything', k)}) b"
        parts.append(
            f"""SELECT * FROM (WITH f AS MATERIALIZED ({inside}), chosen AS MATERIALIZED (SELECT i % {n} AS cell_x, i // {n} AS cell_y FROM range({n * n}) r(i) WHERE {some}),
          everything AS MATERIALIZED ({O.naive_by_blocks('SELECT * FROM f', q) if whole and t != 't1' else O.naive('SELECT * FROM f', q, some)}), boxes AS MATERIALIZED (SELECT m.* FROM ({O.matrix('SELECT * FROM f', q)}) m JOIN chosen USING (cell_x, cell_y)),
          work AS (SELECT count(*) AS fovs, sum((x1 - x0 + 1) * (y1 - y0 + 1))::BIGINT AS visits FROM ({O.span('SELECT * FROM f', q)}))
          SELECT '{t}' AS region, fovs * {n * n} AS naive_pairs, visits AS optimized_pairs, round(fovs * {n * n} / visits::DOUBLE, 6) AS fewer, (SELECT count(*) FROM chosen) AS compared,
            (SELECT round(coalesce(max(abs(coalesce(a.ci_fixed, 0) - coalesce(b.ci_fixed, 0))), 0) / 1e12::DOUBLE, 6) FROM boxes a FULL JOIN everything b ON a.cell_x = b.cell_x AND a.cell_y = b.cell_y) AS max_gap, diff_m, within
          FROM work, ({O.greedy_by(pairs_of, 'one', k, q)}))"""
        )
    return " UNION ALL ".join(parts)


for _w, _k, _v in (("w1", 5, "pie60"), ("w2", 10, "pie60"), ("w3", 5, "mix30"), ("w4", 5, "mix70")):
    register(f"q_{_w}_table", lambda s, d, v=_v, k=_k, a=_w == "w2": _naive_table(s, d, v, k, a), _naive_table_sql(_v, _k, _w == "w2"))

# --- heat maps of three methods ----------------------------------------------------------------------------------------------

IN1 = O.in_range(O.fov_with_mbr("pie60"), T1.area)
register("q_w5_heatmap", lambda s, d: measures.largest_gap(matrix.optimized(events(s, d), T1), matrix.naive(events(s, d), T1)), f"SELECT count(*) AS cells, round(max(abs(coalesce(a.ci_fixed, 0) - coalesce(b.ci_fixed, 0))) / 1e12::DOUBLE, 6) AS max_gap FROM ({M1}) a FULL JOIN ({O.naive(IN1, T1)}) b USING (cell_x, cell_y)")


def _clustered_map(s, d):
    """The map that clustered sampling sees, rescaled and each as a share of its largest sum, against the exact one: how many
    cells each has, and the mean and largest gap over the cells of the exact map."""
    fovs = events(s, d)
    ready = sampler.prepare(fovs, T1, OPT)
    stops = sampler.trace(ready, T1, OPT).where("iter = stop").select("cluster_id", "stop", "p")
    sums = matrix.summed(matrix.exploded(ready.members.join(F.broadcast(stops), "cluster_id").where("batch <= stop"), T1, ("cluster_id", "p"), sampler.BOUNDS), "cluster_id", "p")
    seen = sums.groupBy("cell_x", "cell_y").agg(F.max(F.round(F.col("ci_fixed") / F.col("p"))).cast("long").alias("ci_fixed"))
    exact, guess = matrix.normalised(matrix.optimized(fovs, T1)), matrix.normalised(seen).withColumnRenamed("gamma", "guess")
    both = exact.join(guess, ["cell_x", "cell_y"], "left")
    gap = F.abs(F.col("gamma") - F.coalesce("guess", F.lit(0.0)))
    return both.agg(F.count("*").alias("cells"), F.count("guess").alias("seen_cells"), F.round(F.avg(gap), 6).alias("mean_gap"), F.round(F.max(gap), 6).alias("max_gap"))


_limits = "greatest(x0, cx0) AS x0, least(x1, cx1) AS x1, greatest(y0, cy0) AS y0, least(y1, cy1) AS y1"
register(
    "q_w5_clustered_map",
    _clustered_map,
    O.clustered(
        "pie60",
        T1,
        OPT,
        f"""SELECT count(*) AS cells, count(guess) AS seen_cells, round(avg(abs(gamma - coalesce(guess, 0))), 6) AS mean_gap, round(max(abs(gamma - coalesce(guess, 0))), 6) AS max_gap
        FROM (SELECT cell_x, cell_y, ci_fixed / (max(ci_fixed) OVER ())::DOUBLE AS gamma FROM ({M1}))
        LEFT JOIN (SELECT cell_x, cell_y, c / (max(c) OVER ())::DOUBLE AS guess FROM (SELECT cell_x, cell_y, max(round(total / p)::BIGINT) AS c FROM (
          SELECT sums.cluster_id, cell_x, cell_y, sum(add) AS total FROM sums JOIN stops ON sums.cluster_id = stops.cluster_id AND batch <= stop GROUP BY ALL) t
          JOIN stops ON t.cluster_id = stops.cluster_id JOIN shares ON shares.cluster_id = t.cluster_id AND iter = stop GROUP BY cell_x, cell_y)) USING (cell_x, cell_y)""",
    ),
)

# --- cell sizes and models ---------------------------------------------------------------------------------------------------

CELLS = (1, 5, 10)
register("q_w6_cells", lambda s, d: stack([top(s, d, replace(T1, cell=0.0001 * n)).withColumn("factor", F.lit(n)) for n in CELLS]), " UNION ALL ".join(f"SELECT *, {n}::INT AS factor FROM ({O.top_of(replace(T1, cell=0.0001 * n), 'pie60')})" for n in CELLS))
MODELS = (("probabilistic", T1), ("full_coverage", FULL), ("center_line", LINE))


def _truth_sql(query) -> str:
    far = f"sqrt(pow(({query.area.min_lon!r}::DOUBLE + (cell_x + 0.5::DOUBLE) * 0.0001::DOUBLE - mark_lon) * {O.mx(query.lat0)}, 2) + pow(({query.area.min_lat!r}::DOUBLE + (cell_y + 0.5::DOUBLE) * 0.0001::DOUBLE - mark_lat) * {O.MY}, 2))"
    return f"SELECT rank, arg_min(mark_id, (e, mark_id)) AS mark_id, round(min(e), 6) AS error_m FROM (SELECT rank, mark_id, {far} AS e FROM ({O.top_of(query, 'mix30')}), {MARKS}) GROUP BY rank"


register("q_w7_models", lambda s, d: stack([measures.truth_error(top(s, d, q, "mix30"), carriers.spots(s), q).withColumn("model", F.lit(n)) for n, q in MODELS]), " UNION ALL ".join(f"SELECT *, '{n}' AS model FROM ({_truth_sql(q)})" for n, q in MODELS))

# --- clusters and rounds -----------------------------------------------------------------------------------------------------

CLUSTER_COUNTS, ROUNDS = tuple(range(1, 11)), (5, 10, 15, 20)


def _losses(lists: DataFrame, exact: DataFrame, query, *by: str) -> DataFrame:
    """by, diff_m, within: the greedy pairing of the exact list with the merged list of each group. lists: by, cell_x, cell_y, ci_fixed, p."""
    cells = lists.groupBy(*by, "cell_x", "cell_y").agg(F.max(F.round(F.col("ci_fixed") / F.col("p")).cast("long")).alias("est"))
    rank = F.row_number().over(Window.partitionBy(*by).orderBy(F.col("est").desc(), "cell_y", "cell_x"))
    as_list = lambda name: F.transform(F.sort_array(F.collect_list(F.struct("rank", "cell_x", "cell_y"))), lambda x: F.struct(x["cell_x"].alias("cell_x"), x["cell_y"].alias("cell_y"))).alias(name)
    best = cells.withColumn("rank", rank).where(F.col("rank") <= query.k).groupBy(*by).agg(as_list("b"))
    both = best.crossJoin(F.broadcast(exact.agg(as_list("a")))).withColumn("g", measures.greedy_pairing(F.col("a"), F.col("b"), *measures.cell_metres(query)))
    return both.select(*by, F.round("g.total", 6).alias("diff_m"), F.col("g.within").alias("within"))


def _grid(s, d, query=T4):
    """Processed fields of view and cells, and the distance to the exact list, by clusters and rounds; one trace answers all rounds of a cluster count."""
    fovs, parts = kept(clusters.in_area(events(s, d), query)), []
    exact = kept(detect(fovs, query, "exact"))
    for c in CLUSTER_COUNTS:
        o = replace(OPT, clusters=c, rule="none")
        ready = sampler.prepare(fovs, query, o)
        cells = sum((x1 - x0 + 1) * (y1 - y0 + 1) for x0, x1, y0, y1 in ready.boxes.values())
        rows = sampler.trace(ready, query, o).where(F.col("iter").isin(*ROUNDS))
        parts.append(kept(rows.select(F.lit(c).alias("clusters"), F.lit(cells).cast("long").alias("cells"), F.col("iter").cast("int").alias("rounds"), "p", "seen", "top")))
    at = stack(parts)
    lists = at.select("clusters", "rounds", "p", F.explode("top").alias("x")).select("clusters", "rounds", "x.cell_x", "x.cell_y", "x.ci_fixed", "p")
    done = at.groupBy("clusters", "rounds", "cells").agg(F.sum("seen").alias("processed"))
    return done.join(_losses(lists, exact, query, "clusters", "rounds"), ["clusters", "rounds"]).select("clusters", "rounds", "diff_m", "within", "processed", "cells")


def _best(cells: str, by: str, k: int) -> str:
    """The merged top-k lists (by, rank, cell_x, cell_y) of cluster lists (by, cell_x, cell_y, est)."""
    return f"SELECT {by}, rank, cell_x, cell_y FROM (SELECT {by}, cell_x, cell_y, row_number() OVER (PARTITION BY {by} ORDER BY est DESC, cell_y, cell_x) AS rank FROM (SELECT {by}, cell_x, cell_y, max(est) AS est FROM ({cells}) GROUP BY ALL)) WHERE rank <= {k}"


def _against(exact: str, lists: str, by: str) -> str:
    return f"SELECT {', '.join(f'b.{c.strip()}' for c in by.split(','))}, a.rank AS i, b.rank AS j, a.cell_x AS ax, a.cell_y AS ay, b.cell_x AS bx, b.cell_y AS by_ FROM ({exact}) a, ({lists}) b"


def _grid_sql(query=T4) -> str:
    parts = []
    for c in CLUSTER_COUNTS:
        lists = _best("SELECT r.iter AS rounds, cell_x, cell_y, round(ci_fixed / p)::BIGINT AS est FROM ranked r JOIN shares s ON s.cluster_id = r.cluster_id AND s.iter = r.iter WHERE r.iter IN (5, 10, 15, 20)", "rounds", query.k)
        result = f"SELECT {c} AS clusters, rounds::INT AS rounds, diff_m, within, (SELECT sum(s.seen)::BIGINT FROM shares s JOIN maxima m ON m.cluster_id = s.cluster_id AND m.iter = s.iter WHERE s.iter = rounds) AS processed, (SELECT sum((cx1 - cx0 + 1) * (cy1 - cy0 + 1))::BIGINT FROM ranges) AS cells FROM ({O.greedy_by(_against('SELECT * FROM exact', lists, 'rounds'), 'rounds', query.k, query)})"
        parts.append(f"SELECT * FROM ({O.clustered('pie60', query, replace(OPT, clusters=c, rule='none'), result)})")
    return f"WITH exact AS MATERIALIZED ({O.top_of(query, 'pie60')}) " + " UNION ALL ".join(parts)


register("q_w8_grid", _grid, _grid_sql())

# --- stop rules and thresholds -----------------------------------------------------------------------------------------------


def _trace(s, d, query, options=OPT, variant="pie60"):
    return sampler.trace(sampler.prepare(events(s, d, variant), query, options), query, options)


register(
    "q_w9_trace",
    lambda s, d: stack([_trace(s, d, q).select(F.lit(t).alias("region"), F.col("cluster_id").cast("long"), F.col("iter").cast("long"), F.round("d_max", 6).alias("d_max"), F.round("d_topk", 4).alias("d_topk")) for t, q in (("t2", T2), ("t4", T4))]),
    " UNION ALL ".join(f"SELECT * FROM ({O.clustered('pie60', q, OPT, f'''SELECT '{t}' AS region, cluster_id, iter, round(d_max, 6) AS d_max, round(d_topk, 4) AS d_topk FROM steps''', True)})" for t, q in (("t2", T2), ("t4", T4))),
)
LEVELS = (0.01, 0.05, 0.1, 0.2, 0.5)
CHANGES = ("raw", "rescaled", "relative", "rescaled_relative")


def _sweep(s, d, query=T4):
    """Rounds, processed fields of view and the loss (distance to the exact list, hits) by stopping measure and threshold, all from one trace."""
    fovs = kept(clusters.in_area(events(s, d), query))
    exact = kept(detect(fovs, query, "exact"))
    full = kept(sampler.trace(sampler.prepare(fovs, query, OPT), query, OPT).select("cluster_id", "iter", "seen", "p", "max_fixed", "top"))
    w = Window.partitionBy("cluster_id").orderBy("iter")
    rows = full.withColumns({"before": F.lag("max_fixed").over(w), "p_before": F.lag("p").over(w)})
    change = lambda m: stopping.MEASURES[m](F.col("max_fixed"), F.col("before"), F.col("p"), F.col("p_before"), F.abs, lambda a, b: F.greatest(a, F.lit(b)))
    rows = rows.select("cluster_id", "iter", "seen", F.explode(F.array(*[F.struct(F.lit(m).alias("measure"), change(m).alias("d_max")) for m in CHANGES])).alias("m")).select("cluster_id", "iter", "seen", "m.measure", "m.d_max")
    levels = rows.crossJoin(F.broadcast(s.createDataFrame([(t,) for t in LEVELS], "threshold double")))
    at = levels.groupBy("measure", "threshold", "cluster_id").agg(F.coalesce(F.min(F.when((F.col("d_max") < F.col("threshold")) & (F.col("iter") >= 2), F.col("iter"))), F.max("iter")).alias("iter"))
    at = kept(at.join(full, ["cluster_id", "iter"]))
    lists = at.select("measure", "threshold", "p", F.explode("top").alias("x")).select("measure", "threshold", "x.cell_x", "x.cell_y", "x.ci_fixed", "p")
    done = at.groupBy("measure", "threshold").agg(F.sum("iter").cast("long").alias("rounds"), F.sum("seen").alias("processed"))
    return done.join(_losses(lists, exact, query, "measure", "threshold"), ["measure", "threshold"]).select("measure", "threshold", "rounds", "processed", "diff_m", "within")


def _sweep_sql(query=T4) -> str:
    change = {"raw": "abs(max_fixed - before) / 1e12::DOUBLE", "relative": "abs(max_fixed - before) / greatest(max_fixed, 1)::DOUBLE", "rescaled": "abs(max_fixed / p - before / p_before) / 1e12::DOUBLE", "rescaled_relative": "abs(max_fixed / p - before / p_before) / greatest(max_fixed / p, 1.0)"}
    every = " UNION ALL ".join(f"SELECT cluster_id, iter, seen, p, '{m}' AS measure, {x} AS d FROM maxima" for m, x in change.items())
    at = f"SELECT measure, threshold, cluster_id, coalesce(min(iter) FILTER (d < threshold AND iter >= 2), max(iter)) AS iter FROM ({every}), (VALUES {', '.join(f'({t}::DOUBLE)' for t in LEVELS)}) AS levels(threshold) GROUP BY ALL"
    lists = _best("SELECT measure, threshold, cell_x, cell_y, round(ci_fixed / p)::BIGINT AS est FROM at_stop JOIN ranked USING (cluster_id, iter) JOIN shares USING (cluster_id, iter)", "measure, threshold", query.k)
    loss = O.greedy_by(_against(O.top_of(query, "pie60"), lists, "measure, threshold"), "measure, threshold", query.k, query)
    result = f"SELECT measure, threshold, rounds, processed, diff_m, within FROM (SELECT measure, threshold, sum(iter)::BIGINT AS rounds, sum(seen)::BIGINT AS processed FROM at_stop JOIN shares USING (cluster_id, iter) GROUP BY ALL) JOIN ({loss}) USING (measure, threshold)"
    return O.clustered("pie60", query, OPT, result, extra=f"at_stop AS MATERIALIZED ({at})")


register("q_threshold_sweep", _sweep, _sweep_sql())

# --- clustered against single sampling ---------------------------------------------------------------------------------------


def _methods_of(fovs: DataFrame, q, t: str, v: str, served: bool = True) -> DataFrame:
    """One region and dataset of ``_overall``: a row for each of the two methods, stored together."""
    ready = sampler.prepare(fovs, q, OPT)
    exact = kept(detect(fovs, q, "exact"))
    found, stops = sampler.per_cluster_task(fovs, q, OPT, ready) if sampler._fits_tasks(ready) else sampler.driver_loop(fovs, q, OPT, ready)
    visits = stops.agg(F.sum("seen")).first()[0] or 0
    share = min(visits / max(fovs.count(), 1), 1.0)
    single = detect(fovs, q, "single_sample", fraction=share) if share < 1 else exact  # a sample of all is all
    rows = stack([measures.diff(exact, df, q).withColumn("method", F.lit(name)) for name, df in (("clustered", found), ("single", single))])
    if served:
        once = ready.members.join(F.broadcast(stops.select(F.col("cluster_id").alias("c"), F.col("iter").alias("last"))), (F.col("cluster_id") == F.col("c")) & (F.col("batch") <= F.col("last"))).select("fov_id").distinct()
        rows = rows.crossJoin(once.agg(F.count("*").alias("seen")))
    return kept(rows.select(F.lit(t).alias("region"), F.lit(v).alias("dataset"), "method", F.lit(round(share, 6)).alias("sample"), F.lit(visits).cast("long").alias("visits"), *(["seen"] if served else []), "diff_m", "within"))


def _datasets(s, d) -> dict[str, DataFrame]:
    """``events`` of every variant. Variants differ in angles and boxes only, so what is placed by hashes is placed once."""
    spread = table(s, d, "events").repartition("event_id")
    placed = kept(carriers.events_to_fovs(spread))
    return dict(zip(fov.VARIANTS, side_by_side(s, lambda v: kept(fov.with_mbr(fov.assign_angle(placed, v))), fov.VARIANTS, AT_ONCE), strict=True))


def _overall(s, d, served: bool = True):
    """Clustered against single sampling at equal numbers of fields of view: summed distance and hits, by region and dataset.

    visits counts a field of view once for each cluster that it serves, seen once in all (a pass of its own, if ``served`` is
    asked for); the sample is visits over all.
    A region and dataset is some twenty small jobs, most of few tasks; those of all twelve run side by side to fill the cores."""
    whole = _datasets(s, d)
    both = [(matrix.candidates(whole[v], TARGETS[t]), TARGETS[t], t, v) for t in sorted(TARGETS, reverse=True) for v in fov.VARIANTS]  # the longest first
    return stack(side_by_side(s, lambda at: _methods_of(*at, served), both, AT_ONCE))


def _overall_sql() -> str:
    parts = []
    for t, q in TARGETS.items():
        for v in fov.VARIANTS:
            lists = "SELECT 'clustered' AS method, rank, cell_x, cell_y FROM (SELECT *, row_number() OVER (ORDER BY ci_fixed DESC, cell_y, cell_x) AS rank FROM merged) WHERE rank <= 5 UNION ALL SELECT 'single' AS method, rank, cell_x, cell_y FROM "
            drawn = f"SELECT * FROM f ORDER BY {O.u01_sql('s0', 'fov_id')}, fov_id LIMIT (SELECT least(sum(seen), (SELECT count(*) FROM f))::BIGINT FROM at_stop)"
            single = f"({O.top(O.matrix(drawn, q), 5)})"
            exact = O.top(O.matrix("SELECT * FROM f", q), 5)
            result = f"SELECT '{t}' AS region, '{v}' AS dataset, method, round(least((SELECT sum(seen) FROM at_stop) / (SELECT count(*) FROM f)::DOUBLE, 1.0), 6) AS sample, (SELECT sum(seen)::BIGINT FROM at_stop) AS visits, (SELECT count(DISTINCT fov_id) FROM mem JOIN stops ON mem.cluster_id = stops.cluster_id AND batch <= stop) AS seen, diff_m, within FROM ({O.greedy_by(_against(exact, lists + single, 'method'), 'method', 5, q)})"
            seen = "at_stop AS MATERIALIZED (SELECT seen FROM stops JOIN shares ON shares.cluster_id = stops.cluster_id AND iter = stop)"
            parts.append(f"SELECT * FROM ({O.clustered(v, q, OPT, result, extra=seen)})")
    return " UNION ALL ".join(parts)


OVERALL_SQL = _overall_sql()
register("q_w11_overall", _overall, OVERALL_SQL)
register("q_w12_accuracy", lambda s, d: _overall(s, d, served=False).groupBy("region", "dataset", "method").agg(F.round(F.sum("within") / (5.0 * F.count("*")), 6).alias("share_found")), f"SELECT region, dataset, method, round(within / 5.0::DOUBLE, 6) AS share_found FROM ({OVERALL_SQL})")

# --- k, and the share of full circles ------------------------------------------------------------------------------------------

register("q_w14_k", lambda s, d: stack([top(s, d, replace(T2, k=k)).withColumn("k", F.lit(k)) for k in (1, 5, 10, 20)]), " UNION ALL ".join(f"SELECT *, {k}::INT AS k FROM ({O.top_of(replace(T2, k=k), 'pie60')})" for k in (1, 5, 10, 20)))


def _circles(s, d):
    """By share of full circles: the distance between the exact list and those of clustered and of single sampling on T1."""
    parts = []
    for v, share in (("pie60", 0.0), ("mix70", 0.3), ("mix30", 0.7)):
        fovs = kept(clusters.in_area(events(s, d, v), T1))
        exact = kept(detect(fovs, T1, "exact"))
        found, stops = sampler.run(fovs, T1, OPT)
        part = min((stops.agg(F.sum("seen")).first()[0] or 0) / max(fovs.count(), 1), 1.0)
        for name, df in (("clustered", found), ("single", detect(fovs, T1, "single_sample", fraction=part))):
            parts.append(measures.diff(exact, df, T1).select(F.lit(share).alias("full_circles"), F.lit(name).alias("method"), "diff_m"))
    return stack(parts)


register("q_w15_circles", _circles, f"SELECT CASE dataset WHEN 'pie60' THEN 0.0::DOUBLE WHEN 'mix70' THEN 0.3::DOUBLE ELSE 0.7::DOUBLE END AS full_circles, method, diff_m FROM ({OVERALL_SQL}) WHERE region = 't1'")
