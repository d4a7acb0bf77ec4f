"""Clustered incremental sampling: cluster the cameras, then grow a sample in each cluster's rectangle until a rule says stop.

Three modes give the same result for the same batches: ``prefix`` computes all batches once and finds in running sums where
each cluster would have stopped (for sweeps and as a reference); ``per_cluster_task`` loops inside one task per cluster;
``driver_loop`` runs one job per round over the clusters that are still active, which suits clusters of any size.
"""

from __future__ import annotations

import math
from collections.abc import Callable, Iterator
from dataclasses import dataclass
from typing import Any

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..functions.noise import u01
from ..plans import stopping
from ..plans.query import ClusterOptions, Query
from ..session import kept
from . import clusters, sampling
from .kernel import SHAPE, add_fovs, greedy_total, largest_cells
from .matrix import TILED_FROM, dense, exploded, span_cells, summed, top_cells, with_span
from .measures import cell_metres, greedy_pairing

#: A cluster of more fields of view, or of a rectangle of more cells, than this is not given to one task.
ONE_TASK, ONE_BLOCK = 5_000_000, 50_000_000
#: Rows of a cluster that one task sorts when batches are dealt.
ROWS_PER_SORT = 1_000_000
BOUNDS = ("cx0", "cx1", "cy0", "cy1")


@dataclass
class Prepared:
    """Cluster rectangles, and the fields of view of each cluster with their batch, stored."""

    rects: DataFrame
    members: DataFrame
    #: (cluster, batch) -> number of fields of view.
    batch_sizes: dict[tuple[int, int], int]
    #: cluster -> its range of cells: x0, x1, y0, y1.
    boxes: dict[int, tuple[int, int, int, int]]

    @property
    def sizes(self) -> dict[int, int]:
        out: dict[int, int] = {}
        for (c, _), n in self.batch_sizes.items():
            out[c] = out.get(c, 0) + n
        return out


def prepare(fovs: DataFrame, query: Query, options: ClusterOptions = ClusterOptions()) -> Prepared:  # noqa: B008
    """Cluster a sample, turn clusters into rectangles, and deal each rectangle's fields of view into batches.

    What is in range is stored once in narrow form and read by every step of the clustering; so are the dealt members.
    """
    box = ("min_lat", "max_lat", "min_lon", "max_lon")
    extra = [c for c in ("video_id",) if c in fovs.columns]
    points = clusters.in_area(fovs, query).select("fov_id", *extra, *SHAPE[:5], *box, "px", "py", (u01("cluster" + options.salt, "fov_id") < options.cluster_fraction).alias("in_sample"))
    points = kept(points)
    sample = points.where("in_sample")
    centres, own_radii, drawn = clusters.kmeans_with_radii(sample, options.clusters, options.lloyd_steps, "init" + options.salt)
    if not centres:
        empty = clusters.rectangles(clusters.radii(points, [(0.0, 0.0)]), query).where("false")
        return Prepared(empty, clusters.members(points, empty).withColumn("batch", F.lit(1)), {}, {})
    found = clusters.rectangles(own_radii, query)
    rows = found.collect()  # as many as clusters at most
    rects = fovs.sparkSession.createDataFrame(rows, found.schema)
    if options.membership == "range":
        own = clusters.members(points, rects)
    else:
        own = points.withColumn("cluster_id", clusters.nearest(centres)).join(F.broadcast(rects.select("cluster_id", *BOUNDS)), "cluster_id")
    parts = math.ceil(drawn / options.cluster_fraction / ROWS_PER_SORT)  # any number of parts gives the same deal
    dealt = kept(sampling.batches(own, options.batches, "cluster_id", "batch" + options.salt, options.sampler, parts))
    counts = {(r.cluster_id, r.batch): r["count"] for r in dealt.groupBy("cluster_id", "batch").count().collect()}
    return Prepared(rects, dealt, counts, {r.cluster_id: (r.cx0, r.cx1, r.cy0, r.cy1) for r in rows})


def _change(measure: str, now: Column, before: Column, p: Column, p_before: Column) -> Column:
    """How far the maximum moved from one round to the next."""
    return stopping.MEASURES[measure](now, before, p, p_before, F.abs, lambda a, b: F.greatest(a, F.lit(b)))


def _satisfied(options: ClusterOptions, d_max: Column, d_topk: Column) -> Column:
    return F.coalesce(stopping.RULES[options.rule](options, d_max, d_topk), F.lit(False))


def running_cells(prepared: Prepared, query: Query, options: ClusterOptions) -> DataFrame:
    """cluster_id, cell_x, cell_y, iter, ci_fixed: each cell's running sum after the rounds that add to it."""
    adds = exploded(prepared.members.where(F.col("batch") <= options.rounds), query, ("cluster_id", "batch"), BOUNDS)
    sums = summed(adds, "cluster_id", "batch")
    so_far = Window.partitionBy("cluster_id", "cell_x", "cell_y").orderBy("batch").rowsBetween(Window.unboundedPreceding, Window.currentRow)
    return sums.select("cluster_id", "cell_x", "cell_y", F.col("batch").alias("iter"), F.sum("ci_fixed").over(so_far).alias("ci_fixed"))


def best_by_round(prepared: Prepared, query: Query, options: ClusterOptions) -> DataFrame:
    """cluster_id, iter, rank, cell_x, cell_y, ci_fixed: the k largest cells of each cluster after each round.

    Sums only grow, so a cell among the k largest was so among the cells that changed in the round in which it last
    changed. It is enough to keep k cells for each cluster and round, and to carry these few rows through the rounds.
    """
    order = (F.col("ci_fixed").desc(), "cell_y", "cell_x")
    cells = running_cells(prepared, query, options)
    some = cells.withColumn("rank", F.row_number().over(Window.partitionBy("cluster_id", "iter").orderBy(*order))).where(F.col("rank") <= query.k)
    carried = some.select("cluster_id", "cell_x", "cell_y", "ci_fixed", F.explode(F.sequence("iter", F.lit(options.rounds))).alias("iter"))
    latest = carried.groupBy("cluster_id", "iter", "cell_x", "cell_y").agg(F.max("ci_fixed").alias("ci_fixed"))
    return latest.withColumn("rank", F.row_number().over(Window.partitionBy("cluster_id", "iter").orderBy(*order))).where(F.col("rank") <= query.k)


def trace(prepared: Prepared, query: Query, options: ClusterOptions = ClusterOptions()) -> DataFrame:  # noqa: B008
    """cluster_id, iter, p, max_ci, d_max, d_topk, stop, top: both stopping measures after every round, and where the rule first holds."""
    best = best_by_round(prepared, query, options)
    per = best.groupBy("cluster_id", "iter").agg(F.max("ci_fixed").alias("max_fixed"), F.sort_array(F.collect_list(F.struct("rank", "cell_x", "cell_y", "ci_fixed"))).alias("top"))
    counts = prepared.members.groupBy("cluster_id", "batch").agg(F.count("*").alias("n"))
    so_far = counts.withColumn("seen", F.sum("n").over(Window.partitionBy("cluster_id").orderBy("batch"))).withColumn("all", F.sum("n").over(Window.partitionBy("cluster_id")))
    shares = so_far.select("cluster_id", F.col("batch").alias("iter"), (F.col("seen") / F.col("all")).alias("p"), "seen")
    rows = per.join(shares, ["cluster_id", "iter"])
    by_iter = Window.partitionBy("cluster_id").orderBy("iter")
    rows = rows.withColumns({"before": F.lag("max_fixed").over(by_iter), "p_before": F.lag("p").over(by_iter), "top_before": F.lag("top").over(by_iter)})
    d_max = _change(options.measure, F.col("max_fixed"), F.col("before"), F.col("p"), F.col("p_before"))
    d_topk = F.when(F.col("top_before").isNotNull(), greedy_pairing(F.col("top"), F.col("top_before"), *cell_metres(query))["total"])
    rows = rows.withColumns({"d_max": d_max, "d_topk": d_topk})
    holds = _satisfied(options, F.col("d_max"), F.col("d_topk")) & (F.col("iter") >= options.min_iterations)
    rows = rows.withColumn("holds", holds).withColumn("last", F.max("iter").over(Window.partitionBy("cluster_id")))
    first = F.min(F.when(F.col("holds"), F.col("iter"))).over(Window.partitionBy("cluster_id"))
    return rows.withColumn("stop", F.coalesce(first, F.col("last"))).select("cluster_id", "iter", "p", "seen", F.col("max_fixed"), "d_max", "d_topk", "stop", "top")


def merged(lists: DataFrame, k: int) -> DataFrame:
    """The global top-k of cluster lists (cell_x, cell_y, ci_fixed, p): sums rescaled by the share seen, one entry per cell, the largest."""
    est = F.round(F.col("ci_fixed") / F.col("p"))
    cells = lists.select("cell_x", "cell_y", est.cast("long").alias("ci_fixed")).groupBy("cell_x", "cell_y").agg(F.max("ci_fixed").alias("ci_fixed"))
    return top_cells(cells, k)


def lists_at_stop(rows: DataFrame) -> DataFrame:
    """The cluster lists of a trace where each cluster stopped, as ``merged`` takes them."""
    return rows.where("iter = stop").select("p", F.explode("top").alias("c")).select("c.cell_x", "c.cell_y", "c.ci_fixed", "p")


def prefix(fovs: DataFrame, query: Query, options: ClusterOptions = ClusterOptions()) -> tuple[DataFrame, DataFrame]:  # noqa: B008
    """(top-k, trace) from running sums over all batches."""
    rows = trace(prepare(fovs, query, options), query, options)
    return merged(lists_at_stop(rows), query.k), rows


_Holds = tuple[Callable[..., Any], Callable[..., Any]]


@dataclass
class _Progress:
    """One cluster's way through its rounds, as tasks and the driver keep it."""

    seen: int = 0
    p: float = 1.0
    now: int = 0
    rounds: int = 0
    top: list[tuple[int, int, int]] | None = None

    def step(self, number: int, more: int, whole: int, top: list[tuple[int, int, int]], query: Query, options: ClusterOptions, holds: _Holds) -> bool:
        """Close a round that has seen ``more`` fields of view; whether the rule says stop."""
        before, p_before, top_before = self.now, self.p, self.top
        self.seen, self.rounds, self.top = self.seen + more, number, top
        self.p, self.now = self.seen / whole, top[0][2] if top else 0
        if top_before is None or before <= 0 or self.now <= 0 or number < options.min_iterations:
            return False
        measure, rule = holds
        d_topk = greedy_total([t[:2] for t in top], [t[:2] for t in top_before], *cell_metres(query))
        return bool(rule(options, measure(self.now, before, self.p, p_before, abs, max), d_topk))


def _holds(options: ClusterOptions) -> _Holds:
    """The measure and the rule themselves, looked up on the driver: a task's worker knows none that the caller has added."""
    return stopping.MEASURES[options.measure], stopping.RULES[options.rule]


def per_cluster_task(fovs: DataFrame, query: Query, options: ClusterOptions = ClusterOptions(), ready: Prepared | None = None) -> tuple[DataFrame, DataFrame]:  # noqa: B008
    """(top-k, stops): one task owns one cluster and truly stops early. stops: cluster_id, iter, p, seen.

    A cluster's rows come ordered by batch, in Arrow batches; the task holds its rectangle's sums and nothing else.
    """
    ready = ready or prepare(fovs, query, options)
    if not _fits_tasks(ready):
        raise ValueError("a cluster is too large for one task; use driver_loop")
    sizes, batch_sizes, boxes, rounds, holds = ready.sizes, ready.batch_sizes, ready.boxes, options.rounds, _holds(options)
    rows = with_span(ready.members.where(F.col("batch") <= rounds), query, clip=True).select(F.col("cluster_id").cast("long"), F.col("batch").cast("long"), *SHAPE)
    laid = rows.repartition(max(len(sizes), 1), "cluster_id").sortWithinPartitions("cluster_id", "batch")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        cluster, block, state, stopped = -1, np.zeros((0, 0), np.int64), _Progress(), True

        def close(upto: int) -> None:
            """Close all rounds up to a number, as long as the rule does not hold; rounds without members end it."""
            nonlocal stopped
            while not stopped and state.rounds < upto:
                number = state.rounds + 1
                if (cluster, number) not in batch_sizes:
                    stopped = True
                    return
                least = state.top[-1][2] if state.top and len(state.top) == query.k else 1  # sums only grow
                top = largest_cells(block, boxes[cluster][0], boxes[cluster][2], query.k, least)
                stopped = state.step(number, batch_sizes[cluster, number], sizes[cluster], top, query, options, holds)

        def listed() -> pa.RecordBatch:
            cells = state.top or [(None, None, 0)]
            fixed = [(cluster, state.rounds, state.p, state.seen, *c) for c in cells]
            kinds = (pa.int64(), pa.int64(), pa.float64(), pa.int64(), pa.int64(), pa.int64(), pa.int64())
            return pa.RecordBatch.from_arrays([pa.array([r[i] for r in fixed], kind) for i, kind in enumerate(kinds)], ["cluster_id", "iter", "p", "seen", "cell_x", "cell_y", "ci_fixed"])

        for batch in batches:
            if not batch.num_rows:
                continue
            columns = [c.to_numpy(zero_copy_only=False) for c in batch.columns]
            keys = np.stack(columns[:2])
            cuts = [0, *(np.flatnonzero((keys[:, 1:] != keys[:, :-1]).any(axis=0)) + 1).tolist(), batch.num_rows]
            for i, j in zip(cuts[:-1], cuts[1:], strict=True):
                now, number = int(keys[0, i]), int(keys[1, i])
                if now != cluster:
                    if cluster >= 0:
                        close(rounds)
                        yield listed()
                    x0, x1, y0, y1 = boxes[now]
                    cluster, block, state, stopped = now, np.zeros((y1 - y0 + 1, x1 - x0 + 1), np.int64), _Progress(), False
                close(number - 1)
                if not stopped:
                    add_fovs(block, boxes[cluster][0], boxes[cluster][2], query, [c[i:j] for c in columns[2:]])
        if cluster >= 0:
            close(rounds)
            yield listed()

    out = kept(laid.mapInArrow(run, "cluster_id long, iter long, p double, seen long, cell_x long, cell_y long, ci_fixed long"))
    return merged(out.where("cell_x is not null"), query.k), out.select("cluster_id", "iter", "p", "seen").distinct()


def driver_loop(fovs: DataFrame, query: Query, options: ClusterOptions = ClusterOptions(), ready: Prepared | None = None, blocks_from: int = TILED_FROM) -> tuple[DataFrame, DataFrame]:  # noqa: B008
    """(top-k, stops): a job per round over the clusters still active. Only k rows of each cluster come to the driver.

    Rounds of ``blocks_from`` pairs or more are summed in dense blocks, so that fields of view are shuffled and not cells.
    """
    ready = ready or prepare(fovs, query, options)
    spark, sizes, counts = fovs.sparkSession, ready.sizes, ready.batch_sizes
    pairs = with_span(ready.members, query, clip=True).agg(F.sum(span_cells())).first()[0] or 0
    active, total = sorted(sizes), None
    states = {c: _Progress() for c in active}
    for i in range(1, options.rounds + 1):
        active = [c for c in active if (c, i) in counts]
        if not active:
            break
        rows = ready.members.where((F.col("batch") == i) & F.col("cluster_id").isin(active))
        if pairs // options.batches >= blocks_from:
            add = dense(rows, query, "cluster_id", BOUNDS)
        else:
            add = exploded(rows, query, ("cluster_id",), BOUNDS)
        both = add if total is None else total.where(F.col("cluster_id").isin(active)).union(add.select(total.columns))
        total = kept(summed(both, "cluster_id"))
        order = Window.partitionBy("cluster_id").orderBy(F.col("ci_fixed").desc(), "cell_y", "cell_x")
        tops: dict[int, list] = {c: [] for c in active}
        for r in total.withColumn("rank", F.row_number().over(order)).where(F.col("rank") <= query.k).orderBy("cluster_id", "rank").collect():
            tops[r.cluster_id].append((r.cell_x, r.cell_y, r.ci_fixed))
        active = [c for c in active if not states[c].step(i, counts[c, i], sizes[c], tops[c], query, options, _holds(options))]
    cells = [(x, y, v, s.p) for s in states.values() for x, y, v in s.top or ()]
    stops = spark.createDataFrame([(c, s.rounds, float(s.p), s.seen) for c, s in sorted(states.items())], "cluster_id long, iter long, p double, seen long")
    return merged(spark.createDataFrame(cells, "cell_x long, cell_y long, ci_fixed long, p double"), query.k), stops


def _fits_tasks(ready: Prepared) -> bool:
    area = max(((x1 - x0 + 1) * (y1 - y0 + 1) for x0, x1, y0, y1 in ready.boxes.values()), default=0)
    return max(ready.sizes.values(), default=0) <= ONE_TASK and area <= ONE_BLOCK


def run(fovs: DataFrame, query: Query, options: ClusterOptions = ClusterOptions(), mode: str = "auto") -> tuple[DataFrame, DataFrame]:  # noqa: B008
    """auto: a task per cluster as long as each cluster fits one, else a job per round; both give the same result."""
    if mode == "prefix":
        return prefix(fovs, query, options)
    ready = prepare(fovs, query, options)
    if mode == "auto":
        mode = "per_cluster_task" if _fits_tasks(ready) else "driver_loop"
    return {"per_cluster_task": per_cluster_task, "driver_loop": driver_loop}[mode](fovs, query, options, ready=ready)


__all__ = ["Prepared", "best_by_round", "driver_loop", "lists_at_stop", "merged", "per_cluster_task", "prefix", "prepare", "run", "running_cells", "trace"]
