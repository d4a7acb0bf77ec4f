"""Accuracy and cost measures."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..functions.geo import METRES_PER_DEGREE, east_scale
from ..functions.intention import FIXED
from ..plans.query import GridSpec, Query
from .matrix import centre_of, span_cells, with_span
from .retrieval import candidates


def cell_metres(query: Query) -> tuple[float, float]:
    """Width and height of a cell."""
    return query.cell * east_scale(query.lat0), query.cell * METRES_PER_DEGREE


def greedy_pairing(left: Column, right: Column, width_m: float, height_m: float, within_m: float = 20.0) -> Column:
    """Struct total, within, pairs: the closest pair of what is left, again and again, of two arrays of structs (cell_x, cell_y).

    Each cell is used once; ties go to the earlier place. total adds up the distances, within counts those of at most within_m.
    """
    far = lambda p, q: F.sqrt(F.pow((p["cell_x"] - q["cell_x"]) * F.lit(width_m), F.lit(2.0)) + F.pow((p["cell_y"] - q["cell_y"]) * F.lit(height_m), F.lit(2.0)))
    pairs = F.sort_array(F.flatten(F.transform(left, lambda p, i: F.transform(right, lambda q, j: F.struct(far(p, q).alias("d"), i.alias("i"), j.alias("j"))))))
    start = F.struct(F.expr("cast(array() as array<int>)").alias("i"), F.expr("cast(array() as array<int>)").alias("j"), F.lit(0.0).alias("total"), F.lit(0).cast("long").alias("within"))

    def step(state: Column, pair: Column) -> Column:
        used = F.array_contains(state["i"], pair["i"]) | F.array_contains(state["j"], pair["j"])
        taken = F.struct(F.array_append(state["i"], pair["i"]).alias("i"), F.array_append(state["j"], pair["j"]).alias("j"), (state["total"] + pair["d"]).alias("total"), (state["within"] + (pair["d"] <= within_m).cast("long")).alias("within"))
        return F.when(used, state).otherwise(taken)

    return F.aggregate(pairs, start, step, lambda s: F.struct(s["total"].alias("total"), s["within"].alias("within"), F.size(s["i"]).cast("long").alias("pairs")))


def diff(left: DataFrame, right: DataFrame, query: Query, within_m: float = 20.0) -> DataFrame:
    """One row: diff_m (summed distance of the greedy pairing of two top-k lists), within (pairs of at most within_m) and pairs."""
    as_list = lambda top, name: top.agg(F.transform(F.sort_array(F.collect_list(F.struct("rank", "cell_x", "cell_y"))), lambda s: F.struct(s["cell_x"].alias("cell_x"), s["cell_y"].alias("cell_y"))).alias(name))
    both = as_list(left, "a").crossJoin(as_list(right, "b"))
    out = both.select(greedy_pairing(F.col("a"), F.col("b"), *cell_metres(query), within_m).alias("g"))
    return out.select(F.round("g.total", 6).alias("diff_m"), F.col("g.within").alias("within"), F.col("g.pairs").alias("pairs"))


def truth_error(top: DataFrame, marks: DataFrame, query: Query) -> DataFrame:
    """rank, mark_id, error_m: each found cell's nearest known place (mark_id, mark_lat, mark_lon; few, so broadcast)."""
    lat, lon = centre_of(query.grid, F.col("cell_x"), F.col("cell_y"))
    dx, dy = (lon - F.col("mark_lon")) * east_scale(query.lat0), (lat - F.col("mark_lat")) * METRES_PER_DEGREE
    near = top.crossJoin(F.broadcast(marks)).select("rank", "mark_id", F.sqrt(dx * dx + dy * dy).alias("d"))
    return near.groupBy("rank").agg(F.min(F.struct("d", "mark_id")).alias("m")).select("rank", "m.mark_id", F.round("m.d", 6).alias("error_m"))


def region_stats(fovs: DataFrame, query: Query) -> DataFrame:
    """n_cells, n_fovs, area_km2 of a region."""
    return candidates(fovs, query).agg(F.count("*").alias("n_fovs")).select(F.lit(query.grid.cells).cast("long").alias("n_cells"), "n_fovs", F.round(F.lit(query.area.km2()), 6).alias("area_km2"))


def cells_per_mbr(fovs: DataFrame, query: Query) -> DataFrame:
    """n_fovs, cell_visits, mean_cells: what the optimized method evaluates."""
    n = span_cells()
    return with_span(candidates(fovs, query), query).agg(F.count("*").alias("n_fovs"), F.sum(n).alias("cell_visits"), F.round(F.avg(n), 6).alias("mean_cells"))


def cost_model(fovs: DataFrame, query: Query) -> DataFrame:
    """naive_pairs, optimized_pairs and their ratio."""
    per = cells_per_mbr(fovs, query)
    return per.select((F.col("n_fovs") * query.grid.cells).alias("naive_pairs"), F.col("cell_visits").alias("optimized_pairs"), F.round(F.col("n_fovs") * query.grid.cells / F.col("cell_visits"), 6).alias("ratio"))


def heatmap(matrix: DataFrame, bin_cells: int = 1, log: bool = False) -> DataFrame:
    """bin_x, bin_y, gamma: each bin's largest share of the area's largest sum, optionally on a logarithmic scale."""
    top = matrix.agg(F.max("ci_fixed").alias("top"))
    share = F.max("ci_fixed") / F.first("top")
    value = F.log1p(share * 1000) / F.log1p(F.lit(1000.0)) if log else share
    rows = matrix.crossJoin(F.broadcast(top))
    return rows.groupBy(F.floor(F.col("cell_x") / bin_cells).alias("bin_x"), F.floor(F.col("cell_y") / bin_cells).alias("bin_y")).agg(F.round(value, 6).alias("gamma"))


def largest_gap(left: DataFrame, right: DataFrame) -> DataFrame:
    """cells, max_gap: the largest difference between two matrices; a missing cell counts as zero."""
    both = left.select("cell_x", "cell_y", F.col("ci_fixed").alias("a")).join(right.select("cell_x", "cell_y", F.col("ci_fixed").alias("b")), ["cell_x", "cell_y"], "full_outer")
    return both.agg(F.count("*").alias("cells"), F.round(F.coalesce(F.max(F.abs(F.coalesce("a", F.lit(0)) - F.coalesce("b", F.lit(0)))), F.lit(0)) / FIXED, 6).alias("max_gap"))


__all__ = ["GridSpec", "cell_metres", "cells_per_mbr", "cost_model", "diff", "greedy_pairing", "heatmap", "largest_gap", "region_stats", "truth_error"]
