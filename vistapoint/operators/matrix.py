"""Intention matrices: the sum over all fields of view, cell by cell, in sparse form (cell_x, cell_y, ci_fixed).

naive judges every pair of field of view and cell, far ones of large grids in blocks; mbr_explode only the cells of each bounding box; tiled computes the same
in dense blocks, moving fields of view instead of candidate cells. All sums are over integers, so all three are equal.
"""

from __future__ import annotations

import math
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..functions.geo import METRES_PER_DEGREE, distance, east_scale
from ..functions.intention import FIXED, fixed, gaussian, intention, off_axis, useful_radius
from ..plans.query import GridSpec, Query
from .kernel import SHAPE, add_fovs, largest_cells
from .retrieval import candidates

#: Cells that the naive method broadcasts at most, some 30 bytes each; more are met block by block.
NAIVE_CELLS = 10_000
#: Sides of these blocks in cells, each a multiple of the next.
BLOCKS = (512, 64, 16, 4)
#: Pairs of field of view and cell from which the tiled form is used; below, starting Python workers costs more than it saves.
TILED_FROM = 2_000_000
TILE = 256
#: Pairs that are worth a task of their own in the dense form.
LEAST_WORK = 10_000_000
_SHAPE = ("lat", "lon", "theta", "r_m", "alpha")


def cell_of(grid: GridSpec, lat: Column, lon: Column) -> tuple[Column, Column]:
    return F.floor((lon - grid.area.min_lon) / grid.cell).cast("long"), F.floor((lat - grid.area.min_lat) / grid.cell).cast("long")


def centre_of(grid: GridSpec, x: Column, y: Column) -> tuple[Column, Column]:
    """(lat, lon) of a cell's centre."""
    return F.lit(grid.area.min_lat) + (y + 0.5) * F.lit(grid.cell), F.lit(grid.area.min_lon) + (x + 0.5) * F.lit(grid.cell)


def cells(spark: SparkSession, grid: GridSpec) -> DataFrame:
    """All cells of a grid, made in the tasks."""
    return spark.range(grid.cells).select((F.col("id") % grid.nx).alias("cell_x"), F.floor(F.col("id") / grid.nx).cast("long").alias("cell_y"))


def with_span(fovs: DataFrame, query: Query, clip: bool = False) -> DataFrame:
    """x0, x1, y0, y1: the inclusive cell span of each bounding box inside the grid; those without cells go.

    A stored box lies in the plane of its own latitude; here it is carried into the plane of the query, where cells are
    judged. clip also cuts the span where intentions are certainly zero, which changes no sum.
    """
    slack, grid, a = 1e-6, query.grid, query.area
    scale = F.cos(F.radians("lat")) / F.lit(math.cos(math.radians(query.lat0)))
    west, east = F.col("lon") + (F.col("min_lon") - F.col("lon")) * scale, F.col("lon") + (F.col("max_lon") - F.col("lon")) * scale
    south, north = F.col("min_lat"), F.col("max_lat")
    if clip and query.model.kind == "probabilistic":
        far = F.when(F.col("alpha") >= 360.0, useful_radius(query.model, True)).otherwise(useful_radius(query.model, False))
        dx, dy = far / F.lit(east_scale(query.lat0)), far / F.lit(METRES_PER_DEGREE)
        west, east = F.greatest(west, F.col("lon") - dx), F.least(east, F.col("lon") + dx)
        south, north = F.greatest(south, F.col("lat") - dy), F.least(north, F.col("lat") + dy)
    low = lambda v, origin: F.greatest(F.floor((v - origin) / grid.cell - slack), F.lit(0)).cast("long")
    high = lambda v, origin, n: F.least(F.floor((v - origin) / grid.cell + slack), F.lit(n - 1)).cast("long")
    spans = {"x0": low(west, a.min_lon), "x1": high(east, a.min_lon, grid.nx), "y0": low(south, a.min_lat), "y1": high(north, a.min_lat, grid.ny)}
    return fovs.withColumns(spans).where("x0 <= x1 and y0 <= y1")


def span_cells() -> Column:
    return (F.col("x1") - F.col("x0") + 1) * (F.col("y1") - F.col("y0") + 1)


def _positive(rows: DataFrame, query: Query, keys: tuple[str, ...] = ()) -> DataFrame:
    """keys, cell_x, cell_y, ci_fixed of the pairs of field of view and cell with a positive intention.

    What a pair costs rises step by step: distance, then arc tangent, then densities, each only where the one before allows.
    Catalyst would push the last test down through all steps and so repeat them in one generated method, longer than the JVM
    compiles to machine code (8,000 bytes); a generator's output is not pushed, hence the explode of one value.
    """
    lat, lon = centre_of(query.grid, F.col("cell_x"), F.col("cell_y"))
    dx, dy = (lon - F.col("lon")) * F.lit(east_scale(query.lat0)), (lat - F.col("lat")) * F.lit(METRES_PER_DEGREE)
    model = query.model
    steps = rows.select(*keys, "cell_x", "cell_y", "theta", "r_m", "alpha", dx.alias("dx"), dy.alias("dy"))
    if model.kind != "probabilistic":
        value = fixed(intention(F.col("dx"), F.col("dy"), F.col("theta"), F.col("r_m"), F.col("alpha"), model))
    else:
        radius = F.col("r_m") if model.reach is None else F.least("r_m", F.lit(model.reach * model.sigma_distance))
        steps = steps.withColumn("d", distance(F.col("dx"), F.col("dy")))
        off, angular = off_axis(F.col("dx"), F.col("dy"), F.col("theta")), gaussian(F.col("off"), model.sigma_angle)
        if model.circular == "constant":
            off, angular = F.when(F.col("alpha") >= 360.0, 0.0).otherwise(off), F.when(F.col("alpha") >= 360.0, 1.0).otherwise(angular)
        steps = steps.withColumn("off", F.when(F.col("d") <= radius, off))
        value = F.when(F.col("off") <= F.col("alpha") / 2, fixed(angular * gaussian(F.col("d"), model.sigma_distance))).otherwise(F.lit(0))
    return steps.select(*keys, "cell_x", "cell_y", F.explode(F.array(value)).alias("ci_fixed")).where("ci_fixed > 0")


def summed(rows: DataFrame, *keys: str) -> DataFrame:
    return rows.groupBy(*keys, "cell_x", "cell_y").agg(F.sum("ci_fixed").alias("ci_fixed"))


def _by_blocks(found: DataFrame, query: Query, near: Column) -> DataFrame:
    """found (with ``far``) by every cell that ``near`` holds for, of a grid of any size.

    All fields of view meet all blocks of cells. A block whose nearest centre is beyond ``far`` is done with as a whole, since each
    of its cells fails by its distance; any other falls into smaller blocks and at last into its cells. No cell is stored or moved.
    """
    grid, widest = query.grid, BLOCKS[0]
    nx, ny = -(-grid.nx // widest), -(-grid.ny // widest)
    blocks = found.sparkSession.range(nx * ny).select((F.col("id") % nx * widest).alias("cell_x"), (F.floor(F.col("id") / nx) * widest).cast("long").alias("cell_y"))

    def reached(side: int) -> Column:
        lat, lon = centre_of(grid, F.col("cell_x"), F.col("cell_y"))
        wide = F.lit((side - 1) * grid.cell)
        dx = F.greatest(lon - F.col("lon"), F.col("lon") - lon - wide, F.lit(0.0)) * F.lit(east_scale(query.lat0))
        dy = F.greatest(lat - F.col("lat"), F.col("lat") - lat - wide, F.lit(0.0)) * F.lit(METRES_PER_DEGREE)
        return distance(dx, dy) <= F.col("far") + 1e-3

    rows = found.join(F.broadcast(blocks), reached(widest))
    for side, below in zip(BLOCKS, (*BLOCKS[1:], 1), strict=True):
        across = side // below
        rows = rows.withColumn("place", F.explode(F.sequence(F.lit(0).cast("long"), F.lit(across * across - 1).cast("long"))))
        rows = rows.withColumns({"cell_x": F.col("cell_x") + F.col("place") % across * below, "cell_y": F.col("cell_y") + F.expr(f"place div {across}") * below})
        rows = rows.where((F.col("cell_x") < grid.nx) & (F.col("cell_y") < grid.ny))
        if below > 1:
            rows = rows.where(reached(below))
    lat, lon = centre_of(grid, F.col("cell_x"), F.col("cell_y"))
    return rows.withColumns({"cell_lat": lat, "cell_lon": lon}).where(near)


def naive(fovs: DataFrame, query: Query, cells_of: DataFrame | None = None, limit: int | None = None) -> DataFrame:
    """All pairs, of any number of fields of view and cells. cells_of restricts it to some cells; limit, if given, refuses more fields of view.

    Fields of view are spread over the tasks and each meets all cells, which are broadcast where they are few, and else met
    block by block. The join's condition judges each pair by its distance and, by a product, its angle, with a margin: what
    fails has no intention and makes no row.
    """
    found = candidates(fovs, query).select("fov_id", *_SHAPE)
    if limit is not None and found.limit(limit + 1).count() > limit:
        raise ValueError(f"more than {limit} fields of view; use optimized or tiled")
    grid = cells_of if cells_of is not None else cells(fovs.sparkSession, query.grid)
    few = query.grid.cells <= NAIVE_CELLS or (cells_of is not None and grid.limit(NAIVE_CELLS + 1).count() <= NAIVE_CELLS)
    lat, lon = centre_of(query.grid, F.col("cell_x"), F.col("cell_y"))
    dx, dy = (F.col("cell_lon") - F.col("lon")) * F.lit(east_scale(query.lat0)), (F.col("cell_lat") - F.col("lat")) * F.lit(METRES_PER_DEGREE)
    model, pie, theta = query.model, F.col("alpha") < 360.0, F.radians("theta")
    far = F.when(pie, min(useful_radius(model, False), 1e9)).otherwise(min(useful_radius(model, True), 1e9))
    turned = F.cos(F.radians(F.col("alpha") / 2)) - 1e-9
    axes = {"ahead_x": F.sin(theta), "ahead_y": F.cos(theta), "far": F.least("r_m", far), "least": F.when(pie, turned).otherwise(-2.0) if model.kind == "probabilistic" else F.lit(-2.0)}
    d = distance(dx, dy)
    near = (d <= F.col("far")) & (dx * F.col("ahead_x") + dy * F.col("ahead_y") >= d * F.col("least"))
    tasks = max(int(fovs.sparkSession.conf.get("spark.sql.shuffle.partitions")), 1)
    spread = found.withColumns(axes).repartition(tasks, "fov_id")
    if few:
        return summed(_positive(spread.join(F.broadcast(grid.select("cell_x", "cell_y", lat.alias("cell_lat"), lon.alias("cell_lon"))), near), query))
    sums = summed(_positive(_by_blocks(spread, query, near), query))
    return sums if cells_of is None else sums.join(cells_of, ["cell_x", "cell_y"], "left_semi")


def _bounded(rows: DataFrame, bounds: tuple[str, str, str, str] | None) -> DataFrame:
    if not bounds:
        return rows
    return rows.withColumns({"x0": F.greatest("x0", bounds[0]), "x1": F.least("x1", bounds[1]), "y0": F.greatest("y0", bounds[2]), "y1": F.least("y1", bounds[3])}).where("x0 <= x1 and y0 <= y1")


def exploded(fovs: DataFrame, query: Query, keys: tuple[str, ...] = (), bounds: tuple[str, str, str, str] | None = None, cells_of: DataFrame | None = None) -> DataFrame:
    """keys, cell_x, cell_y, ci_fixed for every cell with a positive intention; bounds names columns that narrow the span,
    cells_of (few, so broadcast) holds the only cells that are asked for."""
    rows = _bounded(with_span(fovs, query, clip=True), bounds)
    rows = rows.select(*keys, *_SHAPE, "x0", "y0", (F.col("x1") - F.col("x0") + 1).alias("wide"), span_cells().alias("cells"))
    rows = rows.withColumn("place", F.explode(F.sequence(F.lit(0).cast("long"), F.col("cells") - 1)))
    rows = rows.withColumns({"cell_x": F.col("x0") + F.col("place") % F.col("wide"), "cell_y": F.col("y0") + F.expr("place div wide")})
    if cells_of is not None:
        rows = rows.join(F.broadcast(cells_of), ["cell_x", "cell_y"], "left_semi")
    return _positive(rows, query, keys)


def optimized(fovs: DataFrame, query: Query, cells_of: DataFrame | None = None) -> DataFrame:
    """Only the cells of each bounding box; full circles skip the angular factor. cells_of restricts it to some cells."""
    return summed(exploded(candidates(fovs, query), query, cells_of=cells_of))


def dense(fovs: DataFrame, query: Query, key: str | None = None, bounds: tuple[str, str, str, str] | None = None, tile: int = TILE, tasks: int | None = None, best: int | None = None) -> DataFrame:
    """key (an integer column, if given), cell_x, cell_y, ci_fixed summed, by dense blocks: fields of view travel to the tiles they overlap.

    best: only so many of a tile's largest cells are wanted. What is not dealt out is whole in its task, which names just
    these; of tiles dealt to several tasks all cells are named, since their parts cannot tell.

    Tiles whose pairs exceed a fair share of a task's work are dealt to several tasks by hash; there are at most four times
    as many such tiles as tasks, so their list is broadcast. Without such tiles nothing is dealt. Little work takes fewer tasks.
    """
    tasks = tasks or max(int(fovs.sparkSession.conf.get("spark.sql.shuffle.partitions")), 1)
    rows = _bounded(with_span(fovs, query, clip=True), bounds)
    rows = rows.select((F.col(key) if key else F.lit(0)).cast("long").alias("own"), "fov_id", *_SHAPE, "x0", "x1", "y0", "y1")
    part = lambda lo, hi: F.explode(F.sequence(F.floor(F.col(lo) / tile), F.floor(F.col(hi) / tile)))
    rows = rows.withColumn("tile_x", part("x0", "x1")).withColumn("tile_y", part("y0", "y1"))
    shared = lambda lo, hi, t: F.least(F.col(hi), (F.col(t) + 1) * tile - 1) - F.greatest(F.col(lo), F.col(t) * tile) + 1
    loads = rows.groupBy("own", "tile_x", "tile_y").agg(F.sum(shared("x0", "x1", "tile_x") * shared("y0", "y1", "tile_y")).alias("load"))
    total = loads.agg(F.sum("load")).first()[0] or 0
    fair = max(total // (4 * tasks), LEAST_WORK)
    tasks = min(tasks, total // LEAST_WORK + 1)
    crowded = loads.where(F.col("load") > fair).select("own", "tile_x", "tile_y", F.ceil(F.col("load") / fair).alias("cuts"))
    if total > fair:
        rows = rows.join(F.broadcast(crowded), ["own", "tile_x", "tile_y"], "left").withColumn("salt", F.pmod(F.xxhash64("fov_id"), F.coalesce("cuts", F.lit(1))))
    else:
        rows = rows.withColumns({"salt": F.lit(0), "cuts": F.lit(None)})
    laid = rows.repartition(tasks, "own", "tile_x", "tile_y", "salt").sortWithinPartitions("own", "tile_x", "tile_y").select("own", "tile_x", "tile_y", F.col("cuts").isNotNull().cast("long").alias("parted"), *SHAPE)
    grid = query.grid

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        at: tuple[int, int, int] | None = None
        block, parted = np.zeros((0, 0), np.int64), False

        def emitted() -> pa.RecordBatch:
            if best is not None and not parted:
                listed = np.array(largest_cells(block, at[1] * tile, at[2] * tile, best), np.int64).reshape(-1, 3)
                return pa.RecordBatch.from_arrays([pa.array(np.full(len(listed), at[0])), *[pa.array(listed[:, i].copy()) for i in range(3)]], ["own", "cell_x", "cell_y", "ci_fixed"])
            y, x = np.nonzero(block)
            return pa.RecordBatch.from_arrays([pa.array(np.full(len(x), at[0])), pa.array(x + at[1] * tile), pa.array(y + at[2] * tile), pa.array(block[y, x])], ["own", "cell_x", "cell_y", "ci_fixed"])

        for batch in batches:
            if not batch.num_rows:
                continue
            columns = [c.to_numpy(zero_copy_only=False) for c in batch.columns]
            names = np.stack(columns[:3])
            cuts = [0, *(np.flatnonzero((names[:, 1:] != names[:, :-1]).any(axis=0)) + 1).tolist(), batch.num_rows]
            for i, j in zip(cuts[:-1], cuts[1:], strict=True):
                now = tuple(int(v) for v in names[:, i])
                if now != at:
                    if at is not None:
                        yield emitted()
                    at, parted = now, bool(columns[3][i])
                    block = np.zeros((min(tile, grid.ny - now[2] * tile), min(tile, grid.nx - now[1] * tile)), np.int64)
                add_fovs(block, now[1] * tile, now[2] * tile, query, [c[i:j] for c in columns[4:]])
        if at is not None:
            yield emitted()

    cells = laid.mapInArrow(run, "own long, cell_x long, cell_y long, ci_fixed long")
    return summed(cells.withColumnRenamed("own", key), key) if key else summed(cells)


def tiled(fovs: DataFrame, query: Query, tile: int = TILE, tasks: int | None = None, best: int | None = None) -> DataFrame:
    """The matrix by dense blocks; ``best`` as for ``dense``."""
    return dense(candidates(fovs, query), query, tile=tile, tasks=tasks, best=best)


def matrix(fovs: DataFrame, query: Query, method: str = "optimized", **options) -> DataFrame:
    return {"naive": naive, "optimized": optimized, "tiled": tiled}[method](fovs, query, **options)


def pair_count(fovs: DataFrame, query: Query) -> tuple[int, int]:
    """(fields of view in range, pairs that the optimized method visits)."""
    spans = with_span(candidates(fovs, query), query, clip=True)
    return tuple(spans.agg(F.count("*"), F.coalesce(F.sum(span_cells()), F.lit(0))).first())


def plan(fovs: DataFrame, query: Query, tiled_from: int = TILED_FROM) -> str:
    """The physical form for an exact answer: candidates are not worth shuffling from ``tiled_from`` pairs on."""
    return "tiled" if pair_count(fovs, query)[1] >= tiled_from else "optimized"


def normalised(matrix: DataFrame) -> DataFrame:
    """gamma: each cell's share of the largest sum."""
    top = matrix.agg(F.max("ci_fixed").alias("top"))
    return matrix.crossJoin(F.broadcast(top)).select("cell_x", "cell_y", (F.col("ci_fixed") / F.col("top")).alias("gamma"))


def camera_cells(fovs: DataFrame, query: Query) -> DataFrame:
    """How many cameras stand in each cell: the measure that ignores what they look at. ci_fixed counts in units of 1e12."""
    x, y = cell_of(query.grid, F.col("lat"), F.col("lon"))
    inside = (F.col("cell_x") >= 0) & (F.col("cell_x") < query.grid.nx) & (F.col("cell_y") >= 0) & (F.col("cell_y") < query.grid.ny)
    return candidates(fovs, query).select(x.alias("cell_x"), y.alias("cell_y")).where(inside).groupBy("cell_x", "cell_y").agg((F.count("*") * int(FIXED)).alias("ci_fixed"))


def top_cells(matrix: DataFrame, k: int) -> DataFrame:
    """The k largest cells: rank, cell_x, cell_y, ci; ties by cell_y, then cell_x. Each partition keeps k rows only."""
    best = matrix.orderBy(F.col("ci_fixed").desc(), "cell_y", "cell_x").limit(k)
    rank = F.row_number().over(Window.orderBy(F.col("ci_fixed").desc(), "cell_y", "cell_x")).cast("long")
    return best.select(rank.alias("rank"), "cell_x", "cell_y", F.round(F.col("ci_fixed") / FIXED, 6).alias("ci"))


def best_cells(fovs: DataFrame, query: Query, method: str) -> DataFrame:
    """``top_cells`` of a method's matrix. The dense form does not bring the matrix together: tiles name their own largest cells."""
    return top_cells(tiled(fovs, query, best=query.k) if method == "tiled" else matrix(fovs, query, method), query.k)


def top_per_group(matrix: DataFrame, group: str, k: int) -> DataFrame:
    """The k largest cells of each group."""
    w = Window.partitionBy(group).orderBy(F.col("ci_fixed").desc(), "cell_y", "cell_x")
    return matrix.withColumn("rank", F.row_number().over(w).cast("long")).where(F.col("rank") <= k).select(group, "rank", "cell_x", "cell_y", F.round(F.col("ci_fixed") / FIXED, 6).alias("ci"))
