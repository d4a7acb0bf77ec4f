"""The dense form of the intentions of many fields of view over a block of cells, for tasks that own a tile or a cluster."""

from __future__ import annotations

import math

import numpy as np

from ..functions.geo import METRES_PER_DEGREE, east_scale
from ..functions.intention import FIXED, Model, density_scale
from ..plans.query import Query

#: Pairs of field of view and cell that are evaluated at once: few enough for a core's own cache.
PAIRS_AT_ONCE = 32_000
#: Metres that lie beyond any visible distance; what pads a span is put there.
OUT_OF_REACH = 1e150
#: Spans are padded to multiples of so many cells, and those of one size are evaluated together.
PADDED = 8
#: What ``add_fovs`` takes of each field of view, in this order.
SHAPE = ("lat", "lon", "theta", "r_m", "alpha", "x0", "x1", "y0", "y1")


def add_fovs(block: np.ndarray, x_first: int, y_first: int, query: Query, columns: list[np.ndarray]) -> None:
    """Add fields of view to ``block`` (rows are y, columns x, from cell (x_first, y_first)).

    columns: SHAPE; the spans are inclusive and are cut to the block. Offsets are taken once for each row and column of a
    span, pies and full circles apart, so that a pair needs no index of its own before it is found to count.
    """
    lat, lon, theta, r_m, alpha, x0, x1, y0, y1 = columns
    x0, x1 = np.maximum(x0, x_first), np.minimum(x1, x_first + block.shape[1] - 1)
    y0, y1 = np.maximum(y0, y_first), np.minimum(y1, y_first + block.shape[0] - 1)
    wide, high = x1 - x0 + 1, y1 - y0 + 1
    inside = np.flatnonzero((wide > 0) & (high > 0))
    if not len(inside):
        return
    flat, area, r_m = block.reshape(-1), query.area, np.minimum(r_m, OUT_OF_REACH / 2)
    sizes = np.stack([needs_no_angle(alpha, query.model), -(-high // PADDED), -(-wide // PADDED)])[:, inside]
    order = np.lexsort(sizes)
    inside, sizes = inside[order], sizes[:, order]
    cuts = [0, *(np.flatnonzero((sizes[:, 1:] != sizes[:, :-1]).any(axis=0)) + 1).tolist(), len(inside)]
    for first, last in zip(cuts[:-1], cuts[1:], strict=True):
        free, rows, cols = bool(sizes[0, first]), int(sizes[1, first]) * PADDED, int(sizes[2, first]) * PADDED
        at_once, x, y = max(PAIRS_AT_ONCE // (rows * cols), 1), np.arange(cols), np.arange(rows)
        place = y[:, None] * block.shape[1] + x
        for at in range(first, last, at_once):
            own = inside[at : min(at + at_once, last)]
            dx = (area.min_lon + (x + x0[own, None] + 0.5) * query.cell - lon[own, None]) * east_scale(query.lat0)
            dy = (area.min_lat + (y + y0[own, None] + 0.5) * query.cell - lat[own, None]) * METRES_PER_DEGREE
            dx[x >= wide[own, None]] = OUT_OF_REACH
            dy[y >= high[own, None]] = OUT_OF_REACH
            found, value = intentions(dx[:, None, :], dy[:, :, None], *(v[own, None, None] for v in (theta, r_m, alpha)), query.model, free)
            corner = (y0[own] - y_first) * block.shape[1] + x0[own] - x_first
            np.add.at(flat, (corner[:, None, None] + place).reshape(-1)[found], value)


def needs_no_angle(alpha: np.ndarray, model: Model) -> np.ndarray:
    """Whether full circles are plain: those need no angle, unless its density is asked for."""
    return (alpha >= 360.0) & ((model.kind == "full_coverage") | (model.circular == "constant"))


def intentions(dx: np.ndarray, dy: np.ndarray, theta: np.ndarray, r_m: np.ndarray, alpha: np.ndarray, model: Model, free: bool) -> tuple[np.ndarray, np.ndarray]:
    """(places, fixed-point intentions) of the pairs within reach; the arrays broadcast to the pairs. free: all are such as ``needs_no_angle`` tells, else none."""
    d = dx * dx + dy * dy
    np.sqrt(d, out=d)
    sd, sa = model.sigma_distance, model.sigma_angle
    seen = d <= (np.minimum(r_m, model.reach * sd) if model.reach is not None and model.kind == "probabilistic" else r_m)
    if model.kind == "center_line":
        t = np.radians(theta)
        ahead, across = dx * np.sin(t) + dy * np.cos(t), np.abs(dx * np.cos(t) - dy * np.sin(t))
        seen &= (ahead >= 0) & (across <= model.line_width_m / 2)
    elif not free:
        off = _off_axis(dx, dy, theta)
        seen &= off <= alpha / 2
    found = np.flatnonzero(seen)
    if model.kind != "probabilistic":
        return found, np.full(len(found), int(FIXED), np.int64)
    ci = _radial(d.reshape(-1)[found], sd)
    if not free:
        off = off.reshape(-1)[found]
        ci *= np.exp(-(off * off) / (2 * sa * sa)) * density_scale(sa)
    return found, np.floor(ci * FIXED + 0.5).astype(np.int64)


def _radial(d: np.ndarray, sigma: float) -> np.ndarray:
    return np.exp(-(d * d) / (2 * sigma * sigma)) * density_scale(sigma)


def _off_axis(dx: np.ndarray, dy: np.ndarray, theta: np.ndarray) -> np.ndarray:
    """Degrees between the axis and (dx, dy), none at the camera. The remainder is slow and these angles are at most one turn off."""
    off = np.degrees(np.arctan2(dx, dy))
    off += 360.0 * (off < 0.0)
    off -= theta
    off += 180.0
    if ((theta < 0.0) | (theta > 360.0)).any():
        off %= 360.0
    else:
        off += 360.0 * (off < 0.0)
        off -= 360.0 * (off >= 360.0)
    off -= 180.0
    np.abs(off, out=off)
    if (here := (dx == 0.0) & (dy == 0.0)).any():
        off[here] = 0.0
    return off


def largest_cells(block: np.ndarray, x_first: int, y_first: int, k: int, least: int = 1) -> list[tuple[int, int, int]]:
    """(cell_x, cell_y, sum) of the k largest positive sums; ties by row, then column. least: at least k sums are known to be as large, if above 1."""
    flat = block.reshape(-1)
    at = np.flatnonzero(flat >= max(least, 1))
    if len(at) > k:
        at = at[flat[at] >= np.partition(flat[at], len(at) - k)[len(at) - k]]
    best = at[np.lexsort((at, -flat[at]))][:k]
    return [(int(i % block.shape[1]) + x_first, int(i // block.shape[1]) + y_first, int(flat[i])) for i in best]


def greedy_total(a: list[tuple[int, int]], b: list[tuple[int, int]], width: float, height: float) -> float:
    """The summed distance of the closest remaining pairs of two short lists of cells."""
    pairs = sorted((math.sqrt(((p[0] - q[0]) * width) ** 2 + ((p[1] - q[1]) * height) ** 2), i, j) for i, p in enumerate(a) for j, q in enumerate(b))
    used_i, used_j, total = set(), set(), 0.0
    for d, i, j in pairs:
        if i not in used_i and j not in used_j:
            used_i.add(i), used_j.add(j)
            total += d
    return total
