"""How much a field of view intends to capture a place: models of the capture intention of one cell.

The angular and the radial factor are normal densities, cut off at half the visible angle and at the visible distance. A
full circle has no direction, so its angular factor is the constant 1 unless the Gaussian is asked for.
"""

from __future__ import annotations

import math
from dataclasses import dataclass

from pyspark.sql import Column
from pyspark.sql import functions as F

from .geo import angle_diff, bearing, distance

#: Sums of intentions are taken over integers, so they are alike for every order and partitioning.
FIXED = 1e12


@dataclass(frozen=True)
class Model:
    """kind: probabilistic, full_coverage or center_line; circular: constant or gaussian; reach: radial cut in sigmas, if any."""

    kind: str = "probabilistic"
    circular: str = "constant"
    sigma_angle: float = 15.0
    sigma_distance: float = 25.0
    reach: float | None = None
    line_width_m: float = 15.742784

    def __post_init__(self) -> None:
        if self.kind not in ("probabilistic", "full_coverage", "center_line") or self.circular not in ("constant", "gaussian"):
            raise ValueError("unknown model")


def density_scale(sigma: float) -> float:
    return 1.0 / (sigma * math.sqrt(2 * math.pi))


def gaussian(value: Column, sigma: float) -> Column:
    return F.exp(-(value * value) / F.lit(2 * sigma * sigma)) * F.lit(density_scale(sigma))


def ci_angle(diff: Column, alpha: Column, sigma: float = 15.0, circular: str = "constant") -> Column:
    """Density of the angle off the axis; 0 beyond half the visible angle; 1 for full circles in constant mode."""
    inside = F.when(diff <= alpha / 2, gaussian(diff, sigma)).otherwise(0.0)
    return F.when(alpha >= 360.0, F.lit(1.0)).otherwise(inside) if circular == "constant" else inside


def ci_dist(d: Column, r_m: Column, sigma: float = 25.0) -> Column:
    """Density of the distance from the camera; 0 beyond the visible distance."""
    return F.when(d <= r_m, gaussian(d, sigma)).otherwise(0.0)


def off_axis(dx: Column, dy: Column, theta: Column) -> Column:
    """Angle between the axis and the direction (dx, dy); none at the camera itself."""
    return F.when((dx == 0.0) & (dy == 0.0), 0.0).otherwise(angle_diff(bearing(dx, dy), theta))


def covers(dx: Column, dy: Column, theta: Column, r_m: Column, alpha: Column) -> Column:
    """Whether the place at (dx, dy) from the camera lies in the pie or disc; its borders count."""
    return (distance(dx, dy) <= r_m) & ((alpha >= 360.0) | (off_axis(dx, dy, theta) <= alpha / 2))


def intention(dx: Column, dy: Column, theta: Column, r_m: Column, alpha: Column, model: Model = Model()) -> Column:  # noqa: B008
    """The capture intention of the place at (dx east, dy north) metres from the camera."""
    d = distance(dx, dy)
    radius = r_m if model.reach is None else F.least(r_m, F.lit(model.reach * model.sigma_distance))
    if model.kind == "full_coverage":
        return F.when(covers(dx, dy, theta, r_m, alpha), 1.0).otherwise(0.0)
    if model.kind == "center_line":
        across = F.abs(dx * F.cos(F.radians(theta)) - dy * F.sin(F.radians(theta)))
        ahead = dx * F.sin(F.radians(theta)) + dy * F.cos(F.radians(theta))
        return F.when((d <= r_m) & (ahead >= 0) & (across <= F.lit(model.line_width_m / 2)), 1.0).otherwise(0.0)
    return ci_angle(off_axis(dx, dy, theta), alpha, model.sigma_angle, model.circular) * ci_dist(d, radius, model.sigma_distance)


def fixed(ci: Column) -> Column:
    """An intention, which is never negative, as an integer of 1e-12; halves go up. Spark's own rounding of doubles goes through big decimals."""
    return F.floor(ci * F.lit(FIXED) + F.lit(0.5)).cast("long")


def useful_radius(model: Model, whole: bool) -> float:
    """The distance beyond which an intention is certainly less than half of 1e-12, and so exactly zero, or beyond ``reach``.

    whole: of full circles. Models without a radial density have no such distance.
    """
    if model.kind != "probabilistic":
        return math.inf
    peak = density_scale(model.sigma_distance) * (1.0 if whole and model.circular == "constant" else density_scale(model.sigma_angle))
    zero = model.sigma_distance * math.sqrt(2 * math.log(max(peak * FIXED / 0.5, 1.0))) * (1 + 1e-9) + 1e-6
    return zero if model.reach is None else min(zero, model.reach * model.sigma_distance)


def reach_error_bound(model: Model, fovs: int) -> float:
    """The most that cutting every field of view at ``reach`` sigmas can take from a cell's sum."""
    if model.reach is None:
        return 0.0
    return fovs * density_scale(model.sigma_distance) * math.exp(-model.reach**2 / 2)
