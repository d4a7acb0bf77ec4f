"""A query: area, grid, time, number of places, and model."""

from __future__ import annotations

import datetime as dt
import math
from dataclasses import dataclass, field

from ..functions.geo import METRES_PER_DEGREE, east_scale
from ..functions.intention import Model
from . import stopping


@dataclass(frozen=True)
class Area:
    """An upright box in degrees; it must not cross the antimeridian or come near the poles."""

    min_lat: float
    max_lat: float
    min_lon: float
    max_lon: float

    def __post_init__(self) -> None:
        if not (-85 <= self.min_lat < self.max_lat <= 85 and -180 <= self.min_lon < self.max_lon <= 180):
            raise ValueError("an area is a box within 85 degrees of latitude that does not cross the antimeridian; split it if need be")

    @classmethod
    def around(cls, lat: float, lon: float, half: float) -> Area:
        return cls(lat - half, lat + half, lon - half, lon + half)

    @property
    def mid_lat(self) -> float:
        return (self.min_lat + self.max_lat) / 2

    def km2(self) -> float:
        return (self.max_lat - self.min_lat) * METRES_PER_DEGREE * (self.max_lon - self.min_lon) * east_scale(self.mid_lat) / 1e6


@dataclass(frozen=True)
class GridSpec:
    """Equal square cells of ``cell`` degrees over an area, counted from its south-west corner; nothing is materialised.

    Where the area is no multiple of the cell, the last row and column reach beyond it, so no part of it is left out.
    """

    area: Area
    cell: float = 0.0001

    @property
    def nx(self) -> int:
        return max(math.ceil((self.area.max_lon - self.area.min_lon) / self.cell - 1e-6), 1)

    @property
    def ny(self) -> int:
        return max(math.ceil((self.area.max_lat - self.area.min_lat) / self.cell - 1e-6), 1)

    @property
    def cells(self) -> int:
        return self.nx * self.ny


@dataclass(frozen=True)
class TimeRange:
    """Half-open; either end may be missing."""

    lo: dt.datetime | None = None
    hi: dt.datetime | None = None


@dataclass(frozen=True)
class Query:
    area: Area
    k: int = 5
    cell: float = 0.0001
    time: TimeRange = field(default_factory=TimeRange)
    model: Model = field(default_factory=Model)
    #: Latitude at which degrees become metres, if not the middle of the area.
    plane_lat: float | None = None

    def __post_init__(self) -> None:
        if self.k < 1 or self.cell <= 0:
            raise ValueError("k and cell must be positive")

    @property
    def grid(self) -> GridSpec:
        return GridSpec(self.area, self.cell)

    @property
    def lat0(self) -> float:
        return self.area.mid_lat if self.plane_lat is None else self.plane_lat


@dataclass(frozen=True)
class ClusterOptions:
    """Of clustered incremental sampling. Recommended: k to 2k clusters, a cluster sample of 0.2 to 0.5."""

    clusters: int = 6
    cluster_fraction: float = 0.5
    batch_fraction: float = 0.05
    threshold: float = 0.1
    rule: str = "max_change"
    measure: str = "relative"
    shift_threshold_m: float = 20.0
    max_iterations: int | None = None
    min_iterations: int = 2
    membership: str = "range"
    #: How batches are dealt: exact, hash, or a name given to operators.sampling.add_sampler.
    sampler: str = "exact"
    lloyd_steps: int = 3
    salt: str = "s0"

    def __post_init__(self) -> None:
        if self.measure not in stopping.MEASURES or self.rule not in stopping.RULES:
            raise ValueError("unknown stopping rule or measure")
        if not (0 < self.cluster_fraction <= 1 and 0 < self.batch_fraction <= 1 and self.clusters >= 1) or self.membership not in ("range", "kmeans"):
            raise ValueError("fractions lie in (0, 1] and there is at least one cluster")

    @classmethod
    def advised(cls, k: int, **options) -> ClusterOptions:
        """Options for a list of k places: clusters between k and 2k, half of the fields of view for clustering."""
        return cls(**{"clusters": max(k + k // 2, 1), **options})

    def within_advice(self, k: int) -> bool:
        """Whether clusters and the cluster sample lie in the recommended ranges for a list of k places."""
        return k <= self.clusters <= 2 * k and 0.2 <= self.cluster_fraction <= 0.5

    @property
    def batches(self) -> int:
        return math.ceil(1 / self.batch_fraction - 1e-9)

    @property
    def rounds(self) -> int:
        return min(self.batches, self.max_iterations or self.batches)
