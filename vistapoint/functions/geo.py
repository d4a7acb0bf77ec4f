"""Plane geometry in local metres, azimuths clockwise from north, and great-circle distance."""

from __future__ import annotations

import math

from pyspark.sql import Column
from pyspark.sql import functions as F

METRES_PER_DEGREE = 111_320.0
EARTH_RADIUS_M = 6_371_008.8


def east_scale(lat0: float) -> float:
    """Metres per degree of longitude at a latitude."""
    return METRES_PER_DEGREE * math.cos(math.radians(lat0))


def east_scale_at(lat: Column) -> Column:
    """Metres per degree of longitude at each row's latitude."""
    return F.lit(METRES_PER_DEGREE) * F.cos(F.radians(lat))


def to_local(lat: Column, lon: Column, lat_origin: float, lon_origin: float, lat0: float | None = None) -> tuple[Column, Column]:
    """(east, north) metres from an origin, equirectangular at latitude lat0, by default the origin's."""
    return (lon - F.lit(lon_origin)) * F.lit(east_scale(lat_origin if lat0 is None else lat0)), (lat - F.lit(lat_origin)) * F.lit(METRES_PER_DEGREE)


def bearing(dx: Column, dy: Column) -> Column:
    """Azimuth of (dx east, dy north), in [0, 360)."""
    return F.pmod(F.degrees(F.atan2(dx, dy)), F.lit(360.0))


def angle_diff(a: Column, b: Column) -> Column:
    """The circular difference of two azimuths, in [0, 180]."""
    return F.abs(F.pmod(a - b + F.lit(180.0), F.lit(360.0)) - F.lit(180.0))


def distance(dx: Column, dy: Column) -> Column:
    return F.sqrt(dx * dx + dy * dy)


def haversine(lat1: Column, lon1: Column, lat2: Column, lon2: Column) -> Column:
    """Great-circle metres."""
    half = F.pow(F.sin(F.radians(lat2 - lat1) / 2), 2) + F.cos(F.radians(lat1)) * F.cos(F.radians(lat2)) * F.pow(F.sin(F.radians(lon2 - lon1) / 2), 2)
    return F.lit(2 * EARTH_RADIUS_M) * F.asin(F.sqrt(half))


def z_order(x: Column, y: Column, bits: int = 16) -> Column:
    """The bits of two non-negative integers interleaved, x in the even places."""
    out = F.lit(0).cast("long")
    for b in range(bits):
        for value, shift in ((x, 2 * b), (y, 2 * b + 1)):
            out = out.bitwiseOR(F.shiftleft(F.shiftright(value.cast("long"), b).bitwiseAND(F.lit(1).cast("long")), shift))
    return out
