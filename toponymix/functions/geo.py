"""Geographic columns over micro-degree integers."""

from __future__ import annotations

import math

from pyspark.sql import Column
from pyspark.sql import functions as F

EARTH_M = 6371008.8


def degrees(micro: Column) -> Column:
    return micro / F.lit(1000000.0)


def great_circle_m(lat1: Column, lon1: Column, lat2: Column, lon2: Column) -> Column:
    """Metres between two points given in degrees (haversine)."""
    a, b = F.radians(lat1), F.radians(lat2)
    dy, dx = F.sin((b - a) / 2), F.sin((F.radians(lon2) - F.radians(lon1)) / 2)
    return F.lit(2 * EARTH_M) * F.asin(F.least(F.lit(1.0), F.sqrt(dy * dy + F.cos(a) * F.cos(b) * dx * dx)))


def planar_m(lat1: Column, lon1: Column, lat2: Column, lon2: Column) -> Column:
    """Equirectangular metres; close to the great circle inside a city."""
    scale = F.cos(F.radians((lat1 + lat2) / 2))
    dy, dx = F.radians(lat2 - lat1), F.radians(lon2 - lon1) * scale
    return F.lit(EARTH_M) * F.sqrt(dy * dy + dx * dx)


def extent_u(side_m: float, lat_ref: float) -> tuple[int, int]:
    """(latitude, longitude) micro-degrees of a square of `side_m` metres at a reference latitude."""
    per_u = math.pi * EARTH_M / 180 / 1e6
    return round(side_m / per_u), round(side_m / (per_u * math.cos(math.radians(lat_ref))))
