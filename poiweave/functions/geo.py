"""Distances, projections and tile keys as native column expressions."""

from __future__ import annotations

import math

from pyspark.sql import Column
from pyspark.sql import functions as F

EARTH_M = 6_371_000.0


def haversine_m(lat1: Column, lon1: Column, lat2: Column, lon2: Column) -> Column:
    """Great-circle metres."""
    a = F.pow(F.sin(F.radians(lat2 - lat1) / 2), 2) + F.cos(F.radians(lat1)) * F.cos(F.radians(lat2)) * F.pow(F.sin(F.radians(lon2 - lon1) / 2), 2)
    return 2 * EARTH_M * F.asin(F.sqrt(F.least(F.lit(1.0), a)))


def equirectangular(lat: Column, lon: Column, lat0: float, lon0: float) -> tuple[Column, Column]:
    """Metres east and north of an origin; good over the extent of a state."""
    return F.radians(lon - lon0) * math.cos(math.radians(lat0)) * EARTH_M, F.radians(lat - lat0) * EARTH_M


def mercator(lat: Column, lon: Column) -> tuple[Column, Column]:
    return F.radians(lon) * EARTH_M, F.log(F.tan(F.lit(math.pi / 4) + F.radians(lat) / 2)) * EARTH_M


def euclid(x1: Column, y1: Column, x2: Column, y2: Column) -> Column:
    return F.sqrt((x2 - x1) * (x2 - x1) + (y2 - y1) * (y2 - y1))


def distance(metric: str, lat1: Column, lon1: Column, lat2: Column, lon2: Column) -> Column:
    """``haversine``, or ``planar``: metres on a plane whose scale is that of the middle latitude."""
    if metric == "haversine":
        return haversine_m(lat1, lon1, lat2, lon2)
    if metric == "planar":
        x = F.radians(lon2 - lon1) * F.cos(F.radians((lat1 + lat2) / 2))
        return EARTH_M * F.sqrt(x * x + F.pow(F.radians(lat2 - lat1), 2))
    raise ValueError(f"unknown metric {metric}")


def tile(value: Column, degrees: float) -> Column:
    """Integer tile along one axis."""
    return F.floor(value / degrees).cast("long")


def zorder(x: Column, y: Column, bits: int = 16) -> Column:
    """Interleaved bits of two non-negative integers: near points get near keys."""
    out = F.lit(0).cast("long")
    for k in range(bits):
        out = out.bitwiseOR(F.shiftleft(F.shiftright(x.cast("long"), k).bitwiseAND(F.lit(1).cast("long")), 2 * k))
        out = out.bitwiseOR(F.shiftleft(F.shiftright(y.cast("long"), k).bitwiseAND(F.lit(1).cast("long")), 2 * k + 1))
    return out


def ring(tx: Column, ty: Column, k: int) -> Column:
    """All tiles within ``k`` steps as an array of structs (x, y)."""
    steps = [(i, j) for i in range(-k, k + 1) for j in range(-k, k + 1)]
    return F.array(*(F.struct((tx + i).alias("x"), (ty + j).alias("y")) for i, j in steps))
