"""Distances between points as Column expressions, with predicates that avoid square roots."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import Column
from pyspark.sql import functions as F

EARTH_M = 6_371_008.8


def sq_euclid(ax: Column, ay: Column, bx: Column, by: Column) -> Column:
    return (ax - bx) * (ax - bx) + (ay - by) * (ay - by)


def euclid(ax: Column, ay: Column, bx: Column, by: Column) -> Column:
    return F.sqrt(sq_euclid(ax, ay, bx, by))


def manhattan(ax: Column, ay: Column, bx: Column, by: Column) -> Column:
    return F.abs(ax - bx) + F.abs(ay - by)


def chebyshev(ax: Column, ay: Column, bx: Column, by: Column) -> Column:
    return F.greatest(F.abs(ax - bx), F.abs(ay - by))


def haversine(ax: Column, ay: Column, bx: Column, by: Column) -> Column:
    """Metres between (longitude, latitude) points in degrees."""
    half = lambda d: F.sin(F.radians(d) / 2)
    h = half(by - ay) ** 2 + F.cos(F.radians(ay)) * F.cos(F.radians(by)) * half(bx - ax) ** 2
    return 2 * EARTH_M * F.asin(F.sqrt(F.least(h, F.lit(1.0))))


def temporal(at: Column, bt: Column) -> Column:
    return F.abs(at - bt)


def sq_vector(a: Column, b: Column) -> Column:
    """Squared distance of two arrays of equal length, components in order."""
    return F.aggregate(F.zip_with(a, b, lambda x, y: (x.cast("double") - y.cast("double")) * (x.cast("double") - y.cast("double"))), F.lit(0.0), lambda s, d: s + d)


WITHIN: dict[str, Callable[..., Column]] = {
    "euclid": lambda ax, ay, bx, by, eps: sq_euclid(ax, ay, bx, by) <= F.lit(float(eps) * float(eps)),
    "manhattan": lambda ax, ay, bx, by, eps: manhattan(ax, ay, bx, by) <= F.lit(float(eps)),
    "chebyshev": lambda ax, ay, bx, by, eps: chebyshev(ax, ay, bx, by) <= F.lit(float(eps)),
    "haversine": lambda ax, ay, bx, by, eps: haversine(ax, ay, bx, by) <= F.lit(float(eps)),
}
"""Name -> predicate; a further metric is one more entry, and must be at least the greater of the axis
differences for the methods that prune by cells (haversine is not, and works with the others)."""
CELL_SAFE = ("euclid", "manhattan", "chebyshev")
