"""Distances between points, and bounds between points and boxes, as column expressions.

Bounds run the same operations in the same order as distances, and each is monotone in
floating point, so a lower bound never exceeds a distance it bounds, nor an upper one
falls below it.
"""

from __future__ import annotations

from collections.abc import Sequence
from functools import reduce

from pyspark.sql import Column
from pyspark.sql import functions as F

from density_peaks.schemas import Space

Columns = Sequence[Column]
METRICS = ("euclidean", "manhattan", "chebyshev", "chord", "haversine")
EARTH_KM = 6371.0088


def _norm(gaps: Columns, metric: str) -> Column:
    """gaps: one non-negative or signed difference an axis."""
    if metric in ("euclidean", "chord"):
        return F.sqrt(reduce(lambda a, b: a + b, [g * g for g in gaps]))
    if metric == "manhattan":
        return reduce(lambda a, b: a + b, [F.abs(g) for g in gaps])
    if metric == "chebyshev":
        return F.greatest(*[F.abs(g) for g in gaps]) if len(gaps) > 1 else F.abs(gaps[0])
    raise ValueError(f"no bounds for metric {metric}; known: {METRICS}")


def dist(a: Columns, b: Columns, space: Space) -> Column:
    """Distance of two points given as lists of coordinates (degrees of longitude, latitude for haversine)."""
    if space.vector:
        return vector_dist(a[0], b[0], space.metric)
    if space.metric == "haversine":
        lon, lat = F.radians(b[0] - a[0]), F.radians(b[1] - a[1])
        h = F.sin(lat / 2) * F.sin(lat / 2) + F.cos(F.radians(a[1])) * F.cos(F.radians(b[1])) * F.sin(lon / 2) * F.sin(lon / 2)
        return F.lit(2 * EARTH_KM) * F.asin(F.least(F.lit(1.0), F.sqrt(h)))
    return _norm([x - y for x, y in zip(a, b, strict=True)], space.metric)


def vector_dist(a: Column, b: Column, metric: str) -> Column:
    """Distance of two arrays; chord is the euclidean distance of vectors of unit length."""
    zero = F.lit(0.0)
    if metric in ("euclidean", "chord"):
        return F.sqrt(F.aggregate(F.zip_with(a, b, lambda x, y: (x - y) * (x - y)), zero, lambda s, v: s + v))
    if metric == "manhattan":
        return F.aggregate(F.zip_with(a, b, lambda x, y: F.abs(x - y)), zero, lambda s, v: s + v)
    if metric == "chebyshev":
        return F.array_max(F.zip_with(a, b, lambda x, y: F.abs(x - y)))
    raise ValueError(f"no vector metric {metric}")


def d_min(p: Columns, lo: Columns, hi: Columns, space: Space) -> Column:
    """Least distance of a point to a box."""
    return _norm([F.greatest(a - x, x - b, F.lit(0.0)) for x, a, b in zip(p, lo, hi, strict=True)], space.metric)


def d_max(p: Columns, lo: Columns, hi: Columns, space: Space) -> Column:
    """Largest distance of a point to a box."""
    return _norm([F.greatest(F.abs(x - a), F.abs(x - b)) for x, a, b in zip(p, lo, hi, strict=True)], space.metric)


def box_min(lo1: Columns, hi1: Columns, lo2: Columns, hi2: Columns, space: Space) -> Column:
    """Least distance between two boxes."""
    return _norm([F.greatest(c - b, a - d, F.lit(0.0)) for a, b, c, d in zip(lo1, hi1, lo2, hi2, strict=True)], space.metric)


def box_max(lo1: Columns, hi1: Columns, lo2: Columns, hi2: Columns, space: Space) -> Column:
    """Largest distance between two boxes."""
    return _norm([F.greatest(F.abs(d - a), F.abs(b - c)) for a, b, c, d in zip(lo1, hi1, lo2, hi2, strict=True)], space.metric)
