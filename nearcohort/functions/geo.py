"""Distances, cells and similarity as column expressions."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F

EARTH_KM = 6371.0088


def euclid(x1, y1, x2, y2) -> Column:
    """Planar distance, rounded to 6 decimals so that every engine orders it alike."""
    return F.round(F.sqrt(F.pow(x1 - x2, F.lit(2.0)) + F.pow(y1 - y2, F.lit(2.0))), 6)


def haversine(x1, y1, x2, y2) -> Column:
    """Great-circle kilometres; x is the longitude, y the latitude, in degrees."""
    a = (F.pow(F.sin(F.radians(y2 - y1) / 2), F.lit(2.0))
         + F.cos(F.radians(y1)) * F.cos(F.radians(y2)) * F.pow(F.sin(F.radians(x2 - x1) / 2), F.lit(2.0)))
    return F.round(2 * EARTH_KM * F.asin(F.sqrt(F.least(a, F.lit(1.0)))), 6)


def distance(metric: str) -> Column:
    """Distance of (x, y) from (qx, qy)."""
    f = {"euclid": euclid, "haversine": haversine}[metric]
    return f(F.col("x"), F.col("y"), F.col("qx"), F.col("qy"))


def jaccard(a, b) -> Column:
    """Similarity of two arrays as sets; 1 if both are empty."""
    union = F.size(F.array_union(a, b))
    return F.when(union == 0, F.lit(1.0)).otherwise(F.size(F.array_intersect(a, b)) / union)


def z_cell(x, y, low: float, high: float, bits: int) -> Column:
    """Z-order number of the grid cell of (x, y) on [low, high)^2 with 2^bits cells a side."""
    side = 1 << bits
    at = lambda v: F.least(F.greatest(F.floor((v - low) / (high - low) * side), F.lit(0)), F.lit(side - 1)).cast("long")
    cx, cy = at(x), at(y)
    out = F.lit(0).cast("long")
    for i in range(bits):
        out = out.bitwiseOR(F.shiftleft(F.shiftright(cx, i).bitwiseAND(F.lit(1).cast("long")), 2 * i))
        out = out.bitwiseOR(F.shiftleft(F.shiftright(cy, i).bitwiseAND(F.lit(1).cast("long")), 2 * i + 1))
    return out


def cosine(a, b) -> Column:
    """Cosine similarity of two numeric arrays."""
    dot = lambda p, q: F.aggregate(F.zip_with(p, q, lambda u, v: u.cast("double") * v.cast("double")), F.lit(0.0), lambda s, t: s + t)
    return dot(a, b) / (F.sqrt(dot(a, a)) * F.sqrt(dot(b, b)))
