"""Column expressions: hash uniforms, lattice arithmetic, Laplace draws, and geometry on hull arrays."""

from __future__ import annotations

import math

from pyspark.sql import Column
from pyspark.sql import functions as F

EARTH_KM = 6371.0088


def uniform(key: Column) -> Column:
    """Number in (0, 1) from the first 52 bits of md5; equal in every engine, for tests and reproducible noise."""
    return (F.conv(F.substring(F.md5(key), 1, 13), 16, 10).cast("double") + F.lit(0.5)) / F.lit(2.0**52)


def laplace_from_uniform(u: Column, scale: float | Column) -> Column:
    """Inverse of the Laplace distribution function."""
    x = u - F.lit(0.5)
    scale = scale if isinstance(scale, Column) else F.lit(float(scale))
    return -scale * F.signum(x) * F.log(F.lit(1.0) - F.lit(2.0) * F.abs(x))


def geometric_from_uniforms(u1: Column, u2: Column, scale: float) -> Column:
    """Two-sided geometric draw: the difference of two geometric ones with ratio exp(-1/scale)."""
    log_ratio = F.lit(-1.0 / scale)
    return F.floor(F.log(u1) / log_ratio) - F.floor(F.log(u2) / log_ratio)


def cell_index(x: Column, d: float, n: int) -> Column:
    """Half-open cell of a coordinate, clipped to the area."""
    return F.least(F.greatest(F.floor(x / F.lit(d)), F.lit(0)), F.lit(n - 1)).cast("int")


def lattice_kind(u: Column, v: Column) -> Column:
    return F.when((u % 2 == 0) & (v % 2 == 0), "face").when((u % 2 == 1) & (v % 2 == 1), "vertex").otherwise("edge")


def lattice_sign(u: Column, v: Column) -> Column:
    return F.when((u + v) % 2 == 0, F.lit(1)).otherwise(F.lit(-1))


def haversine_km(lon1: Column, lat1: Column, lon2: Column, lat2: Column) -> Column:
    a = F.pow(F.sin(F.radians(lat2 - lat1) / 2), 2) + F.cos(F.radians(lat1)) * F.cos(F.radians(lat2)) * F.pow(F.sin(F.radians(lon2 - lon1) / 2), 2)
    return F.lit(2 * EARTH_KM) * F.asin(F.sqrt(a))


def project_x(lon: Column, lon0: float, lat0: float) -> Column:
    return F.radians(lon - F.lit(lon0)) * F.lit(EARTH_KM * math.cos(math.radians(lat0)))


def project_y(lat: Column, lat0: float) -> Column:
    return F.radians(lat - F.lit(lat0)) * F.lit(EARTH_KM)


# ---------------------------------------------------------------- hulls: array<struct<x, y>>, counter-clockwise
def _next(hull: Column, i: Column) -> Column:
    return F.get(hull, (i + 1) % F.size(hull))


def _sum(array: Column) -> Column:
    return F.aggregate(array, F.lit(0.0), lambda a, x: a + x)


def hull_area(hull: Column) -> Column:
    return F.abs(_sum(F.transform(hull, lambda p, i: p["x"] * _next(hull, i)["y"] - _next(hull, i)["x"] * p["y"]))) / 2


def hull_perimeter(hull: Column) -> Column:
    return _sum(F.transform(hull, lambda p, i: F.hypot(_next(hull, i)["x"] - p["x"], _next(hull, i)["y"] - p["y"])))


def hull_diameter(hull: Column) -> Column:
    """Largest distance of two corners."""
    return F.array_max(F.transform(hull, lambda p: F.array_max(F.transform(hull, lambda q: F.hypot(p["x"] - q["x"], p["y"] - q["y"])))))


def hull_contains(hull: Column, x: Column, y: Column, tolerance: float = 1e-9) -> Column:
    """Whether no side has the point strictly on its right."""
    return F.forall(F.transform(hull, lambda p, i: (_next(hull, i)["x"] - p["x"]) * (y - p["y"]) - (_next(hull, i)["y"] - p["y"]) * (x - p["x"])), lambda c: c >= -tolerance)


def hull_bbox(hull: Column) -> Column:
    xs, ys = F.transform(hull, lambda p: p["x"]), F.transform(hull, lambda p: p["y"])
    return F.struct(F.array_min(xs).alias("xmin"), F.array_max(xs).alias("xmax"), F.array_min(ys).alias("ymin"), F.array_max(ys).alias("ymax"))


def box_overlaps(axmin, axmax, aymin, aymax, bxmin, bxmax, bymin, bymax) -> Column:
    return (axmin <= bxmax) & (bxmin <= axmax) & (aymin <= bymax) & (bymin <= aymax)
