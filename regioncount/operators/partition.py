"""Partitions other than the square grid: rectangles from cut arrays, Voronoi cells, and their components."""

from __future__ import annotations

import math
from dataclasses import dataclass

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F


@dataclass(frozen=True)
class RectPartition:
    """Cells between sorted inner cuts; half-open. The lattice of indices is that of the square grid."""

    xcuts: tuple[float, ...]
    ycuts: tuple[float, ...]

    def column(self, x: Column) -> Column:
        return _index(x, self.xcuts)

    def row(self, y: Column) -> Column:
        return _index(y, self.ycuts)

    def box_cells(self, bodies: DataFrame) -> DataFrame:
        return bodies.select("body_id", self.row(F.col("ymin")).alias("r0"), self.row(F.col("ymax")).alias("r1"), self.column(F.col("xmin")).alias("c0"), self.column(F.col("xmax")).alias("c1"))


def _index(x: Column, cuts: tuple[float, ...]) -> Column:
    """Number of cuts at or below x; an expression of the cuts, which are public and few."""
    return F.aggregate(F.array(*[F.lit(float(c)) for c in cuts]), F.lit(0), lambda a, c: a + (c <= x).cast("int")) if cuts else F.lit(0)


def clip(polygon: list[tuple[float, float]], a: float, b: float, c: float) -> list[tuple[float, float]]:
    """Part of a convex polygon where a x + b y <= c."""
    out = []
    for i, p in enumerate(polygon):
        q = polygon[(i + 1) % len(polygon)]
        sp, sq = a * p[0] + b * p[1] - c, a * q[0] + b * q[1] - c
        if sp <= 0:
            out.append(p)
        if sp * sq < 0:
            t = sp / (sp - sq)
            out.append((p[0] + t * (q[0] - p[0]), p[1] + t * (q[1] - p[1])))
    return out


def voronoi(sites: list[tuple[float, float]], area: float) -> list[list[tuple[float, float]]]:
    """Cells of the sites within [0, area] squared, by half-plane clipping."""
    cells = []
    for i, (x, y) in enumerate(sites):
        cell = [(0.0, 0.0), (area, 0.0), (area, area), (0.0, area)]
        for j, (p, q) in enumerate(sites):
            if i != j and cell:
                cell = clip(cell, 2 * (p - x), 2 * (q - y), p * p + q * q - x * x - y * y)
        cells.append(cell)
    return cells


def polygon_area(polygon: list[tuple[float, float]]) -> float:
    return abs(sum(p[0] * q[1] - q[0] * p[1] for p, q in zip(polygon, polygon[1:] + polygon[:1], strict=True))) / 2


def components(cells: list[list[tuple[float, float]]], digits: int = 9) -> list[tuple[int, str, list[tuple[float, float]], list[int]]]:
    """(comp_id, kind, geometry, incident faces): faces, inner edges between two cells, inner vertices of three or more."""
    key = lambda p: (round(p[0], digits), round(p[1], digits))
    out = [(i, "face", c, [i]) for i, c in enumerate(cells)]
    corners: dict[tuple, list[int]] = {}
    for i, c in enumerate(cells):
        for p in {key(p) for p in c}:
            corners.setdefault(p, []).append(i)
    pairs: dict[tuple[int, int], list[tuple]] = {}
    for p, fs in corners.items():
        for a in fs:
            for b in fs:
                if a < b:
                    pairs.setdefault((a, b), []).append(p)
    for (a, b), ends in sorted(pairs.items()):
        if len(ends) == 2:
            out.append((len(out), "edge", ends, [a, b]))
    for p, fs in sorted(corners.items()):
        if len(fs) >= 3:
            out.append((len(out), "vertex", [p], sorted(fs)))
    return out


def complex_table(spark: SparkSession, parts: list[tuple[int, str, list, list[int]]]) -> DataFrame:
    rows = [(i, kind, [(float(x), float(y)) for x, y in g], [int(f) for f in faces], min(x for x, _ in g), max(x for x, _ in g), min(y for _, y in g), max(y for _, y in g)) for i, kind, g, faces in parts]
    return spark.createDataFrame(rows, "comp_id int, kind string, geometry array<struct<x:double,y:double>>, incident array<int>, xmin double, xmax double, ymin double, ymax double")


def convex_meet(a: list[tuple[float, float]], b: list[tuple[float, float]], eps: float = 1e-12) -> bool:
    """Whether two convex sets (polygons, segments or points) meet: no separating axis."""
    for one, other in ((a, b), (b, a)):
        for i, p in enumerate(one):
            q = one[(i + 1) % len(one)]
            for nx, ny in ((p[1] - q[1], q[0] - p[0]), (q[0] - p[0], q[1] - p[1])):
                if nx == ny == 0:
                    continue
                x, y = [nx * s + ny * t for s, t in a], [nx * s + ny * t for s, t in b]
                if max(x) < min(y) - eps or max(y) < min(x) - eps:
                    return False
    if len(a) == len(b) == 1:
        return math.dist(a[0], b[0]) <= eps
    return True


def histogram_general(bodies: DataFrame, complex_: DataFrame, bin_size: float) -> DataFrame:
    """(comp_id, kind, h) for any convex partition. Bodies and components meet on a coarse grid of bins by an equi-join,
    then by their boxes, then by an exact separating-axis test."""

    def binned(df: DataFrame) -> DataFrame:
        at = lambda c: F.floor(F.col(c) / bin_size)
        return df.withColumn("bx", F.explode(F.sequence(at("xmin"), at("xmax")))).withColumn("by", F.explode(F.sequence(at("ymin"), at("ymax"))))

    left = binned(bodies.select("body_id", "hull", "xmin", "xmax", "ymin", "ymax"))
    right = binned(complex_.select("comp_id", "geometry", *[F.col(c).alias(c) for c in ("xmin", "xmax", "ymin", "ymax")])).select("bx", "by", "comp_id", "geometry", *[F.col(c).alias("g" + c) for c in ("xmin", "xmax", "ymin", "ymax")])
    near = left.join(right, ["bx", "by"]).filter((F.col("xmin") <= F.col("gxmax")) & (F.col("gxmin") <= F.col("xmax")) & (F.col("ymin") <= F.col("gymax")) & (F.col("gymin") <= F.col("ymax")))
    near = near.dropDuplicates(["body_id", "comp_id"])

    @F.pandas_udf("boolean")
    def meet(hull: pd.Series, geometry: pd.Series) -> pd.Series:
        pts = lambda g: [(p["x"], p["y"]) for p in g]
        return pd.Series(np.array([convex_meet(pts(a), pts(b)) for a, b in zip(hull, geometry, strict=True)], dtype=bool))

    hit = near.filter(meet("hull", "geometry")).groupBy("comp_id").agg(F.count(F.lit(1)).alias("h"))
    return complex_.select("comp_id", "kind").join(hit, "comp_id", "left").select("comp_id", "kind", F.coalesce("h", F.lit(0)).alias("h"))


def count_general(hist: DataFrame, complex_: DataFrame, faces: list[int]) -> DataFrame:
    """(est): signed sum over the components whose incident faces are all in `faces`, a convex union of cells."""
    wanted = F.array(*[F.lit(int(f)) for f in faces])
    used = complex_.filter(F.size(F.array_except("incident", wanted)) == 0).select("comp_id")
    sign = F.when(F.col("kind") == "edge", -1).otherwise(1)
    return hist.join(used, "comp_id").agg(F.sum(sign * F.col("h")).alias("est"))
