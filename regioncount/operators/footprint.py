"""Which lattice counts a convex body touches: one run of columns per lattice row."""

from __future__ import annotations

import math

import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from regioncount.functions.fn import cell_index
from regioncount.operators.schemas import GridSpec


def inside(bodies: DataFrame, spec: GridSpec) -> DataFrame:
    """Bodies that meet the area."""
    a = F.lit(spec.area)
    return bodies.filter((F.col("xmax") >= 0) & (F.col("xmin") < a) & (F.col("ymax") >= 0) & (F.col("ymin") < a))


def box_cells(bodies: DataFrame, spec: GridSpec, k: int | None = None) -> DataFrame:
    """(body_id, r0, r1, c0, c1) of boxes; those over more than k+1 cells on an axis are dropped when k is given."""
    b = inside(bodies, spec).select(
        "body_id", cell_index(F.col("ymin"), spec.d, spec.n).alias("r0"), cell_index(F.col("ymax"), spec.d, spec.n).alias("r1"),
        cell_index(F.col("xmin"), spec.d, spec.n).alias("c0"), cell_index(F.col("xmax"), spec.d, spec.n).alias("c1"),
    )
    return b if k is None else b.filter((F.col("r1") - F.col("r0") <= k) & (F.col("c1") - F.col("c0") <= k))


def box_runs(bodies: DataFrame, spec: GridSpec, k: int | None = None) -> DataFrame:
    """(body_id, u, vlo, vhi) of boxes by index arithmetic."""
    return box_cells(bodies, spec, k).select("body_id", F.explode(F.sequence(2 * F.col("r0"), 2 * F.col("r1"))).alias("u"), (2 * F.col("c0")).alias("vlo"), (2 * F.col("c1")).alias("vhi"))


def hull_runs(hull: list[tuple[float, float]], area: float, n: int) -> list[tuple[int, int, int]]:
    """(u, vlo, vhi) of one convex polygon (also a point or a segment), clipped to the area.

    Even u: the x-extent of the body inside a strip of cells. Odd u: its x-extent on the line between two strips.
    """
    d = area / n
    m = len(hull)
    ymin, ymax = min(y for _, y in hull), max(y for _, y in hull)
    r0, r1 = max(0, math.floor(ymin / d)), min(n - 1, math.floor(ymax / d))
    out = []

    def on_line(y: float) -> list[float]:
        xs = []
        for i in range(m):
            (ax, ay), (bx, by) = hull[i], hull[(i + 1) % m]
            if min(ay, by) <= y <= max(ay, by):
                xs += [ax, bx] if ay == by else [ax + (y - ay) * (bx - ax) / (by - ay)]
        return xs

    def add(u: int, xs: list[float]) -> None:
        if xs:
            lo, hi = math.floor(min(xs) / d), math.floor(max(xs) / d)
            if hi >= 0 and lo < n:
                out.append((u, 2 * max(0, lo), 2 * min(n - 1, hi)))

    for r in range(r0, r1 + 1):
        low, high = r * d, (r + 1) * d
        add(2 * r, [x for x, y in hull if low <= y < high] + on_line(low) + on_line(high))
        if r < r1:
            add(2 * r + 1, on_line(high))
    return out


def runs(bodies: DataFrame, spec: GridSpec) -> DataFrame:
    """(body_id, u, vlo, vhi) of hulls, by Arrow batches."""
    area, n = spec.area, spec.n

    @F.pandas_udf("array<struct<u:int,vlo:int,vhi:int>>")
    def of(hulls: pd.Series) -> pd.Series:
        return hulls.map(lambda h: [{"u": u, "vlo": a, "vhi": b} for u, a, b in hull_runs([(p["x"], p["y"]) for p in h], area, n)])

    return inside(bodies, spec).select("body_id", F.explode(of("hull")).alias("r")).select("body_id", "r.u", "r.vlo", "r.vhi")
