"""Points of a user to one convex body of bounded diameter: mode, nearest points, trimming, hull or box."""

from __future__ import annotations

import math

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from regioncount.functions import fn
from regioncount.operators.schemas import BODIES

#: Points of a user above which a density is estimated on bins.
HEAVY = 5000


def project_points(points: DataFrame, lon0: float, lat0: float) -> DataFrame:
    """lon, lat to kilometres in a local plane (equirectangular)."""
    return points.withColumn("x", fn.project_x(F.col("lon"), lon0, lat0)).withColumn("y", fn.project_y(F.col("lat"), lat0))


def density_mode(points: DataFrame, method: str = "median", bandwidth: float | None = None, bin_size: float = 0.125) -> DataFrame:
    """(user_id, mode_x, mode_y).

    `kde`: the own point of highest Gaussian density, bandwidth sigma * m^(-1/6) per axis unless given, smallest
    point_id among ties; a user's points meet in one task, so this is for users of bounded size. `kde_sql`: the same
    by a self join, for checks. `binned`: densities of bins by the same kernel, from counts that are combined before
    the shuffle, for users of any size. `bin`, `mean`, `medoid`, `median`: cheaper stand-ins.
    """
    if method == "kde":
        return points.select("user_id", "point_id", "x", "y").groupBy("user_id").applyInPandas(lambda p: _kde(p, bandwidth), "user_id long, mode_x double, mode_y double")
    if method == "kde_sql":
        return _kde_join(points, bandwidth)
    if method == "binned":
        return _kde_binned(points, bin_size)
    if method == "bin":
        b = points.groupBy("user_id", F.floor(F.col("x") / bin_size).alias("bx"), F.floor(F.col("y") / bin_size).alias("by")).agg(F.count(F.lit(1)).alias("c"))
        best = b.groupBy("user_id").agg(F.max_by(F.struct("bx", "by"), F.struct("c", -F.col("bx"), -F.col("by"))).alias("b"))
        return best.select("user_id", ((F.col("b.bx") + 0.5) * bin_size).alias("mode_x"), ((F.col("b.by") + 0.5) * bin_size).alias("mode_y"))
    if method == "mean":
        return points.groupBy("user_id").agg(F.avg("x").alias("mode_x"), F.avg("y").alias("mode_y"))
    if method == "medoid":
        p = points.select("user_id", "point_id", "x", "y")
        q = points.select("user_id", F.col("x").alias("qx"), F.col("y").alias("qy"))
        total = p.join(q, "user_id").groupBy("user_id", "point_id", "x", "y").agg(F.round(F.sum(F.hypot(F.col("x") - F.col("qx"), F.col("y") - F.col("qy"))), 9).alias("t"))
        best = total.groupBy("user_id").agg(F.min_by(F.struct("x", "y"), F.struct("t", "point_id", "x", "y")).alias("b"))
        return best.select("user_id", F.col("b.x").alias("mode_x"), F.col("b.y").alias("mode_y"))
    if method == "median":
        return points.groupBy("user_id").agg(F.median("x").alias("mode_x"), F.median("y").alias("mode_y"))
    raise ValueError(f"unknown method {method!r}")


def _kde(p: pd.DataFrame, bandwidth: float | None) -> pd.DataFrame:
    p = p.sort_values(["point_id", "x", "y"])
    x, y, m = p.x.to_numpy(), p.y.to_numpy(), len(p)
    hx, hy = (bandwidth or s * m ** (-1 / 6) or 1.0 for s in (x.std(), y.std()))
    best, at = -1.0, 0
    for a in range(0, m, 512):  # rows of the distance table in blocks
        dens = np.exp(-0.5 * (((x[a : a + 512, None] - x) / hx) ** 2 + ((y[a : a + 512, None] - y) / hy) ** 2)).sum(axis=1).round(9)
        k = int(dens.argmax())
        if dens[k] > best:
            best, at = float(dens[k]), a + k
    return pd.DataFrame({"user_id": [p.user_id.iloc[0]], "mode_x": [x[at]], "mode_y": [y[at]]})


def _kde_join(points: DataFrame, bandwidth: float | None) -> DataFrame:
    if bandwidth:
        h = points.groupBy("user_id").agg(F.lit(bandwidth).alias("hx"), F.lit(bandwidth).alias("hy"))
    else:
        rule = lambda c: F.stddev_pop(c) * F.pow(F.count(F.lit(1)), F.lit(-1 / 6))
        h = points.groupBy("user_id").agg(rule("x").alias("hx"), rule("y").alias("hy"))
        h = h.select("user_id", *[F.when(F.col(c) > 0, F.col(c)).otherwise(1.0).alias(c) for c in ("hx", "hy")])
    p = points.select("user_id", "point_id", "x", "y").join(h, "user_id")
    q = points.select("user_id", F.col("x").alias("qx"), F.col("y").alias("qy"))
    term = F.exp(-0.5 * (F.pow((F.col("x") - F.col("qx")) / F.col("hx"), 2) + F.pow((F.col("y") - F.col("qy")) / F.col("hy"), 2)))
    dens = p.join(q, "user_id").groupBy("user_id", "point_id", "x", "y").agg(F.round(F.sum(term), 9).alias("t"))
    best = dens.groupBy("user_id").agg(F.min_by(F.struct("x", "y"), F.struct(-F.col("t"), "point_id", "x", "y")).alias("b"))
    return best.select("user_id", F.col("b.x").alias("mode_x"), F.col("b.y").alias("mode_y"))


def _kde_binned(points: DataFrame, size: float, reach: int = 3) -> DataFrame:
    """Kernel of one bin's width over the bins within `reach`; the centre of the densest occupied bin."""
    b = points.groupBy("user_id", F.floor(F.col("x") / size).alias("bx"), F.floor(F.col("y") / size).alias("by")).agg(F.count(F.lit(1)).alias("c"))
    steps = F.array(*[F.struct(F.lit(i).alias("dx"), F.lit(j).alias("dy"), F.lit(math.exp(-0.5 * (i * i + j * j))).alias("w")) for i in range(-reach, reach + 1) for j in range(-reach, reach + 1)])
    spread = b.select("user_id", "bx", "by", "c", F.inline(steps)).select("user_id", (F.col("bx") + F.col("dx")).alias("bx"), (F.col("by") + F.col("dy")).alias("by"), (F.col("c") * F.col("w")).alias("t"))
    dens = spread.groupBy("user_id", "bx", "by").agg(F.round(F.sum("t"), 9).alias("t")).join(b, ["user_id", "bx", "by"], "left_semi")
    best = dens.groupBy("user_id").agg(F.max_by(F.struct("bx", "by"), F.struct("t", -F.col("bx"), -F.col("by"))).alias("b"))
    return best.select("user_id", ((F.col("b.bx") + 0.5) * size).alias("mode_x"), ((F.col("b.by") + 0.5) * size).alias("mode_y"))


def with_modes(points: DataFrame, modes: DataFrame) -> DataFrame:
    return points.join(modes, "user_id")


def nearest_to_mode(points: DataFrame, modes: DataFrame, k: int | None) -> DataFrame:
    """The k points of each user nearest to the mode (all if fewer, or if k is None); ties by ts, point_id and
    coordinates."""
    df = with_modes(points, modes).withColumn("dist", F.hypot(F.col("x") - F.col("mode_x"), F.col("y") - F.col("mode_y")))
    w = Window.partitionBy("user_id").orderBy(F.round("dist", 9), "ts", "point_id", "x", "y")
    ranked = df.withColumn("rank", F.row_number().over(w))
    return ranked if k is None else ranked.filter(F.col("rank") <= k)


def trim(points: DataFrame, body: float, rule: str = "disc", area: float | None = None) -> DataFrame:
    """Drop outliers of points with modes: `disc` keeps points within B/2 of the mode, `bbox` those in a square of
    diagonal B round it. Points outside the area go too."""
    dx, dy = F.abs(F.col("x") - F.col("mode_x")), F.abs(F.col("y") - F.col("mode_y"))
    if rule == "disc":
        keep = dx * dx + dy * dy <= F.lit(body * body / 4)
    elif rule == "bbox":
        half = F.lit(body / (2 * math.sqrt(2)))
        keep = (dx <= half) & (dy <= half)
    else:
        raise ValueError(f"unknown rule {rule!r}")
    out = points.filter(keep)
    return out if area is None else out.filter((F.col("x") >= 0) & (F.col("x") < area) & (F.col("y") >= 0) & (F.col("y") < area))


def envelope(points: DataFrame) -> DataFrame:
    """Axis-parallel box of each user's points; combined before the shuffle."""
    return points.groupBy(F.col("user_id").alias("body_id")).agg(F.min("x").alias("xmin"), F.max("x").alias("xmax"), F.min("y").alias("ymin"), F.max("y").alias("ymax"), F.count(F.lit(1)).alias("n_points"))


def hull_of(xy: np.ndarray) -> list[tuple[float, float]]:
    """Convex hull, counter-clockwise from the least point; a point or two for degenerate sets."""
    pts = sorted({(float(x), float(y)) for x, y in xy})
    if len(pts) < 3:
        return pts

    def chain(points):
        out: list[tuple[float, float]] = []
        for p in points:
            while len(out) > 1 and (out[-1][0] - out[-2][0]) * (p[1] - out[-2][1]) - (out[-1][1] - out[-2][1]) * (p[0] - out[-2][0]) <= 0:
                out.pop()
            out.append(p)
        return out[:-1]

    return chain(pts) + chain(pts[::-1])


def drop_interior(points: DataFrame) -> DataFrame:
    """Drop points strictly inside the polygon of each user's extremes in 8 directions. None of them is a corner of
    the hull, so heavy users shrink before their points meet in one task; exact."""
    extremes = points.groupBy("user_id").agg(*[F.max_by(F.struct("x", "y"), F.struct(F.col("x") * c + F.col("y") * s, "x", "y")).alias(f"e{k}") for k, (c, s) in enumerate(_DIRECTIONS)])
    df = points.join(extremes, "user_id")
    strictly = F.lit(True)
    for k in range(8):
        a, b = F.col(f"e{k}"), F.col(f"e{(k + 1) % 8}")
        side = (b["x"] - a["x"]) * (F.col("y") - a["y"]) - (b["y"] - a["y"]) * (F.col("x") - a["x"])
        strictly = strictly & ((side > 0) | ((a["x"] == b["x"]) & (a["y"] == b["y"])))
    several = F.lit(False)
    for k in range(1, 8):
        several = several | (F.col("e0.x") != F.col(f"e{k}.x")) | (F.col("e0.y") != F.col(f"e{k}.y"))
    return df.filter(~(strictly & several)).select(points.columns)


_DIRECTIONS = [(round(math.cos(k * math.pi / 4), 12), round(math.sin(k * math.pi / 4), 12)) for k in range(8)]


def convex_hull(points: DataFrame) -> DataFrame:
    """One body per user: hull, box, diameter and number of points."""
    counts = points.groupBy("user_id").agg(F.count(F.lit(1)).alias("n_points"))
    lean = drop_interior(points.select("user_id", "point_id", "x", "y")).join(counts, "user_id")

    def of(p: pd.DataFrame) -> pd.DataFrame:
        hull = hull_of(p[["x", "y"]].to_numpy())
        xs, ys = [x for x, _ in hull], [y for _, y in hull]
        a = np.array(hull)
        diameter = float(np.sqrt(((a[:, None] - a) ** 2).sum(axis=2)).max())
        return pd.DataFrame({"body_id": [p.user_id.iloc[0]], "hull": [[{"x": x, "y": y} for x, y in hull]], "xmin": [min(xs)], "xmax": [max(xs)], "ymin": [min(ys)], "ymax": [max(ys)], "diameter": [diameter], "n_points": [p.n_points.iloc[0]]})

    return lean.groupBy("user_id").applyInPandas(of, BODIES)


def extract_bodies(points: DataFrame, body: float, area: float | None = None, k: int | None = None, mode: str = "median", rule: str = "bbox", shape: str = "box") -> DataFrame:
    """The whole chain: one body per user."""
    modes = density_mode(points, mode)
    kept = nearest_to_mode(points, modes, k) if k else with_modes(points, modes)
    kept = trim(kept, body, rule, area)
    return envelope(kept) if shape == "box" else convex_hull(kept.select("user_id", "point_id", "x", "y"))
