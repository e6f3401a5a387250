"""Bounds on single counts, and how often measured noise keeps to them."""

from __future__ import annotations

import math

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from regioncount.operators.release import tail
from regioncount.operators.schemas import GridSpec

ROUNDING = 0.5


def noise_bound(scale: float, counts: int, delta: float) -> float:
    """No noisy count is further from the exact one, but with probability delta."""
    return tail(scale, delta, counts)


def fit_bound(scale: float, counts: int, delta: float) -> float:
    """The same for the distance of a max-norm fit from the noisy counts: the exact histogram is feasible."""
    return tail(scale, delta, counts)


def total_bound(area: float, d: float, body: float, epsilon: float, delta: float) -> float:
    """Noise, fit and rounding together, with the looser form of the sensitivity."""
    k = math.ceil(round(body / d, 9))
    side = area / d
    return 9 * k * (k + 1) / epsilon * math.log((4 * side * side - 4 * side + 1) / delta) + ROUNDING


def coverage(exact: DataFrame, noisy: DataFrame, spec: GridSpec, scale: float, deltas: list[float], keys: list[str]) -> DataFrame:
    """(delta, bound, repeats, within): share of the repeats whose largest change is within the bound."""
    worst = exact.select("u", "v", F.col("h").alias("x")).join(noisy, ["u", "v"]).groupBy(*keys).agg(F.max(F.abs(F.col("h") - F.col("x"))).alias("worst"))
    table = worst.sparkSession.createDataFrame([(d, noise_bound(scale, spec.counts, d)) for d in deltas], "delta double, bound double")
    return worst.crossJoin(F.broadcast(table)).groupBy("delta", "bound").agg(F.count(F.lit(1)).alias("repeats"), F.avg((F.col("worst") <= F.col("bound")).cast("double")).alias("within"))
