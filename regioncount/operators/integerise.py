"""Rounding of fitted counts, and the check that a release looks like a true histogram."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from regioncount.operators import answer, metrics
from regioncount.operators.schemas import GridSpec


def round_counts(hist: DataFrame, mode: str = "half_up") -> DataFrame:
    """Nearest integers. Rounding is monotone, so order constraints stay; each count moves by at most a half."""
    f = {"half_up": F.round, "half_even": F.bround}[mode]
    return hist.withColumn("h", f(F.col("h").cast("double")).cast("long"))


def check_covert(hist: DataFrame, spec: GridSpec, queries: DataFrame, keys: list[str] | None = None) -> DataFrame:
    """(keys, integer, non_negative, violated, negative_answers): share of the rectangle answers below 0."""
    keys = keys or []
    h = F.col("h").cast("double")
    shape = hist.groupBy(*keys).agg(F.min((h == F.round(h)).cast("int")).cast("boolean").alias("integer"), (F.min(h) >= 0).alias("non_negative"))
    broken = metrics.violations(hist, spec, keys).groupBy(*keys).agg(F.sum("violated").alias("violated"))
    below = answer.by_prefix(answer.prefix(hist, keys), queries, keys).groupBy(*keys).agg(F.round(F.avg((F.col("est") < -1e-9).cast("double")), 6).alias("negative_answers"))
    if keys:
        return shape.join(broken, keys).join(below, keys)
    return shape.crossJoin(broken).crossJoin(below)
