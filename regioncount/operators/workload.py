"""Workloads: rectangles of given shares of the area, all shapes, all positions."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F


def shapes(n: int, pct: float) -> list[tuple[int, int]]:
    """All r by c rectangles whose area is nearest to pct percent of n by n cells."""
    target = pct / 100 * n * n
    sizes = [(abs(r * c - target), r, c) for r in range(1, n + 1) for c in range(1, n + 1)]
    least = min(sizes)[0]
    return [(r, c) for gap, r, c in sizes if gap <= least + 1e-9]


def positions(spark: SparkSession, n: int, wanted: list[tuple[float, int, int]], most: int | None = None) -> DataFrame:
    """(q_id, pct, shape_r, shape_c, r0, r1, c0, c1): all positions of each (pct, r, c); at most about `most` of a
    shape by a hash of the position, for large grids."""
    rows = [(k, float(p), r, c) for k, (p, r, c) in enumerate(wanted)]
    s = spark.createDataFrame(rows, "k int, pct double, shape_r int, shape_c int")
    q = s.withColumn("r0", F.explode(F.sequence(F.lit(0), F.lit(n) - F.col("shape_r")))).withColumn("c0", F.explode(F.sequence(F.lit(0), F.lit(n) - F.col("shape_c"))))
    if most is not None:
        here = (F.lit(n) - F.col("shape_r") + 1) * (F.lit(n) - F.col("shape_c") + 1)
        q = q.filter(F.pmod(F.xxhash64("r0", "c0"), here) < most)
    q = q.withColumn("q_id", (F.col("k").cast("long") * n + F.col("r0")) * n + F.col("c0"))
    return q.select("q_id", "pct", "shape_r", "shape_c", "r0", (F.col("r0") + F.col("shape_r") - 1).alias("r1"), "c0", (F.col("c0") + F.col("shape_c") - 1).alias("c1"))


def sizes(n: int, percents: list[float]) -> list[tuple[float, int, int]]:
    return [(p, r, c) for p in percents for r, c in shapes(n, p)]
