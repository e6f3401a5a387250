"""The exact Euler histogram: every body adds one to each face, edge and vertex it touches.

Counts are additive, so map-side combining leaves at most one row per lattice count and task to shuffle. The
difference forms (runs, corners) also avoid one row per touched count.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from regioncount.operators import footprint, lattice
from regioncount.operators.schemas import GridSpec


def _dense(counts: DataFrame, spec: GridSpec) -> DataFrame:
    """All counts of the lattice, zero where nothing was counted."""
    return lattice.cells(counts.sparkSession, spec).join(counts, ["u", "v"], "left").select("u", "v", "kind", F.coalesce("h", F.lit(0)).cast("long").alias("h"))


def histogram(runs: DataFrame, spec: GridSpec, method: str = "runs") -> DataFrame:
    """(u, v, kind, h) from runs: `explode` counts every touched component, `runs` adds up differences along a row."""
    if method == "explode":
        touched = runs.select("u", F.explode(F.sequence("vlo", "vhi")).alias("v"))
        return _dense(touched.groupBy("u", "v").agg(F.count(F.lit(1)).alias("h")), spec)
    if method != "runs":
        raise ValueError(f"method {method!r}: explode or runs")
    ends = F.array(F.struct(F.col("vlo").alias("v"), F.lit(1).alias("delta")), F.struct((F.col("vhi") + 1).alias("v"), F.lit(-1).alias("delta")))
    deltas = runs.select("u", F.inline(ends)).groupBy("u", "v").agg(F.sum("delta").alias("delta"))
    rows = lattice.cells(runs.sparkSession, spec).join(deltas, ["u", "v"], "left")
    along = Window.partitionBy("u").orderBy("v").rowsBetween(Window.unboundedPreceding, 0)
    return rows.select("u", "v", "kind", F.coalesce(F.sum("delta").over(along), F.lit(0)).cast("long").alias("h"))


def corner_deltas(boxes: DataFrame) -> DataFrame:
    """(u, v, delta): four signed corners of each box's lattice rectangle, added up."""
    r0, r1, c0, c1 = (2 * F.col(c) for c in ("r0", "r1", "c0", "c1"))
    four = F.array(*[F.struct(u.alias("u"), v.alias("v"), F.lit(s).alias("delta")) for u, v, s in ((r0, c0, 1), (r1 + 1, c0, -1), (r0, c1 + 1, -1), (r1 + 1, c1 + 1, 1))])
    return boxes.select(F.inline(four)).groupBy("u", "v").agg(F.sum("delta").alias("delta"))


def integrate(deltas: DataFrame, spec: GridSpec) -> DataFrame:
    rows = lattice.cells(deltas.sparkSession, spec).join(deltas, ["u", "v"], "left")
    along = Window.partitionBy("u").orderBy("v").rowsBetween(Window.unboundedPreceding, 0)
    down = Window.partitionBy("v").orderBy("u").rowsBetween(Window.unboundedPreceding, 0)
    rows = rows.withColumn("s", F.coalesce(F.sum("delta").over(along), F.lit(0)))
    return rows.select("u", "v", "kind", F.sum("s").over(down).cast("long").alias("h"))


def histogram_boxes(bodies: DataFrame, spec: GridSpec, k: int | None = None) -> DataFrame:
    """(u, v, kind, h) of boxes, four rows per body before combining."""
    return integrate(corner_deltas(footprint.box_cells(bodies, spec, k)), spec)


def histogram_hulls(bodies: DataFrame, spec: GridSpec) -> DataFrame:
    return histogram(footprint.runs(bodies, spec), spec)
