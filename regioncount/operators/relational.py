"""Operators that Spark has no single call for: as-of, interval and tile-bucketed range joins, salted top-k."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F


def asof_join(left: DataFrame, right: DataFrame, by: str, at: str, values: list[str], order: list[str]) -> DataFrame:
    """Each left row with the values of the last right row of its key at or before its time.

    One union and one window, no inequality join. `order` breaks ties among right rows of one time; a right row at
    the same time counts as before.
    """
    l = left.withColumn("__side", F.lit(1)).withColumn("__v", F.lit(None).cast(_struct_type(right, values)))
    keep = [c for c in left.columns if c not in (by, at)]
    r = right.select(by, at, *[F.col(c).alias("__" + c) for c in order], F.struct(*values).alias("__v"), F.lit(0).alias("__side"))
    both = l.unionByName(r, allowMissingColumns=True)
    w = Window.partitionBy(by).orderBy(at, "__side", *["__" + c for c in order]).rowsBetween(Window.unboundedPreceding, 0)
    out = both.withColumn("__last", F.last("__v", ignorenulls=True).over(w)).filter("__side = 1")
    return out.select(by, at, *keep, *[F.col("__last")[c].alias(f"last_{c}") for c in values])


def _struct_type(df: DataFrame, names: list[str]) -> str:
    return "struct<" + ",".join(f"{c}:{df.schema[c].dataType.simpleString()}" for c in names) + ">"


def range_join(points: DataFrame, rects: DataFrame, tile: float) -> DataFrame:
    """(q_id, point columns): points in rectangles (x0, x1, y0, y1), by an equi-join on tiles and a residual test."""
    at = lambda c: F.floor(F.col(c) / tile)
    r = rects.withColumn("tx", F.explode(F.sequence(at("x0"), at("x1")))).withColumn("ty", F.explode(F.sequence(at("y0"), at("y1"))))
    p = points.withColumn("tx", at("x")).withColumn("ty", at("y"))
    inside = (F.col("x") >= F.col("x0")) & (F.col("x") <= F.col("x1")) & (F.col("y") >= F.col("y0")) & (F.col("y") <= F.col("y1"))
    return p.join(r, ["tx", "ty"]).filter(inside).drop("tx", "ty", "x0", "x1", "y0", "y1")


def interval_join(events: DataFrame, spans: DataFrame, by: str, at: str, width_s: int) -> DataFrame:
    """Events within spans (start, end] of their key, bucketed by time so that a busy key is spread."""
    bucket = lambda c: F.floor(F.unix_seconds(F.col(c)) / width_s)
    s = spans.withColumn("__b", F.explode(F.sequence(bucket("start"), bucket("end"))))
    e = events.withColumn("__b", bucket(at))
    return e.join(s, [by, "__b"]).filter((F.col(at) > F.col("start")) & (F.col(at) <= F.col("end"))).drop("__b")


def top_k(df: DataFrame, by: list[str], order: list, k: int, salts: int = 16) -> DataFrame:
    """First k rows of each group: k per salt first, so that a hot group is spread, then k of those."""
    salted = df.withColumn("__salt", F.pmod(F.xxhash64(*df.columns), F.lit(salts)))
    first = salted.withColumn("__rn", F.row_number().over(Window.partitionBy(*by, "__salt").orderBy(*order))).filter(F.col("__rn") <= k)
    w = Window.partitionBy(*by).orderBy(*order)
    return first.drop("__rn", "__salt").withColumn("rank", F.row_number().over(w)).filter(F.col("rank") <= k)
