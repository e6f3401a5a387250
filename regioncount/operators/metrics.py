"""Accuracy, consistency and cost measures."""

from __future__ import annotations

import time
from collections.abc import Callable

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from regioncount.functions.fn import lattice_sign
from regioncount.operators import lattice
from regioncount.operators.schemas import GridSpec


def absolute_error(est: Column, truth: Column) -> Column:
    return F.abs(est - truth)


def relative_error(est: Column, truth: Column, floor: float = 1.0) -> Column:
    """Error over the truth, or over `floor` where the truth is less."""
    return F.abs(est - truth) / F.greatest(truth.cast("double"), F.lit(float(floor)))


def median_relative_error(answers: DataFrame, by: list[str], floor: float = 1.0, approximate: bool = False) -> DataFrame:
    """(by, median_rel, share_true_zero, answers): over all positions and repeats of a group."""
    e = relative_error(F.col("est"), F.col("truth"), floor)
    mid = F.percentile_approx(e, 0.5, 10000) if approximate else F.median(e)
    return answers.groupBy(*by).agg(mid.alias("median_rel"), F.avg((F.col("truth") == 0).cast("double")).alias("share_true_zero"), F.count(F.lit(1)).alias("answers"))


def extra(answers: DataFrame, by: list[str], floor: float = 1.0) -> DataFrame:
    """(by, bias, rmse, p90_rel, share_negative, share_true_zero)."""
    gap, e = F.col("est") - F.col("truth"), relative_error(F.col("est"), F.col("truth"), floor)
    return answers.groupBy(*by).agg(F.avg(gap).alias("bias"), F.sqrt(F.avg(gap * gap)).alias("rmse"), F.percentile(e, 0.9).alias("p90_rel"), F.avg((F.col("est") < -1e-9).cast("double")).alias("share_negative"), F.avg((F.col("truth") == 0).cast("double")).alias("share_true_zero"))


def relative_distance(exact: DataFrame, noisy: DataFrame, other: DataFrame, keys: list[str] | None = None) -> DataFrame:
    """(keys, rel_distance): L1 distance of `other` from the exact counts, in percent of the noisy counts' distance."""
    keys = keys or []
    d = exact.select("u", "v", F.col("h").alias("x")).join(noisy.select(*keys, "u", "v", F.col("h").alias("y")), ["u", "v"]).join(other.select(*keys, "u", "v", F.col("h").alias("z")), [*keys, "u", "v"])
    return d.groupBy(*keys).agg((100.0 * F.sum(F.abs(F.col("z") - F.col("x"))) / F.sum(F.abs(F.col("y") - F.col("x")))).alias("rel_distance"))


def violations(hist: DataFrame, spec: GridSpec, keys: list[str] | None = None, tolerance: float = 0.0) -> DataFrame:
    """(keys, cls, members, violated, pct) of the constraint classes."""
    keys = keys or []
    cons = lattice.constraints(hist.sparkSession, spec)
    # constraints are as many as the public lattice has counts, times three: broadcast for small lattices only
    side = F.broadcast if spec.n <= 100 else (lambda df: df)
    pairs = side(cons.filter("cls <> 'C3'"))
    low = hist.select(*keys, F.col("u").alias("lo_u"), F.col("v").alias("lo_v"), F.col("h").alias("lo"))
    high = hist.select(*keys, F.col("u").alias("hi_u"), F.col("v").alias("hi_v"), F.col("h").alias("hi"))
    order = low.join(pairs, ["lo_u", "lo_v"]).join(high, [*keys, "hi_u", "hi_v"]).select(*keys, "cls", (F.col("lo") - F.col("hi") > tolerance).cast("long").alias("bad"))
    steps = F.array(*[F.struct(F.lit(a).alias("a"), F.lit(b).alias("b")) for a in (-1, 0, 1) for b in (-1, 0, 1)])
    block = side(cons.filter("cls = 'C3'").select("lo_u", "lo_v", F.inline(steps)).select("lo_u", "lo_v", (F.col("lo_u") + F.col("a")).alias("u"), (F.col("lo_v") + F.col("b")).alias("v")))
    sums = hist.join(block, ["u", "v"]).groupBy(*keys, "lo_u", "lo_v").agg(F.sum(lattice_sign(F.col("u"), F.col("v")) * F.col("h")).alias("s"))
    third = sums.select(*keys, F.lit("C3").alias("cls"), (F.col("s") < -max(tolerance, 1e-9)).cast("long").alias("bad"))
    both = order.union(third)
    return both.groupBy(*keys, "cls").agg(F.count(F.lit(1)).alias("members"), F.sum("bad").alias("violated")).withColumn("pct", 100.0 * F.col("violated") / F.col("members"))


def properties(hist: DataFrame, spec: GridSpec, keys: list[str] | None = None) -> DataFrame:
    """(keys, integers, non_negative, consistent): the flags of a release; answers are checked apart."""
    keys = keys or []
    h = F.col("h").cast("double")
    flags = hist.groupBy(*keys).agg((F.max(F.abs(h - F.round(h))) == 0).alias("integers"), (F.min(h) >= 0).alias("non_negative"))
    broken = violations(hist, spec, keys, 1e-9).groupBy(*keys).agg((F.sum("violated") == 0).alias("consistent"))
    return flags.join(broken, keys) if keys else flags.crossJoin(broken)


def density(hist: DataFrame) -> DataFrame:
    """(r, c, bodies) of the cells."""
    return hist.filter("kind = 'face'").select(F.expr("u div 2").cast("int").alias("r"), F.expr("v div 2").cast("int").alias("c"), F.col("h").alias("bodies"))


def timed(stage: Callable[[], DataFrame]) -> float:
    """Seconds to compute a frame in full, without keeping it."""
    began = time.perf_counter()
    stage().write.format("noop").mode("overwrite").save()
    return time.perf_counter() - began
