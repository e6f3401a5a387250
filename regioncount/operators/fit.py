"""Constrained inference: the nearest consistent histogram, by L1, max norm or L2, and cheap repairs.

The constraints order the lattice: vertex <= edge <= face, so fitting is isotonic regression on an order of height 3.
`keys` are the columns that tell releases and repeats apart; all of them are fitted in one job.
"""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from regioncount.operators import fit_exact, fit_iterative
from regioncount.operators.schemas import GridSpec


def _neighbours(hist: DataFrame, keys: list[str]) -> DataFrame:
    """Add the neighbours along a row (w, e) and a column (n, s); null outside."""
    row, column = Window.partitionBy(*keys, "u").orderBy("v"), Window.partitionBy(*keys, "v").orderBy("u")
    df = hist.withColumn("w", F.lag("h").over(row)).withColumn("e", F.lead("h").over(row))
    df = df.withColumn("rmax", F.greatest("h", "w", "e")).withColumn("rmin", F.least("h", "w", "e"))
    for name, c in (("n", "h"), ("nmax", "rmax"), ("nmin", "rmin")):
        df = df.withColumn(name, F.lag(c).over(column))
    for name, c in (("s", "h"), ("smax", "rmax"), ("smin", "rmin")):
        df = df.withColumn(name, F.lead(c).over(column))
    return df


def linf(hist: DataFrame, keys: list[str] | None = None) -> DataFrame:
    """Max-norm fit in closed form: half of the largest noisy value at or below a node and the least at or above it.

    Below a face are its edges and vertices, above a vertex its edges and faces: three-by-three stencils by two
    windows. The result is monotone, and its largest change is half of the largest violation, the least possible.
    """
    keys = keys or []
    df = _neighbours(hist, keys)
    face = (F.greatest("rmax", "nmax", "smax") + F.col("h")) / 2
    vertex = (F.col("h") + F.least("rmin", "nmin", "smin")) / 2
    flat = (F.greatest("h", "n", "s") + F.least("h", "w", "e")) / 2  # faces west and east, end vertices north and south
    upright = (F.greatest("h", "w", "e") + F.least("h", "n", "s")) / 2
    x = F.when(F.col("kind") == "face", face).when(F.col("kind") == "vertex", vertex).when(F.col("u") % 2 == 0, flat).otherwise(upright)
    return df.select(*keys, "u", "v", "kind", F.greatest(x, F.lit(0.0)).alias("h"))


def clip_down(hist: DataFrame, keys: list[str] | None = None) -> DataFrame:
    """One pass of repair: edges down to their faces, then vertices down to their edges. Feasible, not the nearest."""
    keys = keys or []
    columns = [*keys, "u", "v", "kind"]
    df = _neighbours(hist, keys)
    edge = F.when(F.col("u") % 2 == 0, F.least("h", "w", "e")).otherwise(F.least("h", "n", "s"))
    df = df.select(*columns, F.greatest(F.when(F.col("kind") == "edge", edge).otherwise(F.col("h")), F.lit(0.0)).alias("h"))
    df = _neighbours(df, keys)
    return df.select(*columns, F.when(F.col("kind") == "vertex", F.least("h", "w", "e", "n", "s")).otherwise(F.col("h")).alias("h"))


def _on_lattice(hist: DataFrame, spec: GridSpec, keys: list[str] | None, solve) -> DataFrame:
    """Run a numpy solver on each release's dense lattice; all releases and repeats in parallel."""
    keys = keys or []
    side = spec.side
    group = keys or ["__one"]
    df = hist if keys else hist.withColumn("__one", F.lit(0))
    schema = ", ".join([*(f"{c} {hist.schema[c].dataType.simpleString()}" for c in keys), "u int, v int, kind string, h double"])

    def run(p: pd.DataFrame) -> pd.DataFrame:
        y = np.zeros((side, side))
        y[p.u.to_numpy(), p.v.to_numpy()] = p.h.to_numpy()
        x = solve(y)
        p = p.assign(h=x[p.u.to_numpy(), p.v.to_numpy()].astype(float))
        return p[[*keys, "u", "v", "kind", "h"]]

    return df.select(*group, "u", "v", "kind", F.col("h").cast("double").alias("h")).groupBy(*group).applyInPandas(run, schema)


def l1(hist: DataFrame, spec: GridSpec, keys: list[str] | None = None, solver: str = "auto", classes=("C1", "C2", "C3"), prior: float | None = None, weight: float = 0.0, steps: int = 2000) -> DataFrame:
    """Least-absolute-deviation fit, the likeliest histogram under Laplace noise.

    `exact`: bipartite matchings on split values. `iterative`: a saddle-point iteration ended by a repair.
    `auto`: exact up to 100 cells a side. A prior value with a weight is one more observation of every count
    (iterative). C3 follows from the other classes; alone or without them it needs the iterative solver.
    """
    if solver == "auto":
        solver = "exact" if spec.n <= 100 and weight == 0 and {"C1", "C2"} <= set(classes) else "iterative"
    if solver == "exact":
        return _on_lattice(hist, spec, keys, fit_exact.l1)
    if solver == "iterative":
        return _on_lattice(hist, spec, keys, lambda y: fit_iterative.l1(y, steps=steps, classes=classes, prior=prior, weight=weight)[0])
    raise ValueError(f"unknown solver {solver!r}")


def l2(hist: DataFrame, spec: GridSpec, keys: list[str] | None = None, tolerance: float = 1e-7) -> DataFrame:
    """Least-squares fit by cyclic projections with corrections, up to a change of `tolerance`."""
    return _on_lattice(hist, spec, keys, lambda y: fit_iterative.l2(y, tolerance=tolerance))


def certificate(noisy: DataFrame, fitted: DataFrame, spec: GridSpec, keys: list[str] | None = None, steps: int = 3000) -> DataFrame:
    """(keys, violations, objective, dual_bound, gap) of an L1 fit: no feasible histogram is nearer than dual_bound."""
    keys = keys or []
    side = spec.side
    both = noisy.select(*keys, "u", "v", F.col("h").cast("double").alias("y")).join(fitted.select(*keys, "u", "v", F.col("h").cast("double").alias("x")), [*keys, "u", "v"])
    group = keys or ["__one"]
    both = both if keys else both.withColumn("__one", F.lit(0))
    schema = ", ".join([*(f"{c} {noisy.schema[c].dataType.simpleString()}" for c in keys), "violations long, objective double, dual_bound double, gap double"])

    def run(p: pd.DataFrame) -> pd.DataFrame:
        y, x = np.zeros((side, side)), np.zeros((side, side))
        y[p.u.to_numpy(), p.v.to_numpy()], x[p.u.to_numpy(), p.v.to_numpy()] = p.y.to_numpy(), p.x.to_numpy()
        objective, bound = float(np.abs(x - y).sum()), fit_iterative.l1(y, steps=steps)[1]
        out = {c: [p[c].iloc[0]] for c in keys}
        return pd.DataFrame(out | {"violations": [int(fit_iterative.violations(x, 1e-9))], "objective": [objective], "dual_bound": [bound], "gap": [(objective - bound) / max(1.0, objective)]})

    return both.groupBy(*group).applyInPandas(run, schema)


def program(hist: DataFrame, constraints: DataFrame, norm: str = "l1") -> DataFrame:
    """(constraint, var, coef, rhs): the linear program of a fit, every row meaning sum(coef * var) <= rhs.

    L1 has a slack for each count, the max norm one slack for all.
    """
    x = lambda u, v: F.concat(F.lit("x:"), u, F.lit(":"), v)
    node = x(F.col("u"), F.col("v"))
    slack = F.concat(F.lit("s:"), F.col("u"), F.lit(":"), F.col("v")) if norm == "l1" else F.lit("s")
    terms = lambda *pairs: F.array(*[F.struct(var.alias("var"), F.lit(float(c)).alias("coef")) for var, c in pairs])
    over = hist.select(F.concat(F.lit("over:"), node).alias("constraint"), F.inline(terms((node, 1), (slack, -1))), F.col("h").cast("double").alias("rhs"))
    under = hist.select(F.concat(F.lit("under:"), node).alias("constraint"), F.inline(terms((node, -1), (slack, -1))), (-F.col("h")).cast("double").alias("rhs"))
    sign = hist.select(F.concat(F.lit("sign:"), node).alias("constraint"), F.inline(terms((node, -1))), F.lit(0.0).alias("rhs"))
    name = F.concat_ws(":", "cls", "lo_u", "lo_v", "hi_u", "hi_v")
    order = constraints.filter("cls <> 'C3'").select(name.alias("constraint"), F.inline(terms((x(F.col("lo_u"), F.col("lo_v")), 1), (x(F.col("hi_u"), F.col("hi_v")), -1))), F.lit(0.0).alias("rhs"))
    steps = F.array(*[F.struct(F.lit(a).alias("a"), F.lit(b).alias("b")) for a in (-1, 0, 1) for b in (-1, 0, 1)])
    block = constraints.filter("cls = 'C3'").select(name.alias("constraint"), "lo_u", "lo_v", F.inline(steps))
    block = block.select("constraint", x(F.col("lo_u") + F.col("a"), F.col("lo_v") + F.col("b")).alias("var"), F.when((F.col("a") + F.col("b")) % 2 == 0, -1.0).otherwise(1.0).alias("coef"), F.lit(0.0).alias("rhs"))
    return over.unionByName(under).unionByName(sign).unionByName(order).unionByName(block)
