"""The dense lattice of faces, edges and vertices, and its order constraints."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from regioncount.functions.fn import lattice_kind
from regioncount.operators.schemas import GridSpec


def cells(spark: SparkSession, spec: GridSpec) -> DataFrame:
    """(u, v, kind) of all counts."""
    at = spark.range(spec.counts)
    u, v = F.floor(F.col("id") / spec.side).cast("int"), (F.col("id") % spec.side).cast("int")
    return at.select(u.alias("u"), v.alias("v")).withColumn("kind", lattice_kind(F.col("u"), F.col("v")))


def constraints(spark: SparkSession, spec: GridSpec, classes=("C1", "C2", "C3")) -> DataFrame:
    """(cls, lo_u, lo_v, hi_u, hi_v): lower node at most the upper one; C3 names the vertex of a two-by-two block.

    C1: an edge and a face beside it. C2: a vertex and an edge at it. C3: the block's signed sum is not negative.
    """
    c, top = cells(spark, spec), spec.side - 1
    u, v = F.col("u"), F.col("v")
    steps = F.array(*[F.struct(F.lit(a).alias("du"), F.lit(b).alias("dv")) for a, b in ((0, -1), (0, 1), (-1, 0), (1, 0))])
    near = c.withColumn("s", F.explode(steps)).withColumn("hi_u", u + F.col("s.du")).withColumn("hi_v", v + F.col("s.dv"))
    near = near.filter(F.col("hi_u").between(0, top) & F.col("hi_v").between(0, top))
    upper_face = (F.col("hi_u") % 2 == 0) & (F.col("hi_v") % 2 == 0)
    out = {
        "C1": near.filter((F.col("kind") == "edge") & upper_face),
        "C2": near.filter(F.col("kind") == "vertex"),
        "C3": c.filter("kind = 'vertex'").withColumn("hi_u", u).withColumn("hi_v", v),
    }
    found = None
    for name in classes:
        part = out[name].select(F.lit(name).alias("cls"), u.alias("lo_u"), v.alias("lo_v"), "hi_u", "hi_v")
        found = part if found is None else found.union(part)
    return found
