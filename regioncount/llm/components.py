"""Connected components of an edge table, distributed: alternating large-star and small-star steps.

Each step points nodes at smaller neighbours; when no edge changes every node points at the least node of its
component. A step is a combined minimum and a join with it; the join is salted, so that a node with very many edges is
dealt to several tasks and is never gathered in one. Every round is written to the shared folder.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from regioncount.llm.common import Scratch, spread_join


def _large_star(edges: DataFrame) -> DataFrame:
    """Larger neighbours of every node go to the least of it and its neighbours."""
    both = edges.select("a", "b").union(edges.select(F.col("b").alias("a"), F.col("a").alias("b")))
    joined = spread_join(both.filter("b > a"), both.groupBy("a").agg(F.min("b").alias("m")), "a", "b")
    return joined.select(F.col("b").alias("a"), F.least("a", "m").alias("b")).filter("a > b").distinct()


def _small_star(edges: DataFrame) -> DataFrame:
    """Edges point from a to a smaller b: a and its neighbours go to the least of them."""
    joined = spread_join(edges, edges.groupBy("a").agg(F.min("b").alias("m")), "a", "b")
    out = joined.select(F.col("b").alias("a"), F.col("m").alias("b")).union(joined.select("a", F.col("m").alias("b")))
    return out.filter("a > b").distinct()


def components(edges: DataFrame, scratch: Scratch) -> DataFrame:
    """(a, b): every node a of an edge that is not the least of its component, and that least node b."""
    now = scratch.save(edges.select(F.greatest("a", "b").alias("a"), F.least("a", "b").alias("b")).filter("a > b").distinct(), "edges")
    print_of = lambda df: tuple(df.agg(F.count(F.lit(1)), F.sum(F.xxhash64("a", "b").cast("decimal(38,0)"))).first())
    before = print_of(now)
    while before[0]:
        after = scratch.save(_small_star(_large_star(now)), "edges")
        scratch.drop(now)
        now, state = after, print_of(after)
        if state == before:
            break
        before = state
    return now
