"""What the release is compared with."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from regioncount.functions import fn
from regioncount.operators import answer, release
from regioncount.operators.schemas import GridSpec


def _faces_only(hist: DataFrame) -> DataFrame:
    """Edges and vertices set to 0: the signed sum is then the sum of the cells."""
    return hist.withColumn("h", F.when(F.col("kind") == "face", F.col("h")).otherwise(F.col("h") * 0))


def cell_sum(hist: DataFrame, queries: DataFrame, keys: list[str] | None = None) -> DataFrame:
    """Cell counts of bodies, added up: a body counts once in each cell it meets."""
    return answer.by_prefix(answer.prefix(_faces_only(hist), keys), queries, keys)


def cell_sum_private(hist: DataFrame, queries: DataFrame, spec: GridSpec, body: float, epsilon: float, seed: str = "cells", reps: int | None = None) -> DataFrame:
    delta_f = release.sensitivity(spec, body, "add_remove", "cells")
    noisy = release.perturb(hist, epsilon, delta_f, seed=seed, reps=reps)
    return cell_sum(noisy, queries, ["rep"] if reps else None)


def point_histogram(bodies: DataFrame, spec: GridSpec) -> DataFrame:
    """One representative point per body, the centre of its box: (u, v, kind, h) with counts in the faces."""
    from regioncount.operators.euler import _dense

    at = lambda a, b: 2 * fn.cell_index((F.col(a) + F.col(b)) / 2, spec.d, spec.n)
    counts = bodies.groupBy(at("ymin", "ymax").alias("u"), at("xmin", "xmax").alias("v")).agg(F.count(F.lit(1)).alias("h"))
    return _dense(counts, spec)


def point_count(bodies: DataFrame, queries: DataFrame, spec: GridSpec) -> DataFrame:
    return answer.by_prefix(answer.prefix(point_histogram(bodies, spec)), queries)


def point_count_private(bodies: DataFrame, queries: DataFrame, spec: GridSpec, epsilon: float, seed: str = "points") -> DataFrame:
    """A body is one point, so the sensitivity is 1."""
    return cell_sum(release.perturb(point_histogram(bodies, spec), epsilon, 1.0, seed=seed), queries)


def interactive(exact_answers: DataFrame, epsilon: float, max_queries: int, seed: str = "interactive") -> DataFrame:
    """Every exact answer with noise of its own and an equal part of the budget; refuses more than max_queries."""
    n = exact_answers.count()
    if n > max_queries:
        raise ValueError(f"{n} queries; the budget was split for {max_queries}")
    u = fn.uniform(F.concat_ws(":", F.lit(seed), F.col("q_id")))
    return exact_answers.withColumn("est", F.col("est") + fn.laplace_from_uniform(u, max_queries / epsilon))
