"""Private release of a histogram: sensitivity, Laplace (or geometric) noise, truncation, budget ledger."""

from __future__ import annotations

import math
import os
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from regioncount.functions import fn
from regioncount.operators.schemas import LEDGER, GridSpec

FORMS, ADJACENCY, NOISES = ("tight", "lemma", "unbounded", "cells"), ("add_remove", "replace"), ("laplace", "geometric")


def sensitivity(spec: GridSpec, body: float, adjacency: str, form: str = "tight") -> float:
    """Largest L1 change of the counts when one body comes or goes (`add_remove`) or is replaced (`replace`: twice).

    `tight`: all counts of a (k+1) by (k+1) block of cells. `lemma`: the looser printed bound. `unbounded`: no limit
    on the body, so every count. `cells`: cell counts alone.
    """
    if adjacency not in ADJACENCY:
        raise ValueError(f"adjacency is one of {ADJACENCY}")
    k = spec.span(body)
    value = {"tight": 4 * k * (k + 1) + 1, "lemma": 4.5 * k * (k + 1), "unbounded": spec.counts, "cells": (k + 1) ** 2}[form]
    return float(value * (2 if adjacency == "replace" else 1))


def perturb(hist: DataFrame, epsilon: float, delta_f: float, seed: str = "0", source: str = "hash", noise: str = "laplace", truncate: bool = True, reps: int | None = None) -> DataFrame:
    """Noise of scale delta_f / epsilon on every count, zero counts too; negative results become 0 with `truncate`.

    `source` hash: drawn from md5 of (seed, rep, u, v), the same on every run and in every engine; for tests and
    experiments, not for publication. os: drawn from the operating system's entropy; use `publish_once`, as a task
    that runs again draws again. With reps, a column rep holds the repeats.
    """
    scale = delta_f / epsilon
    df = hist if reps is None else hist.crossJoin(F.broadcast(hist.sparkSession.range(reps).select(F.col("id").cast("int").alias("rep"))))
    rep = F.lit(0) if reps is None else F.col("rep")
    if source == "hash":
        key = lambda tag: F.concat_ws(":", F.lit(seed + tag), rep, F.col("u"), F.col("v"))
        if noise == "laplace":
            y = fn.laplace_from_uniform(fn.uniform(key("")), scale)
        elif noise == "geometric":
            y = fn.geometric_from_uniforms(fn.uniform(key("a")), fn.uniform(key("b")), scale).cast("double")
        else:
            raise ValueError(f"noise is one of {NOISES}")
    elif source == "os":
        df, y = _entropy(df, scale, noise), F.col("__y")
    else:
        raise ValueError("source is hash or os")
    value = F.col("h").cast("double") + y
    return df.withColumn("h", F.greatest(value, F.lit(0.0)) if truncate else value).drop("__y")


def _entropy(df: DataFrame, scale: float, noise: str) -> DataFrame:
    schema = df.schema.simpleString()[7:-1].replace(":", " ")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            n = batch.num_rows
            u = ((np.frombuffer(os.urandom(16 * n), np.uint64) >> np.uint64(12)).astype(float) + 0.5) / 2.0**52
            x = u[:n] - 0.5
            y = -scale * np.sign(x) * np.log(1 - 2 * np.abs(x)) if noise == "laplace" else np.floor(np.log(u[:n]) * -scale) - np.floor(np.log(u[n:]) * -scale)
            yield pa.RecordBatch.from_arrays([*batch.columns, pa.array(y)], names=[*batch.schema.names, "__y"])

    return df.mapInArrow(run, f"{schema}, __y double")


def publish_once(noisy: DataFrame, path: str) -> DataFrame:
    """Write a noisy histogram and read it back, so that nothing downstream can draw the noise a second time."""
    noisy.write.mode("errorifexists").parquet(path)
    return noisy.sparkSession.read.parquet(path)


class Ledger:
    """Budget of one dataset. Releases over the same users add up; releases over disjoint users cost their largest."""

    def __init__(self, budget: float):
        self.budget, self.rows = budget, []

    def spent(self) -> float:
        parts: dict[str, float] = {}
        for r, group in self.rows:
            parts[group] = parts.get(group, 0.0) + r["epsilon"]
        shared = parts.pop("", 0.0)
        return shared + max(parts.values(), default=0.0)

    def charge(self, release_id: str, epsilon: float, sensitivity_: float, adjacency: str, noise: str = "laplace", users: str = "") -> None:
        """users: name of the group of users if releases of different names touch different users; "" for all."""
        row = {"release_id": release_id, "epsilon": float(epsilon), "sensitivity": float(sensitivity_), "adjacency": adjacency, "noise": noise}
        self.rows.append((row, users))
        if self.spent() > self.budget + 1e-12:
            self.rows.pop()
            raise ValueError(f"{release_id}: over budget {self.budget}")

    def table(self, spark: SparkSession) -> DataFrame:
        return spark.createDataFrame([r for r, _ in self.rows], LEDGER)


def release_card(spark: SparkSession, spec: GridSpec, body: float, epsilon: float) -> DataFrame:
    """Sensitivities, scale, number of counts and of constraints of a release."""
    n, k = spec.n, spec.span(body)
    tight = sensitivity(spec, body, "add_remove")
    row = (n, k, float(spec.counts), tight, sensitivity(spec, body, "add_remove", "lemma"), round(tight / epsilon, 6), 4 * n * (n - 1), 4 * (n - 1) ** 2, (n - 1) ** 2)
    return spark.createDataFrame([row], "n int, k int, counts double, tight double, lemma double, scale double, c1 int, c2 int, c3 int")


def components_near(complex_: DataFrame, body: float) -> DataFrame:
    """(comp_id, touched): for each face of a general partition, the components that meet its B-neighbourhood, by
    bounding boxes (an upper bound, from public geometry only)."""
    f = complex_.filter("kind = 'face'").select(F.col("comp_id").alias("face"), *[F.col(c).alias("f" + c) for c in ("xmin", "xmax", "ymin", "ymax")])
    c = complex_.select("comp_id", "xmin", "xmax", "ymin", "ymax")
    b = F.lit(body)
    if f.count() > 20_000:
        raise ValueError("too many faces for a broadcast; bound the sensitivity by regions")
    near = c.join(F.broadcast(f), (F.col("xmin") <= F.col("fxmax") + b) & (F.col("xmax") >= F.col("fxmin") - b) & (F.col("ymin") <= F.col("fymax") + b) & (F.col("ymax") >= F.col("fymin") - b))
    return near.groupBy(F.col("face").alias("comp_id")).agg(F.count(F.lit(1)).alias("touched"))


def sensitivity_general(complex_: DataFrame, body: float) -> float:
    """Sensitivity of a general partition of public size: the most components that one body can touch."""
    return float(components_near(complex_, body).agg(F.max("touched")).first()[0])


def noise_scale(delta_f: float, epsilon: float) -> float:
    return delta_f / epsilon


def tail(scale: float, delta: float, counts: int) -> float:
    """Bound that no count's noise passes, but with probability delta."""
    return scale * math.log(counts / delta)
