"""Streams of points: boxes per user and window, histogram differences, one live body per user, releases per batch.

The method itself is for a fixed set of bodies. A user who appears in many windows spends budget in each: the
releases of a stream compose, and the ledger refuses what is over budget.
"""

from __future__ import annotations

import uuid
from collections.abc import Callable

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from regioncount.operators import euler, fit, footprint, integerise, release
from regioncount.operators.schemas import POINTS, GridSpec
from regioncount.sources import points as sources
from regioncount.sources.shared import cut


def points(spark: SparkSession, path: str, delay: str = "1 hour", files: int = 1) -> DataFrame:
    """Points from parquet files as they come; later ones than `delay` are dropped."""
    return spark.readStream.schema(POINTS).option("maxFilesPerTrigger", files).parquet(path).withWatermark("ts", delay)


def dedup(df: DataFrame) -> DataFrame:
    return df.dropDuplicatesWithinWatermark(["user_id", "point_id"])


def window_boxes(df: DataFrame, length: str = "1 day", slide: str | None = None, gap: str | None = None) -> DataFrame:
    """(body_id, start, box, n_points): the box of each user's points in tumbling, sliding or session windows."""
    w = F.session_window("ts", gap) if gap else F.window("ts", length, slide) if slide else F.window("ts", length)
    boxes = df.groupBy(F.col("user_id").alias("body_id"), w.alias("w")).agg(F.min("x").alias("xmin"), F.max("x").alias("xmax"), F.min("y").alias("ymin"), F.max("y").alias("ymax"), F.count(F.lit(1)).alias("n_points"))
    return boxes.select("body_id", F.col("w.start").alias("start"), "xmin", "xmax", "ymin", "ymax", "n_points")


def deltas(boxes: DataFrame, spec: GridSpec, k: int) -> DataFrame:
    """(u, v, delta) of a batch of boxes: corner differences are additive, so batches add up."""
    return euler.corner_deltas(footprint.box_cells(boxes, spec, k))


def late(df: DataFrame, seen_until: str) -> DataFrame:
    """Points before a time that is already released, counted apart and never released again."""
    return df.filter(F.col("ts") < F.lit(seen_until).cast("timestamp")).groupBy(F.window("ts", "1 day").alias("w")).agg(F.count(F.lit(1)).alias("late"))


def live_bodies(df: DataFrame) -> DataFrame:
    """(body_id, sign, box): one box per user over all time; a change takes the old box out and puts the new one in.

    State per user is four numbers. A change touches two footprints, so its adjacency is `replace`.
    """
    schema = "body_id long, sign int, xmin double, xmax double, ymin double, ymax double"

    def step(key, frames, state):
        old = state.get if state.exists else None
        now = old
        for p in frames:
            box = (float(p.x.min()), float(p.x.max()), float(p.y.min()), float(p.y.max()))
            now = box if now is None else (min(now[0], box[0]), max(now[1], box[1]), min(now[2], box[2]), max(now[3], box[3]))
        if now != old:
            state.update(now)
            rows = [(int(key[0]), 1, *now)] + ([(int(key[0]), -1, *old)] if old else [])
            yield pd.DataFrame(rows, columns=["body_id", "sign", "xmin", "xmax", "ymin", "ymax"])

    return df.groupBy("user_id").applyInPandasWithState(step, schema, "xmin double, xmax double, ymin double, ymax double", "append", "NoTimeout")


def release_batches(boxes: DataFrame, spec: GridSpec, body: float, epsilon: float, book: release.Ledger, sink: Callable[[DataFrame, int], None], source: str = "os"):
    """Writer that releases the exact histogram of every batch of closed windows: noise, max-norm fit, rounding.

    Each batch is charged to the ledger before its noise is drawn, and written before it is used.
    """
    delta_f = release.sensitivity(spec, body, "replace")

    def run(batch: DataFrame, number: int) -> None:
        book.charge(f"batch-{number}", epsilon, delta_f, "replace")
        hist = euler.histogram_boxes(batch, spec, spec.span(body))
        noisy = cut(release.perturb(hist, epsilon, delta_f, seed=f"batch-{number}", source=source))
        sink(integerise.round_counts(fit.linf(noisy)), number)

    return boxes.writeStream.foreachBatch(run).outputMode("append")


def _shape(df: DataFrame) -> DataFrame:
    return df.select("body_id", F.unix_seconds("start").alias("start"), *[F.round(c, 6).alias(c) for c in ("xmin", "xmax", "ymin", "ymax")], "n_points")


def batch_windows(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _shape(window_boxes(sources.core(spark, sf_dir)))


def replay_windows(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The same by a stream that reads the points as files, two at a time.

    Boxes and counts of parts of a window add up, so every batch writes the boxes of its own points and they are put
    together at the end: no state and nothing on the driver grows with the windows. A batch that runs again writes over
    what it wrote.
    """
    from regioncount.sources.shared import shared_dir

    root = f"{shared_dir(spark)}/stream-{uuid.uuid4().hex}"
    sources.core(spark, sf_dir).repartitionByRange(4, "ts").write.parquet(f"{root}/in")
    stream = spark.readStream.schema(POINTS).option("maxFilesPerTrigger", 2).parquet(f"{root}/in")
    query = stream.writeStream.foreachBatch(lambda batch, number: window_boxes(batch).write.mode("overwrite").parquet(f"{root}/out/batch={number}")).option("checkpointLocation", f"{root}/at").trigger(availableNow=True).start()
    query.awaitTermination()
    parts = spark.read.parquet(f"{root}/out").groupBy("body_id", "start")
    return _shape(parts.agg(F.min("xmin").alias("xmin"), F.max("xmax").alias("xmax"), F.min("ymin").alias("ymin"), F.max("ymax").alias("ymax"), F.sum("n_points").alias("n_points")))
