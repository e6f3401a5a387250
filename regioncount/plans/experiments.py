"""The experiment workloads on the given tables."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from regioncount.operators import answer, bounds, euler, fit, footprint, integerise, metrics, regions, release, workload
from regioncount.operators.schemas import GridSpec
from regioncount.sources import points
from regioncount.sources.shared import cut

#: Repeats of every experiment; the median is reported.
REPS = 100
BODY = 2.0
AREAS = {"even": 20.0, "dense": 20.0, "core": 3.2}


@dataclass(frozen=True)
class Setting:
    role: str
    n: int
    epsilon: float = 1.0
    body: float = BODY
    seed: str = "exp"
    reps: int = REPS

    @property
    def spec(self) -> GridSpec:
        return GridSpec(AREAS[self.role], self.n)

    @property
    def delta_f(self) -> float:
        return release.sensitivity(self.spec, self.body, "add_remove", "tight")

    @property
    def scale(self) -> float:
        return self.delta_f / self.epsilon


def bodies(spark: SparkSession, sf_dir: str, role: str, body: float = BODY) -> DataFrame:
    """Box bodies of a role: per-axis median as the mode, trimmed to a square of diagonal `body`."""
    return regions.extract_bodies(points.ROLES[role](spark, sf_dir), body, AREAS[role])


def exact(spark: SparkSession, sf_dir: str, s: Setting) -> DataFrame:
    return euler.histogram_boxes(bodies(spark, sf_dir, s.role, s.body), s.spec)


def releases(hist: DataFrame, s: Setting, methods: tuple[str, ...]) -> DataFrame:
    """(method, rep, u, v, kind, h): all methods on the same noise."""
    noisy = cut(release.perturb(hist, s.epsilon, s.delta_f, seed=s.seed, reps=s.reps).select("rep", "u", "v", "kind", "h"))
    keys, made = ["rep"], {"noise": noisy}
    if {"linf", "round"} & set(methods):
        made["linf"] = fit.linf(noisy, keys)
        made["round"] = integerise.round_counts(made["linf"]).withColumn("h", F.col("h").cast("double"))
    if "clip" in methods:
        made["clip"] = fit.clip_down(noisy, keys)
    if {"l1", "l1_round"} & set(methods):
        made["l1"] = cut(fit.l1(noisy, s.spec, keys))
        made["l1_round"] = integerise.round_counts(made["l1"]).withColumn("h", F.col("h").cast("double"))
    if "l2" in methods:
        made["l2"] = fit.l2(noisy, s.spec, keys)
    out = None
    for m in methods:
        part = made[m].select(F.lit(m).alias("method"), "rep", "u", "v", "kind", "h")
        out = part if out is None else out.union(part)
    return out


def errors(spark: SparkSession, sf_dir: str, s: Setting, wanted: list[tuple[float, int, int]], methods: tuple[str, ...], by: list[str]) -> DataFrame:
    """Median relative error and its companions over all positions and repeats."""
    hist = cut(exact(spark, sf_dir, s))
    keys = ["method", "rep"]
    arrays = answer.prefix_arrays(answer.prefix(releases(hist, s, methods), keys), keys)
    truth = answer.prefix_arrays(answer.prefix(hist.withColumn("rep", F.lit(0)), ["rep"]), ["rep"])
    q = workload.positions(spark, s.n, wanted)
    q = answer.by_arrays(truth, q, s.spec, ["rep"]).withColumnRenamed("est", "truth").drop("rep")
    a = answer.by_arrays(arrays, q, s.spec, keys)
    r = metrics.median_relative_error(a, ["method", *by])
    return r.select("method", *by, F.round("median_rel", 6).alias("median_rel"), F.round("share_true_zero", 6).alias("share_true_zero"), "answers")


def distances(spark: SparkSession, sf_dir: str, s: Setting, methods: tuple[str, ...]) -> DataFrame:
    """(method, rel_distance): distance to the exact counts in percent of the noisy ones', mean over repeats."""
    hist = cut(exact(spark, sf_dir, s))
    both = releases(hist, s, ("noise", *methods)).join(F.broadcast(hist.select("u", "v", F.col("h").alias("x"))), ["u", "v"])
    sums = both.groupBy("method", "rep").agg(F.sum(F.abs(F.col("h") - F.col("x"))).alias("d"))
    base = sums.filter("method = 'noise'").select("rep", F.col("d").alias("base"))
    return sums.join(base, "rep").groupBy("method").agg(F.round(F.avg(100.0 * F.col("d") / F.col("base")), 6).alias("rel_distance"))


def violated(spark: SparkSession, sf_dir: str, s: Setting, methods: tuple[str, ...]) -> DataFrame:
    """(method, cls, members, violated): violations of each class, mean over repeats."""
    hist = cut(exact(spark, sf_dir, s))
    v = metrics.violations(releases(hist, s, methods), s.spec, ["method", "rep"])
    return v.groupBy("method", "cls").agg(F.max("members").alias("members"), F.round(F.avg("violated"), 6).alias("violated"))


def running_time(spark: SparkSession, sf_dir: str, n: int = 20) -> DataFrame:
    """(role, stage, seconds) of one release; every stage starts from what the one before wrote."""
    rows = []
    for role in AREAS:
        s = Setting(role, n, reps=1)
        b = cut(bodies(spark, sf_dir, role))
        rows.append((role, "points_to_bodies", metrics.timed(lambda role=role: bodies(spark, sf_dir, role))))
        rows.append((role, "exact", metrics.timed(lambda b=b, s=s: euler.histogram_boxes(b, s.spec))))
        hist = cut(euler.histogram_boxes(b, s.spec))
        noise = lambda hist=hist, s=s: release.perturb(hist, s.epsilon, s.delta_f, seed=s.seed)
        rows.append((role, "noise", metrics.timed(noise)))
        noisy = cut(noise())
        rows.append((role, "fit_l1", metrics.timed(lambda noisy=noisy, s=s: fit.l1(noisy, s.spec))))
        rows.append((role, "fit_linf", metrics.timed(lambda noisy=noisy: fit.linf(noisy))))
        fitted = cut(fit.l1(noisy, s.spec))
        rows.append((role, "round", metrics.timed(lambda fitted=fitted: integerise.round_counts(fitted))))
    return spark.createDataFrame(rows, "role string, stage string, seconds double")


def bound_coverage(spark: SparkSession, sf_dir: str, s: Setting, deltas: list[float]) -> DataFrame:
    hist = cut(exact(spark, sf_dir, s))
    noisy = release.perturb(hist, s.epsilon, s.delta_f, seed=s.seed, reps=s.reps)
    c = bounds.coverage(hist, noisy, s.spec, s.scale, deltas, ["rep"])
    return c.select("delta", F.round("bound", 6).alias("bound"), "repeats", F.round("within", 6).alias("within"))


def worked_example(spark: SparkSession, boxes: DataFrame | None = None, spec: GridSpec = GridSpec(4.0, 4)) -> DataFrame:
    """Boxes (two, unless given) on a four by four grid: faces, edges, vertices inside the query, their answer, and the
    truth."""
    two = boxes if boxes is not None else spark.createDataFrame([(1, 0.5, 1.5, 0.5, 1.5), (2, 1.5, 2.5, 1.5, 2.5)], "body_id long, xmin double, xmax double, ymin double, ymax double")
    q = spark.createDataFrame([(1, 0, 2, 0, 2)], "q_id long, r0 int, r1 int, c0 int, c1 int")
    hist = euler.histogram_boxes(two, spec)
    inside = hist.filter("u <= 4 and v <= 4")
    totals = inside.agg(*[F.sum(F.when(F.col("kind") == k, F.col("h"))).alias(name) for k, name in (("face", "faces"), ("edge", "edges"), ("vertex", "vertices"))])
    est = answer.by_sum(hist, q).select(F.col("est").alias("answer"))
    truth = answer.true_count(footprint.box_runs(two, spec), q).select("truth")
    return totals.crossJoin(est).crossJoin(truth)


def planes(spark: SparkSession, sf_dir: str, which: str) -> DataFrame:
    """Boxes on a plane of 10 by 10 from other columns: customers' dates and prices, or vectors' first numbers."""
    if which == "orders":
        o = points.table(spark, sf_dir, "orders").select(F.col("o_custkey").alias("user_id"), F.datediff("o_orderdate", F.lit("1992-01-01")).cast("double").alias("x"), F.col("o_totalprice").alias("y"), F.col("o_orderkey").alias("point_id"))
    else:
        o = points.table(spark, sf_dir, "embeddings").select(F.pmod("vec_id", F.lit(50)).cast("long").alias("user_id"), F.col("embedding")[0].cast("double").alias("x"), F.col("embedding")[1].cast("double").alias("y"), F.col("vec_id").alias("point_id"))
    lim = o.agg(F.min("x").alias("x0"), F.max("x").alias("x1"), F.min("y").alias("y0"), F.max("y").alias("y1"))
    scaled = lambda c: (F.col(c) - F.col(c + "0")) / (F.col(c + "1") - F.col(c + "0")) * F.lit(9.999)
    p = o.crossJoin(F.broadcast(lim)).select("user_id", "point_id", scaled("x").alias("x"), scaled("y").alias("y"))
    return regions.extract_bodies(p, BODY, 10.0)


def replicated(spark: SparkSession, sf_dir: str, role: str, times: int, n: int) -> DataFrame:
    """(kind, total): histogram totals of a role's bodies, each repeated with small shifts round the area."""
    area = AREAS[role]
    b = bodies(spark, sf_dir, role).withColumn("copy", F.explode(F.sequence(F.lit(0), F.lit(times - 1))))
    shift = F.col("copy") * F.lit(area / times / 2)
    moved = b.select((F.col("body_id") * times + F.col("copy")).alias("body_id"), *[(F.col(c) + shift).alias(c) for c in ("xmin", "xmax", "ymin", "ymax")])
    h = euler.histogram_boxes(moved, GridSpec(area, n))
    return h.groupBy("kind").agg(F.sum("h").alias("total"), F.max("h").alias("most"))
