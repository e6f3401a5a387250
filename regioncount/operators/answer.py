"""Rectangle counts from a lattice: signed sums, prefix tables with four look-ups, and the truth from runs."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from regioncount.functions.fn import lattice_sign
from regioncount.operators.schemas import GridSpec


#: Queries up to which a range join broadcasts them; beyond, `by_prefix` answers at four look-ups each.
MOST_QUERIES = 200_000


def _few(queries: DataFrame) -> DataFrame:
    """The queries as a broadcast side, after a check of their number."""
    n = queries.count()
    if n > MOST_QUERIES:
        raise ValueError(f"{n} queries; use by_prefix")
    return F.broadcast(queries)


def by_sum(hist: DataFrame, queries: DataFrame, keys: list[str] | None = None) -> DataFrame:
    """(keys, q_id, est): faces minus edges plus vertices inside each rectangle, by a range join. A query reads its
    own area; for many queries use `by_prefix`."""
    keys = keys or []
    q = queries.select("q_id", *[(2 * F.col(c)).alias(c) for c in ("r0", "r1", "c0", "c1")])
    inside = (F.col("u") >= F.col("r0")) & (F.col("u") <= F.col("r1")) & (F.col("v") >= F.col("c0")) & (F.col("v") <= F.col("c1"))
    return hist.join(_few(q), inside).groupBy(*keys, "q_id").agg(F.sum(lattice_sign(F.col("u"), F.col("v")) * F.col("h")).alias("est"))


def prefix(hist: DataFrame, keys: list[str] | None = None) -> DataFrame:
    """(keys, u, v, p): sums of the signed lattice over all rows and columns up to (u, v)."""
    keys = keys or []
    along = Window.partitionBy(*keys, "u").orderBy("v").rowsBetween(Window.unboundedPreceding, 0)
    down = Window.partitionBy(*keys, "v").orderBy("u").rowsBetween(Window.unboundedPreceding, 0)
    df = hist.select(*keys, "u", "v", (lattice_sign(F.col("u"), F.col("v")) * F.col("h")).alias("s"))
    df = df.withColumn("s", F.sum("s").over(along))
    return df.select(*keys, "u", "v", F.sum("s").over(down).alias("p"))


def by_prefix(table: DataFrame, queries: DataFrame, keys: list[str] | None = None) -> DataFrame:
    """(keys, q_id, est) with four look-ups per query and release: the queries' corners are exploded and joined."""
    keys = keys or []
    r1, c1, r0, c0 = 2 * F.col("r1"), 2 * F.col("c1"), 2 * F.col("r0") - 1, 2 * F.col("c0") - 1
    four = F.array(*[F.struct(u.alias("u"), v.alias("v"), F.lit(s).alias("s")) for u, v, s in ((r1, c1, 1), (r0, c1, -1), (r1, c0, -1), (r0, c0, 1))])
    corners = queries.select("q_id", F.inline(four)).filter("u >= 0 and v >= 0")
    return table.join(corners, ["u", "v"]).groupBy(*keys, "q_id").agg(F.sum(F.col("s") * F.col("p")).alias("est"))


def prefix_arrays(table: DataFrame, keys: list[str]) -> DataFrame:
    """(keys, ps): one array per release, by (u, v), for `by_arrays`; lattices of moderate size."""
    rows = table.groupBy(*keys).agg(F.array_sort(F.collect_list(F.struct("u", "v", "p"))).alias("ps"))
    return rows.select(*keys, F.transform("ps", lambda x: x["p"]).alias("ps"))


def by_arrays(arrays: DataFrame, queries: DataFrame, spec: GridSpec, keys: list[str]) -> DataFrame:
    """(keys, queries' columns, est): every query on every release, four array look-ups, no shuffle. The arrays are
    broadcast: releases times lattice numbers, which no data size changes."""
    side = spec.side

    def at(u, v):
        return F.when((u >= 0) & (v >= 0), F.get(F.col("ps"), u * side + v)).otherwise(F.lit(0.0))

    r1, c1, r0, c0 = 2 * F.col("r1"), 2 * F.col("c1"), 2 * F.col("r0") - 1, 2 * F.col("c0") - 1
    est = at(r1, c1) - at(r0, c1) - at(r1, c0) + at(r0, c0)
    return queries.crossJoin(F.broadcast(arrays)).withColumn("est", est).drop("ps")


def true_count(runs: DataFrame, queries: DataFrame) -> DataFrame:
    """(q_id, truth): distinct bodies that overlap each rectangle, without the histogram; for evaluation."""
    q = queries.select("q_id", "r0", "r1", "c0", "c1")
    faces = runs.filter("u % 2 = 0")
    hit = (F.col("u") >= 2 * F.col("r0")) & (F.col("u") <= 2 * F.col("r1")) & (F.col("vlo") <= 2 * F.col("c1")) & (F.col("vhi") >= 2 * F.col("c0"))
    found = faces.join(_few(q), hit).select("q_id", "body_id").distinct().groupBy("q_id").agg(F.count(F.lit(1)).alias("truth"))
    return q.select("q_id").join(found, "q_id", "left").select("q_id", F.coalesce("truth", F.lit(0)).alias("truth"))


def snap(rects: DataFrame, spec: GridSpec) -> DataFrame:
    """Rectangles in coordinates (x0, x1, y0, y1), enlarged to whole cells."""
    d, top = F.lit(spec.d), F.lit(spec.n - 1)
    low = lambda c: F.greatest(F.floor(F.col(c) / d), F.lit(0)).cast("int")
    high = lambda c: F.least(F.greatest(F.ceil(F.col(c) / d) - 1, F.floor(F.col(c.replace("1", "0")) / d)), top).cast("int")
    return rects.select("q_id", low("y0").alias("r0"), high("y1").alias("r1"), low("x0").alias("c0"), high("x1").alias("c1"))


def by_mask(hist: DataFrame, cells: DataFrame) -> DataFrame:
    """(est): answer for a union of cells (r, c). Edges count if both faces are in it, vertices if all four are;
    exact for convex unions, an approximation otherwise."""
    faces = cells.select((2 * F.col("r")).alias("u"), (2 * F.col("c")).alias("v")).distinct()
    around = F.array(*[F.struct(F.lit(a).alias("du"), F.lit(b).alias("dv")) for a in (-1, 0, 1) for b in (-1, 0, 1)])
    near = faces.select("u", "v", F.inline(around)).select((F.col("u") + F.col("du")).alias("u"), (F.col("v") + F.col("dv")).alias("v"))
    full = near.groupBy("u", "v").agg(F.count(F.lit(1)).alias("faces")).withColumn("need", F.when((F.col("u") % 2 == 0) & (F.col("v") % 2 == 0), 1).when((F.col("u") % 2 == 1) & (F.col("v") % 2 == 1), 4).otherwise(2))
    used = full.filter("faces = need")
    return hist.join(used, ["u", "v"]).agg(F.sum(lattice_sign(F.col("u"), F.col("v")) * F.col("h")).alias("est"))


def with_interval(answers: DataFrame, queries: DataFrame, scale: float, delta: float = 0.05) -> DataFrame:
    """Add the standard deviation of an untruncated noisy answer, a normal interval, and a union bound."""
    q = queries.select("q_id", ((2 * (F.col("r1") - F.col("r0")) + 1) * (2 * (F.col("c1") - F.col("c0")) + 1)).alias("terms"))
    sd = F.lit(scale) * F.sqrt(2.0 * F.col("terms"))
    return answers.join(q, "q_id").withColumn("sd", sd).withColumn("lo", F.col("est") - 1.96 * F.col("sd")).withColumn("hi", F.col("est") + 1.96 * F.col("sd")).withColumn("union_bound", F.lit(scale) * F.col("terms") * F.log(F.col("terms") / F.lit(delta)))


