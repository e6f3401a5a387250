"""SQL surface of a release: a view of its prefix table, and the table function region_count(r0, r1, c0, c1)."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql.functions import udtf

from regioncount.operators import answer
from regioncount.operators.schemas import GridSpec

#: Lattice counts up to which a release travels inside the function; beyond, join with the view.
MOST_COUNTS = 4_000_000


def register(spark: SparkSession, hist: DataFrame, spec: GridSpec, view: str, function: str = "region_count") -> None:
    """Create view (u, v, p) and the function, usable with LATERAL. The lattice is public in size, and checked."""
    table = answer.prefix(hist)
    table.createOrReplaceTempView(view)
    if spec.counts > MOST_COUNTS:
        raise ValueError(f"{spec.counts} counts: join with the view {view}")
    side = spec.side
    values = [0.0] * spec.counts
    for r in table.collect():
        values[r["u"] * side + r["v"]] = float(r["p"])

    class RegionCount:
        def eval(self, r0: int, r1: int, c0: int, c1: int):
            def at(u, v):
                return values[u * side + v] if u >= 0 and v >= 0 else 0.0

            yield (at(2 * r1, 2 * c1) - at(2 * r0 - 1, 2 * c1) - at(2 * r1, 2 * c0 - 1) + at(2 * r0 - 1, 2 * c0 - 1),)

    spark.udtf.register(function, udtf(RegionCount, returnType="est double"))


def register_functions(spark: SparkSession) -> None:
    """Table functions runs_of (runs of a hull) and query_shapes (rectangles of a share of the area)."""
    from regioncount.operators.footprint import hull_runs
    from regioncount.operators.workload import shapes

    class RunsOf:
        def eval(self, hull, area: float, n: int):
            for u, lo, hi in hull_runs([(p["x"], p["y"]) for p in hull], float(area), n):
                yield u, lo, hi

    class QueryShapes:
        def eval(self, n: int, pct: float):
            yield from shapes(n, float(pct))

    spark.udtf.register("runs_of", udtf(RunsOf, returnType="u int, vlo int, vhi int"))
    spark.udtf.register("query_shapes", udtf(QueryShapes, returnType="r int, c int"))
