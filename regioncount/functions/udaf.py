"""Grouped aggregate functions in Arrow batches, for SQL and DataFrames."""

from __future__ import annotations

import pandas as pd
from pyspark.sql import SparkSession
from pyspark.sql import functions as F

from regioncount.operators.regions import hull_of


def hull_wkt():
    """Aggregate of x and y columns: the convex hull of a group as WKT (a point or a line if degenerate)."""

    @F.pandas_udf("string")
    def aggregate(x: pd.Series, y: pd.Series) -> str:
        hull = hull_of(list(zip(x, y, strict=True)))
        if len(hull) == 1:
            return f"POINT({hull[0][0]} {hull[0][1]})"
        if len(hull) == 2:
            return f"LINESTRING({', '.join(f'{a} {b}' for a, b in hull)})"
        return f"POLYGON(({', '.join(f'{a} {b}' for a, b in [*hull, hull[0]])}))"

    return aggregate


def register(spark: SparkSession) -> None:
    """SQL name hull_wkt(x, y)."""
    spark.udf.register("hull_wkt", hull_wkt())
