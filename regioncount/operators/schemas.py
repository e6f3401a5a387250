"""Fixed schemas and the public grid."""

from __future__ import annotations

import math
from dataclasses import dataclass

from pyspark.sql import types as T

POINT = T.StructType([T.StructField("x", T.DoubleType()), T.StructField("y", T.DoubleType())])
POINTS = T.StructType([T.StructField("user_id", T.LongType()), T.StructField("point_id", T.LongType()), T.StructField("ts", T.TimestampType()), T.StructField("x", T.DoubleType()), T.StructField("y", T.DoubleType())])
BODIES = T.StructType([T.StructField("body_id", T.LongType()), T.StructField("hull", T.ArrayType(POINT)), *[T.StructField(c, T.DoubleType()) for c in ("xmin", "xmax", "ymin", "ymax", "diameter")], T.StructField("n_points", T.LongType())])
RUNS = T.StructType([T.StructField("body_id", T.LongType()), *[T.StructField(c, T.IntegerType()) for c in ("u", "vlo", "vhi")]])
LATTICE = T.StructType([T.StructField("u", T.IntegerType()), T.StructField("v", T.IntegerType()), T.StructField("kind", T.StringType()), T.StructField("h", T.DoubleType())])
QUERIES = T.StructType([T.StructField("q_id", T.LongType()), *[T.StructField(c, T.IntegerType()) for c in ("shape_r", "shape_c", "r0", "r1", "c0", "c1")], T.StructField("pct", T.DoubleType())])
LEDGER = T.StructType([T.StructField("release_id", T.StringType()), T.StructField("epsilon", T.DoubleType()), T.StructField("sensitivity", T.DoubleType()), T.StructField("adjacency", T.StringType()), T.StructField("noise", T.StringType())])


@dataclass(frozen=True)
class GridSpec:
    """n by n square cells over [0, A) squared."""

    area: float
    n: int

    @property
    def d(self) -> float:
        return self.area / self.n

    @property
    def side(self) -> int:
        """Lattice rows: faces, edges and vertices interleaved."""
        return 2 * self.n - 1

    @property
    def counts(self) -> int:
        return self.side**2

    def span(self, body: float) -> int:
        """k: cells that a body diameter reaches across, rounded before the ceiling so that 2 / (20/30) is 3."""
        return math.ceil(round(body / self.d, 9))
