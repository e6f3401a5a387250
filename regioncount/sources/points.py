"""Points: the three roles made from the given tables, readers for location files, and text geometry."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from regioncount.functions.fn import uniform
from regioncount.operators.schemas import POINTS

#: Hubs of the dense role, by nation modulo 5 (fixed values).
HUBS = ((5.3, 6.2), (7.1, 13.4), (10.2, 9.7), (13.6, 8.3), (15.4, 15.1))


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def _u(tag: str, user: Column) -> Column:
    return uniform(F.concat(F.lit(f"{tag}:"), user.cast("string")))


def _frac(a: Column) -> Column:
    return (F.pmod(a, F.lit(1000)).cast("double") + F.lit(0.5)) / F.lit(1000.0) - F.lit(0.5)


def _cents(c: str) -> Column:
    return F.round(F.col(c) * 100).cast("long")


def _days(c: str) -> Column:
    return (37 * F.datediff(F.col(c), F.lit("1995-01-01"))).cast("long")


def _spread(df: DataFrame) -> DataFrame:
    """Columns user_id, point_id, ts, hx, hy, a, b to points round a home; every eleventh point is an outlier."""
    w = F.lit(1.2) * (F.lit(0.3) + F.lit(0.7) * _u("s", F.col("user_id")))
    w = F.when(F.col("point_id") % 11 == 0, w * F.lit(5.0)).otherwise(w)
    return df.select("user_id", "point_id", F.col("ts").cast("timestamp").alias("ts"), (F.col("hx") + w * _frac(F.col("a"))).alias("x"), (F.col("hy") + w * _frac(F.col("b"))).alias("y"))


def even(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Many users, spread over the area of 20 by 20: from orders."""
    user = F.col("o_custkey")
    return _spread(table(spark, sf_dir, "orders").select(user.alias("user_id"), F.col("o_orderkey").alias("point_id"), F.col("o_orderdate").alias("ts"), (F.lit(20.0) * _u("ex", user)).alias("hx"), (F.lit(20.0) * _u("ey", user)).alias("hy"), _cents("o_totalprice").alias("a"), _days("o_orderdate").alias("b")))


def core(spark: SparkSession, sf_dir: str) -> DataFrame:
    """A small concentrated area of 3.2 by 3.2: from events."""
    user = F.col("user_id")
    home = lambda axis: F.lit(1.6) + F.lit(0.8) * (_u(f"c{axis}1", user) + _u(f"c{axis}2", user) + _u(f"c{axis}3", user) - F.lit(1.5))
    seconds = (37 * (F.unix_seconds(F.col("ts").cast("timestamp")) - F.lit(1704067200))).cast("long")
    return _spread(table(spark, sf_dir, "events").select("user_id", F.col("event_id").alias("point_id"), "ts", home("x").alias("hx"), home("y").alias("hy"), _cents("value").alias("a"), seconds.alias("b")))


def dense(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Many points per user round five hubs: from lineitem and supplier."""
    user, hub = F.col("l_suppkey"), F.pmod(F.col("s_nationkey"), F.lit(5)).cast("int")
    home = lambda axis, k: F.get(F.array(*[F.lit(h[k]) for h in HUBS]), hub) + F.lit(3.0) * (_u(f"d{axis}1", user) + _u(f"d{axis}2", user) - F.lit(1.0))
    joined = table(spark, sf_dir, "lineitem").select("l_suppkey", "l_orderkey", "l_linenumber", "l_extendedprice", "l_shipdate").join(table(spark, sf_dir, "supplier").select("s_suppkey", "s_nationkey"), F.col("l_suppkey") == F.col("s_suppkey"))
    return _spread(joined.select(user.alias("user_id"), (F.col("l_orderkey") * 8 + F.col("l_linenumber")).cast("long").alias("point_id"), F.col("l_shipdate").alias("ts"), home("x", 0).alias("hx"), home("y", 1).alias("hy"), _cents("l_extendedprice").alias("a"), _days("l_shipdate").alias("b")))


ROLES = {"even": even, "dense": dense, "core": core}


# ---------------------------------------------------------------- files
def read_points(spark: SparkSession, path: str, form: str = "parquet", lon_lat: bool = False) -> DataFrame:
    """Points from parquet, orc, csv (with header) or json lines; rows that do not parse have null fields."""
    names = ("lon", "lat") if lon_lat else ("x", "y")
    schema = T.StructType([*POINTS.fields[:3], *[T.StructField(c, T.DoubleType()) for c in names]])
    reader = spark.read.schema(schema)
    if form == "csv":
        return reader.option("header", True).option("mode", "PERMISSIVE").csv(path)
    return reader.format(form).load(path)


def read_text_points(spark: SparkSession, path: str) -> DataFrame:
    """Lines `user,point,timestamp,x,y` of plain text; other lines are left out."""
    parts = F.split("value", ",")
    df = spark.read.text(path).filter(F.col("value").rlike(r"^\d+,\d+,[^,]+,-?[\d.]+,-?[\d.]+$"))
    return df.select(parts[0].cast("long").alias("user_id"), parts[1].cast("long").alias("point_id"), parts[2].cast("timestamp").alias("ts"), parts[3].cast("double").alias("x"), parts[4].cast("double").alias("y"))


def parse_wkt(wkt: Column) -> Column:
    """Outer ring of POLYGON((x y, ...)) without the repeated first point."""
    ring = F.regexp_extract(wkt, r"\(\(([^)]*)\)", 1)
    pts = F.transform(F.split(ring, r"\s*,\s*"), lambda p: F.struct(F.split(F.trim(p), r"\s+")[0].cast("double").alias("x"), F.split(F.trim(p), r"\s+")[1].cast("double").alias("y")))
    return F.slice(pts, 1, F.size(pts) - 1)


def to_wkt(hull: Column) -> Column:
    closed = F.concat(hull, F.slice(hull, 1, 1))
    return F.concat(F.lit("POLYGON(("), F.array_join(F.transform(closed, lambda p: F.concat_ws(" ", p["x"], p["y"])), ", "), F.lit("))"))


def to_geojson(hull: Column) -> Column:
    closed = F.concat(hull, F.slice(hull, 1, 1))
    return F.to_json(F.struct(F.lit("Polygon").alias("type"), F.array(F.transform(closed, lambda p: F.array(p["x"], p["y"]))).alias("coordinates")))


def parse_geojson(text: Column) -> Column:
    rings = F.from_json(text, "type string, coordinates array<array<array<double>>>")["coordinates"][0]
    return F.transform(F.slice(rings, 1, F.size(rings) - 1), lambda p: F.struct(p[0].alias("x"), p[1].alias("y")))


def register_generator(spark: SparkSession) -> None:
    """Data source `user_points`: options users, points, area, seed, partitions. Every partition can be made again."""
    from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition

    class Reader(DataSourceReader):
        def __init__(self, options):
            self.users, self.points = int(options.get("users", 100)), int(options.get("points", 20))
            self.area, self.seed, self.parts = float(options.get("area", 20)), int(options.get("seed", 0)), int(options.get("partitions", 4))

        def partitions(self):
            return [InputPartition(k) for k in range(self.parts)]

        def read(self, partition):
            import datetime
            import random

            for user in range(partition.value, self.users, self.parts):
                rng = random.Random(self.seed * 1_000_003 + user)
                hx, hy = rng.uniform(0, self.area), rng.uniform(0, self.area)
                for k in range(self.points):
                    yield user, user * self.points + k, datetime.datetime(2024, 1, 1) + datetime.timedelta(minutes=k), hx + rng.gauss(0, 0.3), hy + rng.gauss(0, 0.3)

    class UserPoints(DataSource):
        @classmethod
        def name(cls):
            return "user_points"

        def schema(self):
            return POINTS

        def reader(self, schema):
            return Reader(self.options)

    spark.dataSource.register(UserPoints)


# ---------------------------------------------------------------- sinks
def publish(hist: DataFrame, path: str, stage: str, form: str = "parquet") -> None:
    """Write a release, partitioned by release_id where there is one. An exact histogram is refused."""
    if stage not in ("noise", "fit", "round"):
        raise ValueError("only noisy, fitted or rounded counts are published")
    writer = hist.write.mode("errorifexists")
    if "release_id" in hist.columns:
        writer = writer.partitionBy("release_id")
    (writer.option("header", True).csv if form == "csv" else writer.parquet)(path)
