"""Readers, the generator, SQL functions, streams, and plan shapes."""

from pyspark.sql import functions as F

from regioncount.operators import euler, release
from regioncount.operators.schemas import GridSpec
from regioncount.plans import experiments as x
from regioncount.plans import sqlapi
from regioncount.sources import points
from regioncount.streaming import stream


def test_readers(spark, tmp_path):
    p = points.even(spark, "/root/testdata/sf0.001").limit(20)
    for form in ("parquet", "orc", "json", "csv"):
        w = p.write.option("header", True)
        getattr(w, form)(str(tmp_path / form))
        assert points.read_points(spark, str(tmp_path / form), form).select("user_id", "point_id").exceptAll(p.select("user_id", "point_id")).count() == 0
    (tmp_path / "t.txt").write_text("1,2,2024-01-01 00:00:00,0.5,-1.25\nnot a point\n")
    assert [(r.user_id, r.x, r.y) for r in points.read_text_points(spark, str(tmp_path / "t.txt")).collect()] == [(1, 0.5, -1.25)]


def test_generator_is_the_same_at_any_partitioning(spark):
    points.register_generator(spark)
    a = spark.read.format("user_points").option("users", 10).option("partitions", 2).load()
    b = spark.read.format("user_points").option("users", 10).option("partitions", 5).load()
    assert a.count() == 200 and a.exceptAll(b).count() == 0


def test_sql_functions(spark):
    sqlapi.register_functions(spark)
    assert {(r.r, r.c) for r in spark.sql("SELECT * FROM query_shapes(20, 1.0D)").collect()} == {(1, 4), (2, 2), (4, 1)}
    got = spark.sql("SELECT * FROM runs_of(array(named_struct('x', 0.5D, 'y', 0.5D), named_struct('x', 1.5D, 'y', 1.5D)), 4.0D, 4)").collect()
    assert {(r.u, r.vlo, r.vhi) for r in got} == {(0, 0, 2), (1, 2, 2), (2, 2, 2)}


def test_live_bodies_and_releases(spark, sf_dir, tmp_path):
    p = points.core(spark, sf_dir)
    p.repartitionByRange(3, "ts").write.parquet(str(tmp_path / "in"))
    boxes = stream.live_bodies(spark.readStream.schema(p.schema).option("maxFilesPerTrigger", 1).parquet(str(tmp_path / "in")))
    q = boxes.writeStream.format("memory").queryName("live").option("checkpointLocation", str(tmp_path / "c1")).trigger(availableNow=True).start()
    q.awaitTermination()
    net = spark.table("live").groupBy("body_id", "xmin", "xmax", "ymin", "ymax").agg(F.sum("sign").alias("s")).filter("s <> 0")
    want = p.groupBy(F.col("user_id").alias("body_id")).agg(F.min("x").alias("xmin"), F.max("x").alias("xmax"), F.min("y").alias("ymin"), F.max("y").alias("ymax")).withColumn("s", F.lit(1).cast("long"))
    assert net.exceptAll(want).count() == 0 and want.count() == net.count()

    out, book, spec = [], release.Ledger(10.0), GridSpec(3.2, 4)
    windows = stream.window_boxes(stream.dedup(stream.points(spark, str(tmp_path / "in"))), "30 days")
    q = stream.release_batches(windows, spec, 2.0, 0.5, book, lambda df, k: out.append(df.count()), source="hash").option("checkpointLocation", str(tmp_path / "c2")).trigger(availableNow=True).start()
    q.awaitTermination()
    assert out and set(out) == {49} and book.spent() == 0.5 * len(out)


def test_replay_keeps_no_state_and_nothing_on_the_driver(spark, sf_dir):
    """The windows of all batches are rows of files, not of a table in the driver's memory."""
    df = stream.replay_windows(spark, sf_dir)
    files, want = df.inputFiles(), stream.batch_windows(spark, sf_dir)
    assert {f.split("batch=")[1][0] for f in files} == {"0", "1"}
    assert df.exceptAll(want).count() == 0 and df.count() == want.count()


def test_plans(spark, sf_dir):
    """Points reach the bodies without Python, a Cartesian product, or more columns than needed."""
    b = x.bodies(spark, sf_dir, "even")
    plan = euler.histogram_boxes(b, GridSpec(20.0, 20))._jdf.queryExecution().toString()
    assert "Python" not in plan and "CartesianProduct" not in plan and "o_orderpriority" not in plan.split("Physical Plan")[-1]


def test_hull_aggregate(spark):
    from regioncount.functions import udaf

    udaf.register(spark)
    df = spark.createDataFrame([(1, 0.0, 0.0), (1, 1.0, 0.0), (1, 1.0, 1.0), (1, 0.5, 0.2), (2, 3.0, 4.0)], "g int, x double, y double")
    df.createOrReplaceTempView("hull_points")
    got = {r.g: r.h for r in spark.sql("SELECT g, hull_wkt(x, y) AS h FROM hull_points GROUP BY g").collect()}
    assert got == {1: "POLYGON((0.0 0.0, 1.0 0.0, 1.0 1.0, 0.0 0.0))", 2: "POINT(3.0 4.0)"}
