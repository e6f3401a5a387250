"""Exactness of the histogram, footprints and answers."""

import math
import random

import pytest
from hypothesis import given, settings
from hypothesis import strategies as st

from regioncount.operators import answer, euler, footprint, partition, regions, release
from regioncount.operators.footprint import hull_runs
from regioncount.operators.regions import hull_of
from regioncount.operators.schemas import GridSpec


def truth(hull, d, n, r0, r1, c0, c1):
    """Whether a convex polygon meets the half-open rectangle, by clipping."""
    box = [(c0 * d, r0 * d), ((c1 + 1) * d - 1e-9, r0 * d), ((c1 + 1) * d - 1e-9, (r1 + 1) * d - 1e-9), (c0 * d, (r1 + 1) * d - 1e-9)]
    return partition.convex_meet(hull, box)


def answer_of(runs, r0, r1, c0, c1):
    total = 0
    for u, lo, hi in runs:
        if 2 * r0 <= u <= 2 * r1:
            a, b = max(lo, 2 * c0), min(hi, 2 * c1)
            total += sum((-1) ** (u + v) for v in range(a, b + 1))
    return total


@settings(max_examples=150, deadline=None)
@given(st.integers(0, 10**9))
def test_hull_answers_are_exact(seed):
    rng = random.Random(seed)
    n, d = 8, 1.0
    cx, cy = rng.uniform(0, 8), rng.uniform(0, 8)
    hull = hull_of([(cx + rng.uniform(-1, 1), cy + rng.uniform(-1, 1)) for _ in range(rng.randint(1, 12))])
    runs = hull_runs(hull, n * d, n)
    for _ in range(10):
        r0, c0 = rng.randrange(n), rng.randrange(n)
        r1, c1 = rng.randrange(r0, n), rng.randrange(c0, n)
        assert answer_of(runs, r0, r1, c0, c1) == int(truth(hull, d, n, r0, r1, c0, c1))
    assert sum(hi - lo + 1 for _, lo, hi in runs) <= 4 * 2 * 3 + 1


def test_disconnected_body_is_counted_twice():
    a, b = hull_runs([(0.5, 0.5)], 4.0, 4), hull_runs([(2.5, 0.5)], 4.0, 4)
    assert answer_of(a + b, 0, 3, 0, 3) == 2


def test_body_that_leaves_and_returns():
    # a horseshoe: left and right arms inside the query, the bow outside
    arms = [(0, 0, 0), (0, 4, 4), (1, 0, 0), (1, 4, 4), (2, 0, 4)]
    assert answer_of(arms, 0, 0, 0, 2) == 2


def test_aligned_width_meets_at_most_k_plus_one_cells():
    runs = hull_runs([(1.0, 1.0), (3.0, 1.0), (3.0, 3.0), (1.0, 3.0)], 8.0, 8)
    assert max(hi // 2 - lo // 2 + 1 for _, lo, hi in runs) == 3


def test_worked_example(spark):
    from regioncount.plans.experiments import worked_example

    assert tuple(worked_example(spark).first()) == (8, 8, 2, 2, 2)


@pytest.mark.parametrize("method", ["explode", "runs"])
def test_methods_agree(spark, sf_dir, method):
    from regioncount.plans.experiments import bodies

    spec = GridSpec(20.0, 20)
    b = bodies(spark, sf_dir, "even")
    assert euler.histogram(footprint.box_runs(b, spec), spec, method).exceptAll(euler.histogram_boxes(b, spec)).count() == 0


def test_empty_and_degenerate_bodies(spark):
    spec = GridSpec(4.0, 4)
    schema = "body_id long, xmin double, xmax double, ymin double, ymax double"
    assert euler.histogram_boxes(spark.createDataFrame([], schema), spec).agg({"h": "sum"}).first()[0] == 0
    whole = euler.histogram_boxes(spark.createDataFrame([(1, -1.0, 9.0, -1.0, 9.0)], schema), spec)
    assert {r.h for r in whole.collect()} == {1}
    outside = euler.histogram_boxes(spark.createDataFrame([(1, 4.0, 5.0, 0.0, 1.0)], schema), spec)
    assert outside.agg({"h": "sum"}).first()[0] == 0
    assert hull_of([(1, 1)]) == [(1, 1)] and len(hull_of([(0, 0), (1, 1), (2, 2)])) == 2


def test_hull_histogram_answers(spark, sf_dir):
    from regioncount.plans.q_core import ALL4, hulls
    from regioncount.operators import workload

    spec = GridSpec(3.2, 4)
    b = hulls(spark, sf_dir)
    q = workload.positions(spark, 4, ALL4)
    est = {r.q_id: r.est for r in answer.by_prefix(answer.prefix(euler.histogram_hulls(b, spec)), q).collect()}
    want = {r.q_id: r.truth for r in answer.true_count(footprint.runs(b, spec), q).collect()}
    assert est == want
    hull = [[(p.x, p.y) for p in r.hull] for r in b.collect()]
    for r in q.collect():
        assert est[r.q_id] == sum(truth(h, 0.8, 4, r.r0, r.r1, r.c0, r.c1) for h in hull)


def test_drop_interior_keeps_every_corner(spark):
    rng = random.Random(4)
    pts = [(1, k, None, rng.gauss(0, 1), rng.gauss(0, 1)) for k in range(300)] + [(2, 0, None, 1.0, 1.0), (2, 1, None, 1.0, 1.0), (3, 0, None, 0.0, 0.0), (3, 1, None, 1.0, 1.0)]
    df = spark.createDataFrame(pts, "user_id long, point_id long, ts timestamp, x double, y double")
    lean = regions.drop_interior(df)
    assert lean.count() < 200
    for user in (1, 2, 3):
        assert hull_of([(p[3], p[4]) for p in pts if p[0] == user]) == hull_of([(r.x, r.y) for r in lean.filter(f"user_id = {user}").collect()])


def test_voronoi(spark):
    from regioncount.plans.q_core import SITES

    cells = partition.voronoi(SITES, 3.2)
    assert math.isclose(sum(map(partition.polygon_area, cells)), 3.2**2, rel_tol=1e-9)
    parts = partition.components(cells)
    counts = {k: sum(p[1] == k for p in parts) for k in ("face", "edge", "vertex")}
    assert counts["face"] - counts["edge"] + counts["vertex"] == 1
    table = partition.complex_table(spark, parts)
    rng = random.Random(3)
    bodies = [hull_of([(min(3.19, max(0, cx + rng.uniform(-0.4, 0.4))), min(3.19, max(0, cy + rng.uniform(-0.4, 0.4)))) for _ in range(6)]) for cx, cy in ((rng.uniform(0, 3.2), rng.uniform(0, 3.2)) for _ in range(60))]
    rows = [(i, [(x, y) for x, y in h], min(x for x, _ in h), max(x for x, _ in h), min(y for _, y in h), max(y for _, y in h), 1.0, 6) for i, h in enumerate(bodies)]
    df = spark.createDataFrame(rows, "body_id long, hull array<struct<x:double,y:double>>, xmin double, xmax double, ymin double, ymax double, diameter double, n_points long")
    hist = partition.histogram_general(df, table, 0.8)
    got = {r.comp_id: r.h for r in hist.collect()}
    assert got == {i: sum(partition.convex_meet(h, g) for h in bodies) for i, _, g, _ in parts}
    assert partition.count_general(hist, table, list(range(len(SITES)))).first()[0] == len(bodies)
    assert partition.count_general(hist, table, [4]).first()[0] == sum(partition.convex_meet(h, cells[4]) for h in bodies)
    assert release.sensitivity_general(table, 0.8) <= len(parts)


def test_nearest_all_has_no_limit(spark, monkeypatch):
    from pyspark.sql import functions as F

    from regioncount.plans import q_core
    from regioncount.sources import points

    n = 1_000_003  # of one user
    one = spark.range(n).select(F.lit(1).cast("long").alias("user_id"), F.col("id").alias("point_id"), F.lit(0).alias("ts"), (F.col("id") % 1000 / 100.0).alias("x"), F.lit(1.0).alias("y"))
    monkeypatch.setattr(points, "core", lambda spark, d: one)
    found = q_core.QUERIES["nearest_all"][0](spark, "").agg(F.count(F.lit(1)), F.max("rank")).first()
    assert tuple(found) == (n, n)
    assert q_core.QUERIES["nearest_k"][0](spark, "").count() == 40


def test_hulls_of_the_concentrated_role_are_exact(spark, sf_dir):
    """Corners and areas as in rational arithmetic on the same doubles, where a side's rounded test could err."""
    from fractions import Fraction

    from pyspark.sql import functions as F

    from regioncount.functions import fn
    from regioncount.plans import q_core
    from regioncount.sources import points

    p = points.core(spark, sf_dir)
    kept = regions.trim(regions.with_modes(p, regions.density_mode(p)), 2.0, "disc", 3.2).select("user_id", "x", "y").collect()
    got = {r.body_id: (r.c, r.a) for r in q_core.hulls(spark, sf_dir).select("body_id", F.size("hull").alias("c"), fn.hull_area(F.col("hull")).alias("a")).collect()}
    sets = {}
    for r in kept:
        sets.setdefault(r.user_id, set()).add((Fraction(r.x), Fraction(r.y)))
    assert set(got) == set(sets)

    def chain(ps):
        out = []
        for c in ps:
            while len(out) > 1 and (out[-1][0] - out[-2][0]) * (c[1] - out[-2][1]) - (out[-1][1] - out[-2][1]) * (c[0] - out[-2][0]) <= 0:
                out.pop()
            out.append(c)
        return out[:-1]

    for user, s in sets.items():
        ps = sorted(s)
        h = chain(ps) + chain(ps[::-1]) if len(ps) > 2 else ps
        area = abs(sum(a[0] * b[1] - b[0] * a[1] for a, b in zip(h, h[1:] + h[:1], strict=True))) / 2
        assert got[user][0] == len(h) and abs(got[user][1] - float(area)) < 1e-9
