"""Noise, sensitivity, budget, fits and rounding."""

import itertools
import math

import numpy as np
import pytest
from pyspark.sql import functions as F

from regioncount.functions import fn
from regioncount.operators import bounds, euler, fit, fit_exact, fit_iterative, fit_tiled, integerise, lattice, metrics, release
from regioncount.operators.schemas import GridSpec


def lattice_frame(spark, y, rep=None):
    rows = [(u, v, "vertex" if u % 2 and v % 2 else "edge" if u % 2 or v % 2 else "face", float(y[u, v])) for u in range(y.shape[0]) for v in range(y.shape[1])]
    return spark.createDataFrame(rows, "u int, v int, kind string, h double")


def array_of(df, side):
    out = np.zeros((side, side))
    for r in df.collect():
        out[r.u, r.v] = r.h
    return out


@pytest.mark.parametrize("area,n,tight,lemma", [(20, 10, 9, 9), (20, 20, 25, 27), (20, 30, 49, 54), (3.2, 4, 49, 54), (3.2, 20, 729, 819)])
def test_sensitivities(area, n, tight, lemma):
    spec = GridSpec(float(area), n)
    assert release.sensitivity(spec, 2.0, "add_remove") == tight
    assert release.sensitivity(spec, 2.0, "add_remove", "lemma") == lemma
    assert release.sensitivity(spec, 2.0, "replace") == 2 * tight


def test_counts_and_constraints(spark):
    spec = GridSpec(20.0, 20)
    c = {r.cls: r["count"] for r in lattice.constraints(spark, spec).groupBy("cls").count().collect()}
    assert c == {"C1": 1520, "C2": 1444, "C3": 361} and spec.counts == 1521


def test_removing_or_replacing_a_body_stays_within_the_sensitivity(spark):
    spec, rng = GridSpec(20.0, 20), np.random.default_rng(1)
    schema = "body_id long, xmin double, xmax double, ymin double, ymax double"

    def some(seed, n):
        r = np.random.default_rng(seed)
        x, y, w, h = r.uniform(0, 18, n), r.uniform(0, 18, n), r.uniform(0, 2, n), r.uniform(0, 2, n)
        return [(i, float(a), float(a + c), float(b), float(b + d)) for i, (a, b, c, d) in enumerate(zip(x, y, w, h, strict=True))]

    base = some(1, 12)
    hist = lambda rows: array_of(euler.histogram_boxes(spark.createDataFrame(rows, schema), spec), spec.side)
    full = hist(base)
    for k in range(4):
        less = base[:k] + base[k + 1 :]
        assert np.abs(full - hist(less)).sum() <= 25
        assert np.abs(full - hist([*less, (99, *some(50 + k, 1)[0][1:])])).sum() <= 50
    assert rng is not None


def test_laplace_law(spark):
    n, scale = 20000, 9.0
    draws = spark.range(n).select(fn.laplace_from_uniform(fn.uniform(F.concat(F.lit("t:"), F.col("id"))), scale).alias("y")).toPandas().y.to_numpy()
    assert abs(np.abs(draws).mean() - scale) < 0.3
    x = np.sort(draws)
    law = np.where(x < 0, 0.5 * np.exp(x / scale), 1 - 0.5 * np.exp(-x / scale))
    assert np.abs(law - (np.arange(n) + 0.5) / n).max() < 1.63 / math.sqrt(n)


def test_noise_does_not_depend_on_partitions(spark):
    h = lattice.cells(spark, GridSpec(4.0, 4)).withColumn("h", F.lit(3))
    once = {(r.u, r.v): r.h for r in release.perturb(h, 1.0, 9.0, seed="a").collect()}
    again = {(r.u, r.v): r.h for r in release.perturb(h.repartition(7), 1.0, 9.0, seed="a").collect()}
    assert once == again and once != {(r.u, r.v): r.h for r in release.perturb(h, 1.0, 9.0, seed="b").collect()}


def test_entropy_is_written_once(spark, tmp_path):
    h = lattice.cells(spark, GridSpec(4.0, 4)).withColumn("h", F.lit(3).cast("long"))
    kept = release.publish_once(release.perturb(h, 1.0, 9.0, source="os", truncate=False), str(tmp_path / "noisy"))
    assert kept.collect() == kept.collect() and kept.select("h").distinct().count() > 20


def test_ledger():
    book = release.Ledger(1.0)
    book.charge("a", 0.6, 25, "add_remove")
    with pytest.raises(ValueError):
        book.charge("b", 0.6, 25, "add_remove")
    book.charge("n", 0.4, 25, "add_remove", users="n")
    book.charge("s", 0.4, 25, "add_remove", users="s")
    assert math.isclose(book.spent(), 1.0)
    with pytest.raises(ValueError):
        release.sensitivity(GridSpec(4.0, 4), 2.0, "other")


def feasible_3x3():
    ups = fit_exact.above(3)
    v = np.array(list(itertools.product(range(4), repeat=9)))
    ok = np.ones(len(v), bool)
    for i, above in enumerate(ups):
        for j in above:
            ok &= v[:, i] <= v[:, j]
    return v[ok]


def test_l1_against_brute_force():
    best, rng = feasible_3x3(), np.random.default_rng(0)
    assert len(best) == 5424
    for _ in range(200):
        y = rng.integers(0, 4, (3, 3)).astype(float)
        x = fit_exact.l1(y)
        assert fit_iterative.violations(x) == 0
        assert np.abs(x - y).sum() == np.abs(best - y.ravel()).sum(axis=1).min()


def test_block_constraint_follows(spark):
    for x in feasible_3x3()[::50]:
        assert fit_iterative.violations(x.reshape(3, 3).astype(float)) == 0


def test_linf_changes_by_half_the_largest_violation(spark):
    rng = np.random.default_rng(2)
    ups = fit_exact.above(5)
    for _ in range(5):
        y = rng.uniform(0, 9, (5, 5))
        x = array_of(fit.linf(lattice_frame(spark, y)), 5)
        worst = max(max(y.ravel()[i] - y.ravel()[j], 0) for i, above in enumerate(ups) for j in above)
        assert fit_iterative.violations(x, 1e-12) == 0
        assert math.isclose(np.abs(x - y).max(), worst / 2, abs_tol=1e-12)


def test_fits_agree_and_are_certified(spark):
    rng, spec = np.random.default_rng(3), GridSpec(6.0, 6)
    y = np.maximum(rng.laplace(2, 25, (11, 11)), 0)
    noisy = lattice_frame(spark, y)
    made = {name: array_of(f, 11) for name, f in {"exact": fit.l1(noisy, spec, solver="exact"), "iterative": fit.l1(noisy, spec, solver="iterative"), "clip": fit.clip_down(noisy), "linf": fit.linf(noisy), "l2": fit.l2(noisy, spec)}.items()}
    cost = {k: np.abs(x - y).sum() for k, x in made.items()}
    assert all(fit_iterative.violations(x, 1e-9) == 0 for x in made.values())
    assert math.isclose(cost["exact"], cost["iterative"], rel_tol=1e-5)
    assert cost["exact"] <= min(cost.values()) + 1e-9
    assert ((made["l2"] - y) ** 2).sum() <= min(((x - y) ** 2).sum() for x in made.values()) + 1e-6
    c = fit.certificate(noisy, fit.l1(noisy, spec), spec).first()
    assert c.violations == 0 and c.gap < 1e-4
    tiled, gap, _ = fit_tiled.l1(noisy, spec, tile=6, rounds=10, inner=2, check_every=10)
    assert fit_iterative.violations(array_of(tiled, 11), 1e-9) == 0 and gap < 0.2


def test_tiles_make_the_steps_of_the_whole_lattice(spark):
    rng, spec = np.random.default_rng(5), GridSpec(5.0, 5)
    y = np.maximum(rng.laplace(0, 9, (9, 9)), 0)
    one = array_of(fit_tiled.l1(lattice_frame(spark, y), spec, tile=9, rounds=3, inner=2, check_every=5)[0], 9)
    many = array_of(fit_tiled.l1(lattice_frame(spark, y), spec, tile=5, rounds=6, inner=1, check_every=5)[0], 9)
    assert np.allclose(one, many, atol=1e-9)


def test_feasible_input_is_left_alone(spark):
    y = np.zeros((5, 5))
    y[0:3, 0:3] += 1
    noisy, spec = lattice_frame(spark, y), GridSpec(3.0, 3)
    for f in (fit.l1(noisy, spec), fit.linf(noisy), fit.clip_down(noisy), fit.l2(noisy, spec)):
        assert np.allclose(array_of(f, 5), y, atol=1e-6)


def test_rounding_keeps_the_order(spark):
    rng = np.random.default_rng(6)
    x = fit_exact.l1(np.maximum(rng.laplace(0, 9, (9, 9)), 0)) + 0.0
    r = array_of(integerise.round_counts(lattice_frame(spark, x)), 9)
    assert fit_iterative.violations(r) == 0 and np.abs(r - x).max() <= 0.5


def test_consistent_counts_may_still_answer_below_zero(spark):
    y = np.ones((5, 5))
    y[1::2, 1::2] = 0
    assert fit_iterative.violations(y) == 0
    sign = (-1.0) ** np.add.outer(np.arange(5), np.arange(5))
    assert (sign * y).sum() == -3
    assert {r.cls: r.violated for r in metrics.violations(lattice_frame(spark, y), GridSpec(3.0, 3)).collect()} == {"C1": 0, "C2": 0, "C3": 0}


def test_prior_pulls_towards_it():
    rng = np.random.default_rng(7)
    y = np.maximum(rng.laplace(0, 9, (7, 7)), 0)
    plain, pulled = fit_iterative.l1(y, 1000)[0], fit_iterative.l1(y, 1000, prior=30.0, weight=2.0)[0]
    assert np.abs(pulled - 30).mean() < np.abs(plain - 30).mean() and fit_iterative.violations(pulled, 1e-9) == 0


def test_bounds():
    assert math.isclose(bounds.total_bound(20.0, 1.0, 2.0, 1.0, 0.05), 557.9, abs_tol=0.05)
    assert math.isclose(bounds.noise_bound(25.0, 1521, 0.05), 25 * math.log(1521 / 0.05))


def test_exact_counts_are_not_published(spark, tmp_path):
    from regioncount.sources.points import publish

    h = lattice.cells(spark, GridSpec(4.0, 4)).withColumn("h", F.lit(1))
    with pytest.raises(ValueError):
        publish(h, str(tmp_path / "x"), "exact")
    publish(h.withColumn("release_id", F.lit("a")), str(tmp_path / "y"), "round")
    assert spark.read.parquet(str(tmp_path / "y")).count() == 49


@pytest.mark.parametrize("classes", [("C1",), ("C2",), ("C3",), ("C1", "C3"), ("C2", "C3"), ("C1", "C2")])
def test_fits_under_some_classes_are_feasible(classes):
    """Each class that is asked for holds, also for iterates cut off early; fewer classes cost no more than all."""
    rng = np.random.default_rng(7)
    for k in range(8):
        y = rng.normal(2, 6, (9, 9)) if k % 2 else np.rint(rng.laplace(0, 9, (7, 7)))
        for steps in (1, 30, 3000):
            x = fit_iterative.l1(y, steps, classes=classes)[0]
            assert x.min() >= 0 and all((x[lo] <= x[up]).all() for lo, up in fit_iterative._cuts(classes))
            assert "C3" not in classes or fit_iterative._blocks(x).min() >= 0
        assert np.abs(x - y).sum() <= np.abs(fit_iterative.l1(y, 3000)[0] - y).sum() * 1.001
