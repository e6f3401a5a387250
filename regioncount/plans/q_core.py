"""Queries of pre-processing, exact histograms, releases, fits, answers and baselines."""

from __future__ import annotations

import math

from pyspark.sql import functions as F

from regioncount.functions import fn
from regioncount.operators import answer, baselines, bounds, euler, fit, footprint, integerise, lattice, metrics, partition, regions, release, workload
from regioncount.operators.schemas import GridSpec
from regioncount.plans import experiments as x
from regioncount.plans import sqlapi
from regioncount.plans import sqlparts as sql
from regioncount.sources import points
from regioncount.sources.shared import cut

QUERIES: dict = {}
CORE4, EVEN20 = x.Setting("core", 4), x.Setting("even", 20)
EVEN_BODIES, CORE_BODIES = sql.bodies("even", 2.0, 20.0), sql.bodies("core", 2.0, 3.2)
EVEN_HIST = f"{EVEN_BODIES},\n{sql.hist(20, 1.0)}"
CORE_HIST = f"{CORE_BODIES},\n{sql.hist(4, 0.8)}"


def r6(df, *columns):
    """Doubles rounded to 6 decimals, without negative zeros."""
    return df.select(*[(F.round(c, 6) + F.lit(0.0)).alias(c) if df.schema[c].dataType.simpleString() == "double" else F.col(c) for c in (columns or df.columns)])


def _points(role):
    return lambda spark, d: r6(points.ROLES[role](spark, d), "user_id", "point_id", "x", "y")


for _role in x.AREAS:
    QUERIES[f"points_{_role}"] = (_points(_role), f"WITH {sql.points(_role)} SELECT user_id, point_id, round(x, 6) AS x, round(y, 6) AS y FROM points")
    QUERIES[f"bodies_box_{_role}"] = (lambda spark, d, role=_role: r6(x.bodies(spark, d, role)), f"WITH {sql.bodies(_role, 2.0, x.AREAS[_role])} SELECT body_id, round(xmin, 6) AS xmin, round(xmax, 6) AS xmax, round(ymin, 6) AS ymin, round(ymax, 6) AS ymax, n_points FROM bodies")

# ---------------------------------------------------------------- pre-processing
_LON = "(2.0::DOUBLE + x / 100.0::DOUBLE)"
_LAT = "(48.0::DOUBLE + y / 100.0::DOUBLE)"


def _project(spark, d):
    p = points.core(spark, d).select("point_id", (F.lit(2.0) + F.col("x") / 100.0).alias("lon"), (F.lit(48.0) + F.col("y") / 100.0).alias("lat"))
    p = regions.project_points(p, 2.0, 48.0).withColumn("km", fn.haversine_km(F.lit(2.0), F.lit(48.0), F.col("lon"), F.col("lat")))
    return r6(p, "point_id", "x", "y", "km")


QUERIES["project_haversine"] = (_project, f"""WITH {sql.points('core')}, g AS (SELECT point_id, {_LON} AS lon, {_LAT} AS lat FROM points)
SELECT point_id, round(radians(lon - 2.0::DOUBLE) * {fn.EARTH_KM * math.cos(math.radians(48.0))!r}::DOUBLE, 6) AS x, round(radians(lat - 48.0::DOUBLE) * {fn.EARTH_KM!r}::DOUBLE, 6) AS y,
  round({2 * fn.EARTH_KM!r}::DOUBLE * asin(sqrt(pow(sin(radians(lat - 48.0::DOUBLE) / 2), 2) + cos(radians(48.0::DOUBLE)) * cos(radians(lat)) * pow(sin(radians(lon - 2.0::DOUBLE) / 2), 2))), 6) AS km FROM g""")

_KDE_SQL = f"""WITH {sql.points('core')},
h0 AS (SELECT user_id, stddev_pop(x) * pow(count(*), -1.0 / 6) AS hx, stddev_pop(y) * pow(count(*), -1.0 / 6) AS hy FROM points GROUP BY user_id),
h AS (SELECT user_id, CASE WHEN hx > 0 THEN hx ELSE 1 END AS hx, CASE WHEN hy > 0 THEN hy ELSE 1 END AS hy FROM h0),
dens AS (SELECT p.user_id, p.point_id, p.x, p.y, round(sum(exp(-0.5 * (pow((p.x - q.x) / hx, 2) + pow((p.y - q.y) / hy, 2)))), 9) AS t FROM points p JOIN points q ON p.user_id = q.user_id JOIN h ON h.user_id = p.user_id GROUP BY p.user_id, p.point_id, p.x, p.y)
SELECT user_id, round(arg_min(x, (-t, point_id)), 6) AS mode_x, round(arg_min(y, (-t, point_id)), 6) AS mode_y FROM dens GROUP BY user_id"""
QUERIES["mode_kde"] = (lambda spark, d: r6(regions.density_mode(points.core(spark, d), "kde")), _KDE_SQL)
QUERIES["mode_kde_join"] = (lambda spark, d: r6(regions.density_mode(points.core(spark, d), "kde_sql")), _KDE_SQL)
_BIN = "bins AS (SELECT user_id, floor(x / 0.125)::BIGINT AS bx, floor(y / 0.125)::BIGINT AS by_, count(*) AS c FROM points GROUP BY user_id, bx, by_)"
QUERIES["mode_bin"] = (lambda spark, d: r6(regions.density_mode(points.core(spark, d), "bin")), f"WITH {sql.points('core')}, {_BIN} SELECT user_id, (arg_max(bx, (c, -bx, -by_)) + 0.5::DOUBLE) * 0.125::DOUBLE AS mode_x, (arg_max(by_, (c, -bx, -by_)) + 0.5::DOUBLE) * 0.125::DOUBLE AS mode_y FROM bins GROUP BY user_id")
QUERIES["mode_binned"] = (lambda spark, d: r6(regions.density_mode(points.core(spark, d), "binned")), f"""WITH {sql.points('core')}, {_BIN},
spread AS (SELECT user_id, bx + i AS bx, by_ + j AS by_, c * exp(-0.5::DOUBLE * (i * i + j * j)) AS t FROM bins, range(-3, 4) a(i), range(-3, 4) b(j)),
dens AS (SELECT user_id, bx, by_, round(sum(t), 9) AS t FROM spread SEMI JOIN bins USING (user_id, bx, by_) GROUP BY user_id, bx, by_)
SELECT user_id, (arg_max(bx, (t, -bx, -by_)) + 0.5::DOUBLE) * 0.125::DOUBLE AS mode_x, (arg_max(by_, (t, -bx, -by_)) + 0.5::DOUBLE) * 0.125::DOUBLE AS mode_y FROM dens GROUP BY user_id""")
QUERIES["mode_mean"] = (lambda spark, d: r6(regions.density_mode(points.even(spark, d), "mean")), f"WITH {sql.points('even')} SELECT user_id, round(avg(x), 6) AS mode_x, round(avg(y), 6) AS mode_y FROM points GROUP BY user_id")
QUERIES["mode_medoid"] = (lambda spark, d: r6(regions.density_mode(points.core(spark, d), "medoid")), f"""WITH {sql.points('core')},
t AS (SELECT p.user_id, p.point_id, p.x, p.y, round(sum(sqrt((p.x - q.x) * (p.x - q.x) + (p.y - q.y) * (p.y - q.y))), 9) AS t FROM points p JOIN points q USING (user_id) GROUP BY p.user_id, p.point_id, p.x, p.y)
SELECT user_id, round(arg_min(x, (t, point_id)), 6) AS mode_x, round(arg_min(y, (t, point_id)), 6) AS mode_y FROM t GROUP BY user_id""")

_MODES = "modes AS (SELECT user_id, median(x) AS mode_x, median(y) AS mode_y FROM points GROUP BY user_id)"
_NEAR = "near AS (SELECT p.*, mode_x, mode_y, row_number() OVER (PARTITION BY p.user_id ORDER BY round(sqrt((x - mode_x) * (x - mode_x) + (y - mode_y) * (y - mode_y)), 9), ts, point_id, x, y) AS rank FROM points p JOIN modes USING (user_id))"


def _nearest(k):
    def run(spark, d):
        p = points.core(spark, d)
        return regions.nearest_to_mode(p, regions.density_mode(p), k).select("user_id", "point_id", F.col("rank").cast("long").alias("rank"))

    return run


QUERIES["nearest_k"] = (_nearest(40), f"WITH {sql.points('core')}, {_MODES}, {_NEAR} SELECT user_id, point_id, rank::BIGINT AS rank FROM near WHERE rank <= 40")
QUERIES["nearest_all"] = (_nearest(None), f"WITH {sql.points('core')}, {_MODES}, {_NEAR} SELECT user_id, point_id, rank::BIGINT AS rank FROM near")


def _trim(rule):
    def run(spark, d):
        p = points.even(spark, d)
        return regions.trim(regions.with_modes(p, regions.density_mode(p)), 2.0, rule, 20.0).select("user_id", "point_id")

    return run


_IN = "x >= 0 AND x < 20 AND y >= 0 AND y < 20"
QUERIES["trim_disc"] = (_trim("disc"), f"WITH {sql.points('even')}, {_MODES} SELECT user_id, point_id FROM points JOIN modes USING (user_id) WHERE (x - mode_x) * (x - mode_x) + (y - mode_y) * (y - mode_y) <= 1.0 AND {_IN}")
QUERIES["trim_bbox"] = (_trim("bbox"), f"WITH {EVEN_BODIES} SELECT user_id, point_id FROM kept")


def hulls(spark, d, role="core", k=None):
    return regions.extract_bodies(points.ROLES[role](spark, d), 2.0, x.AREAS[role], k=k, rule="disc", shape="hull")


_DISC = f"disc AS (SELECT DISTINCT user_id, x, y FROM points JOIN modes USING (user_id) WHERE (x - mode_x) * (x - mode_x) + (y - mode_y) * (y - mode_y) <= 1.0 AND x >= 0 AND x < 3.2 AND y >= 0 AND y < 3.2)"
#: A pair (a, b) is a side of the hull if no third point is on its right, or beyond b on its line.
_SIDES = """sides AS (SELECT a.user_id, a.x AS ax, a.y AS ay, b.x AS bx, b.y AS by_ FROM disc a JOIN disc b ON a.user_id = b.user_id AND (a.x <> b.x OR a.y <> b.y)
  WHERE NOT EXISTS (SELECT 1 FROM disc c WHERE c.user_id = a.user_id AND ((b.x - a.x) * (c.y - a.y) - (b.y - a.y) * (c.x - a.x) < 0
    OR (b.x - a.x) * (c.y - a.y) - (b.y - a.y) * (c.x - a.x) = 0 AND (c.x - b.x) * (b.x - a.x) + (c.y - b.y) * (b.y - a.y) > 0)))"""
QUERIES["bodies_hull_core"] = (
    lambda spark, d: hulls(spark, d).select("body_id", F.size("hull").cast("long").alias("corners"), F.round(fn.hull_perimeter(F.col("hull")), 6).alias("perimeter")),
    f"WITH {sql.points('core')}, {_MODES}, {_DISC}, {_SIDES} SELECT user_id AS body_id, count(*) AS corners, round(sum(sqrt((bx - ax) * (bx - ax) + (by_ - ay) * (by_ - ay))), 6) AS perimeter FROM sides GROUP BY user_id",
)
QUERIES["hull_measures"] = (
    lambda spark, d: hulls(spark, d).select("body_id", F.round(fn.hull_area(F.col("hull")), 6).alias("area"), F.round(fn.hull_diameter(F.col("hull")), 6).alias("diameter"), F.round(F.col("xmin"), 6).alias("xmin"), F.round(F.col("xmax"), 6).alias("xmax")),
    f"""WITH {sql.points('core')}, {_MODES}, {_DISC}, {_SIDES},
area AS (SELECT user_id, abs(sum(ax * by_ - bx * ay)) / 2 AS area FROM sides GROUP BY user_id),
far AS (SELECT a.user_id, max(sqrt((a.x - b.x) * (a.x - b.x) + (a.y - b.y) * (a.y - b.y))) AS diameter, min(a.x) AS xmin, max(a.x) AS xmax FROM disc a JOIN disc b USING (user_id) GROUP BY a.user_id)
SELECT user_id AS body_id, round(area, 6) AS area, round(diameter, 6) AS diameter, round(xmin, 6) AS xmin, round(xmax, 6) AS xmax FROM area JOIN far USING (user_id)""",
)
QUERIES["hull_kde_chain"] = (lambda spark, d: r6(regions.extract_bodies(points.core(spark, d), 2.0, 3.2, k=40, mode="kde", rule="disc", shape="hull").drop("hull")), None)

# ---------------------------------------------------------------- lattice and exact histograms
def _lattice(spark, d):
    """All nodes, with the points in the square of half a cell that each stands for."""
    s = EVEN20.spec
    p = points.even(spark, d).filter((F.col("x") >= 0) & (F.col("x") < s.area) & (F.col("y") >= 0) & (F.col("y") < s.area))
    counted = p.groupBy(fn.cell_index(F.col("y"), s.d / 2, s.side).alias("u"), fn.cell_index(F.col("x"), s.d / 2, s.side).alias("v")).agg(F.count(F.lit(1)).alias("points"))
    return lattice.cells(spark, s).join(counted, ["u", "v"], "left").select("u", "v", "kind", F.coalesce("points", F.lit(0)).alias("points"))


_half = lambda c: f"least(greatest(floor({c} / 0.5::DOUBLE), 0), 38)::INTEGER"
QUERIES["lattice_n20"] = (_lattice, f"""WITH {sql.points('even')}, {sql.lattice(20)}, c AS (SELECT {_half('y')} AS u, {_half('x')} AS v, count(*) AS points FROM points WHERE x >= 0 AND x < 20 AND y >= 0 AND y < 20 GROUP BY 1, 2)
SELECT u, v, kind, coalesce(points, 0)::BIGINT AS points FROM lattice LEFT JOIN c USING (u, v)""")


def _constraints(spark, d):
    """All constraints, with the exact counts of their two nodes."""
    hist = cut(x.exact(spark, d, EVEN20))
    at = lambda c: hist.select(F.col("u").alias(f"{c}_u"), F.col("v").alias(f"{c}_v"), F.col("h").alias(c))
    return lattice.constraints(spark, EVEN20.spec).join(at("lo"), ["lo_u", "lo_v"]).join(at("hi"), ["hi_u", "hi_v"]).select("cls", "lo_u", "lo_v", "hi_u", "hi_v", "lo", "hi")


QUERIES["constraints_n20"] = (_constraints, f"WITH {EVEN_HIST}, {sql.constraints(20)} SELECT cls, lo_u, lo_v, hi_u, hi_v, a.h AS lo, b.h AS hi FROM cons JOIN hist a ON a.u = lo_u AND a.v = lo_v JOIN hist b ON b.u = hi_u AND b.v = hi_v")
QUERIES["box_runs"] = (
    lambda spark, d: footprint.box_runs(x.bodies(spark, d, "even"), GridSpec(20.0, 20)),
    f"WITH {EVEN_BODIES}, {sql.boxes(20, 1.0)} SELECT body_id, unnest(range(2 * r0, 2 * r1 + 1))::INTEGER AS u, (2 * c0)::INTEGER AS vlo, (2 * c1)::INTEGER AS vhi FROM boxes",
)
_EXACT_SQL = f"WITH {EVEN_HIST} SELECT u, v, kind, h FROM hist"
QUERIES["euler_explode"] = (lambda spark, d: euler.histogram(footprint.box_runs(x.bodies(spark, d, "even"), GridSpec(20.0, 20)), GridSpec(20.0, 20), "explode"), _EXACT_SQL)
QUERIES["euler_runs"] = (lambda spark, d: euler.histogram(footprint.box_runs(x.bodies(spark, d, "even"), GridSpec(20.0, 20)), GridSpec(20.0, 20), "runs"), _EXACT_SQL)
QUERIES["euler_corners"] = (lambda spark, d: x.exact(spark, d, EVEN20), _EXACT_SQL)
QUERIES["euler_hull"] = (lambda spark, d: euler.histogram_hulls(hulls(spark, d), GridSpec(3.2, 4)), None)
_XC, _YC = (1.0, 2.5, 4.0, 9.0, 15.0), (3.0, 7.5, 12.0)


def _rect(spark, d):
    cells = partition.RectPartition(_XC, _YC).box_cells(x.bodies(spark, d, "even"))
    return cells.groupBy("r0", "r1", "c0", "c1").agg(F.count(F.lit(1)).alias("bodies"))


_cut = lambda c, cuts: "(" + " + ".join(f"({v!r}::DOUBLE <= {c})::INTEGER" for v in cuts) + ")"
QUERIES["euler_rect_partition"] = (_rect, f"WITH {EVEN_BODIES} SELECT {_cut('ymin', _YC)} AS r0, {_cut('ymax', _YC)} AS r1, {_cut('xmin', _XC)} AS c0, {_cut('xmax', _XC)} AS c1, count(*) AS bodies FROM bodies GROUP BY 1, 2, 3, 4")
SITES = [(0.4, 0.5), (1.2, 0.7), (2.3, 0.4), (2.8, 1.3), (1.7, 1.6), (0.6, 1.7), (0.5, 2.7), (1.6, 2.6), (2.6, 2.5)]


def _voronoi(spark, d):
    parts = partition.components(partition.voronoi(SITES, 3.2))
    table = partition.complex_table(spark, parts)
    return partition.histogram_general(hulls(spark, d), table, 0.8).withColumn("sensitivity", F.lit(release.sensitivity_general(table, 2.0)))


QUERIES["euler_voronoi"] = (_voronoi, None)
QUERIES["density_map"] = (lambda spark, d: metrics.density(x.exact(spark, d, EVEN20)), f"WITH {EVEN_HIST} SELECT (u // 2)::INTEGER AS r, (v // 2)::INTEGER AS c, h AS bodies FROM hist WHERE kind = 'face'")

# ---------------------------------------------------------------- release
_GRIDS = [("2 km", 20.0, 10), ("1 km", 20.0, 20), ("0.66 km", 20.0, 30), ("0.8 km", 3.2, 4), ("0.16 km", 3.2, 20)]
_ROLE_OF = {20.0: "even", 3.2: "core"}
_TOUCHED = " UNION ALL ".join(f"SELECT '{g}' AS grid, max((2 * (r1 - r0) + 1) * (2 * (c1 - c0) + 1))::BIGINT AS touched FROM (WITH {sql.bodies(_ROLE_OF[a], 2.0, a)}, {sql.boxes(n, a / n)} SELECT * FROM boxes)" for g, a, n in _GRIDS)


def _sensitivities(spark, d):
    rows = [(name, GridSpec(a, n).span(2.0), *[release.sensitivity(GridSpec(a, n), 2.0, adj, form) for adj in release.ADJACENCY for form in ("tight", "lemma")], release.sensitivity(GridSpec(a, n), 2.0, "add_remove", "unbounded")) for name, a, n in _GRIDS]
    table = spark.createDataFrame(rows, "grid string, k int, tight double, lemma double, tight_replace double, lemma_replace double, unbounded double")
    # beside the bounds: the most counts that a body of the tables touches on each grid
    made, found = {role: cut(x.bodies(spark, d, role)) for role in ("even", "core")}, None
    for name, a, n in _GRIDS:
        cells = footprint.box_cells(made[_ROLE_OF[a]], GridSpec(a, n))
        most = cells.agg(F.max((2 * (F.col("r1") - F.col("r0")) + 1) * (2 * (F.col("c1") - F.col("c0")) + 1)).cast("long").alias("touched")).select(F.lit(name).alias("grid"), "touched")
        found = most if found is None else found.union(most)
    return table.join(found, "grid")


QUERIES["sensitivity_table"] = (_sensitivities, f"""WITH g(grid, area, n) AS (VALUES {', '.join(f"('{g}', {a}::DOUBLE, {n})" for g, a, n in _GRIDS)}),
k AS (SELECT grid, n, ceil(round(2.0 / (area / n), 9))::INTEGER AS k FROM g), most AS ({_TOUCHED})
SELECT grid, touched, k, (4 * k * (k + 1) + 1)::DOUBLE AS tight, 4.5::DOUBLE * k * (k + 1) AS lemma, 2 * (4 * k * (k + 1) + 1)::DOUBLE AS tight_replace, 9.0::DOUBLE * k * (k + 1) AS lemma_replace, ((2 * n - 1) * (2 * n - 1))::DOUBLE AS unbounded FROM k JOIN most USING (grid)""")
_noise = lambda spark, d, **kw: r6(release.perturb(x.exact(spark, d, CORE4), 1.0, 49.0, seed="q", reps=20, **kw), "rep", "u", "v", "kind", "h")
QUERIES["noise_laplace"] = (_noise, f"WITH {CORE_HIST}, {sql.noisy(49.0, 'q', 20)} SELECT rep, u, v, kind, round(h, 6) AS h FROM noisy")
QUERIES["noise_untruncated"] = (lambda spark, d: _noise(spark, d, truncate=False), f"WITH {CORE_HIST}, {sql.noisy(49.0, 'q', 20, truncate=False)} SELECT rep, u, v, kind, round(h, 6) AS h FROM noisy")
_UA, _UB = (sql.u(f"'q{t}:' || rep || ':' || u || ':' || v") for t in "ab")
QUERIES["noise_geometric"] = (lambda spark, d: _noise(spark, d, noise="geometric"), f"WITH {CORE_HIST} SELECT rep::INTEGER AS rep, u, v, kind, greatest(h + (floor(ln({_UA}) / {-1 / 49!r}::DOUBLE) - floor(ln({_UB}) / {-1 / 49!r}::DOUBLE)), 0)::DOUBLE AS h FROM hist, range(20) r(rep)")
QUERIES["noise_entropy"] = (lambda spark, d: release.perturb(x.exact(spark, d, CORE4), 1.0, 49.0, source="os"), None)


def _ledger(spark, d):
    """A release of all users' orders for each year, and of each third of the users for the years that it has."""
    years = points.table(spark, d, "orders").select(F.year("o_orderdate").alias("y"), F.pmod("o_custkey", F.lit(3)).alias("g")).distinct()
    found = sorted(tuple(r) for r in years.filter("y is not null and g is not null").collect())
    book = release.Ledger(10.0)
    for y in sorted({y for y, _ in found}):
        book.charge(f"{y}-all", 0.125, 25, "add_remove")
    for y, g in found:
        book.charge(f"{y}-{g}", 0.25 * (g + 1), 50, "replace", users=str(g))
    return book.table(spark).withColumn("spent", F.lit(book.spent()))


QUERIES["ledger_compose"] = (_ledger, """WITH y AS (SELECT DISTINCT year(o_orderdate) AS y, o_custkey % 3 AS g FROM orders WHERE o_orderdate IS NOT NULL AND o_custkey IS NOT NULL),
r AS (SELECT DISTINCT y || '-all' AS release_id, 0.125::DOUBLE AS epsilon, 25.0::DOUBLE AS sensitivity, 'add_remove' AS adjacency, -1 AS g FROM y UNION ALL SELECT y || '-' || g, 0.25::DOUBLE * (g + 1), 50.0, 'replace', g FROM y),
s AS (SELECT g, sum(epsilon) AS e FROM r GROUP BY g), t AS (SELECT (SELECT e FROM s WHERE g = -1) + (SELECT max(e) FROM s WHERE g >= 0) AS spent)
SELECT release_id, epsilon, sensitivity, adjacency, 'laplace' AS noise, spent FROM r, t""")


def _card(spark, d):
    """The card of a release of the tables' bodies: a grid of 1 km over all of them, and their number."""
    found = cut(x.bodies(spark, d, "even")).agg(F.ceil(F.max(F.greatest("xmax", "ymax"))).cast("int").alias("n"), F.count(F.lit(1)).alias("bodies")).first()
    n = found.n or 1
    return release.release_card(spark, GridSpec(float(n), n), 2.0, 1.0).withColumn("bodies", F.lit(found.bodies).cast("long"))


QUERIES["release_card"] = (_card, f"""WITH {EVEN_BODIES}, b AS (SELECT ceil(max(greatest(xmax, ymax)))::INTEGER AS n, count(*) AS bodies FROM bodies)
SELECT n, 2::INTEGER AS k, ((2 * n - 1) * (2 * n - 1))::DOUBLE AS counts, 25.0::DOUBLE AS tight, 27.0::DOUBLE AS lemma, 25.0::DOUBLE AS scale, (4 * n * (n - 1))::INTEGER AS c1, (4 * (n - 1) * (n - 1))::INTEGER AS c2, ((n - 1) * (n - 1))::INTEGER AS c3, bodies FROM b""")
_BOUNDS = [(d, e) for d in (0.01, 0.05, 0.5) for e in (0.1, 1.0)]


def _bounds(spark, d):
    """The bounds, and the largest change that noise makes on the tables' exact counts."""
    rows = [(dl, e, bounds.noise_bound(25 / e, 1521, dl), bounds.fit_bound(25 / e, 1521, dl), bounds.total_bound(20.0, 1.0, 2.0, e, dl)) for dl, e in _BOUNDS]
    table, hist, found = spark.createDataFrame(rows, "delta double, epsilon double, noise double, fit double, total double"), cut(x.exact(spark, d, EVEN20)), None
    for e in sorted({e for _, e in _BOUNDS}):
        noisy = release.perturb(hist.withColumn("x", F.col("h")), e, 25.0, seed="bounds")
        worst = noisy.agg(F.max(F.abs(F.col("h") - F.col("x"))).alias("worst")).select(F.lit(e).alias("epsilon"), "worst")
        found = worst if found is None else found.union(worst)
    return r6(table.join(found, "epsilon"))


_WORST = " UNION ALL ".join(f"SELECT {e}::DOUBLE AS epsilon, max(abs(n.h - x.h)) AS worst FROM {t} n JOIN hist x USING (u, v)" for e, t in ((0.1, "low"), (1.0, "high")))
QUERIES["bounds_table"] = (
    _bounds,
    f"""WITH {EVEN_HIST}, {sql.noisy(250.0, 'bounds', 1, name='low')}, {sql.noisy(25.0, 'bounds', 1, name='high')}, w AS ({_WORST})
SELECT delta, epsilon, round(25 / epsilon * ln(1521 / delta), 6) AS noise, round(25 / epsilon * ln(1521 / delta), 6) AS fit, round(54 / epsilon * ln(1521 / delta) + 0.5, 6) AS total, round(worst, 6) AS worst FROM (VALUES {', '.join(f'({a}::DOUBLE, {b}::DOUBLE)' for a, b in _BOUNDS)}) t(delta, epsilon) JOIN w USING (epsilon)""",
)

# ---------------------------------------------------------------- fit and rounding
_CORE_NOISY = f"{CORE_HIST},\n{sql.noisy(49.0, 'q', 20)}"


def core_noisy(spark, d, reps=20):
    return cut(release.perturb(x.exact(spark, d, CORE4), 1.0, 49.0, seed="q", reps=reps).select("rep", "u", "v", "kind", "h"))


REP = ["rep"]
QUERIES["fit_linf"] = (lambda spark, d: r6(fit.linf(core_noisy(spark, d), REP)), f"WITH {_CORE_NOISY}, {sql.linf()} SELECT rep, u, v, kind, round(h, 6) AS h FROM fitted")
QUERIES["fit_clip_down"] = (lambda spark, d: r6(fit.clip_down(core_noisy(spark, d), REP)), f"WITH {_CORE_NOISY}, {sql.clip()} SELECT rep, u, v, kind, round(h, 6) AS h FROM clipped")
QUERIES["round_linf"] = (lambda spark, d: integerise.round_counts(fit.linf(core_noisy(spark, d), REP)), f"WITH {_CORE_NOISY}, {sql.linf()}, {sql.rounded()} SELECT rep, u, v, kind, h FROM rounded")
_S4 = CORE4.spec
QUERIES["fit_l1"] = (lambda spark, d: r6(fit.l1(core_noisy(spark, d), _S4, REP)), None)
QUERIES["fit_l1_iterative"] = (lambda spark, d: r6(fit.l1(core_noisy(spark, d), _S4, REP, solver="iterative")), None)
QUERIES["fit_l1_prior"] = (lambda spark, d: r6(fit.l1(core_noisy(spark, d), _S4, REP, prior=10.0, weight=0.5)), None)
QUERIES["fit_l1_c3_only"] = (lambda spark, d: r6(fit.l1(core_noisy(spark, d), _S4, REP, classes=("C3",))), None)
QUERIES["fit_l1_tiled"] = (lambda spark, d: _tiled(spark, d), None)
QUERIES["fit_l2"] = (lambda spark, d: r6(fit.l2(core_noisy(spark, d), _S4, REP)), None)
QUERIES["round_l1"] = (lambda spark, d: integerise.round_counts(fit.l1(core_noisy(spark, d), _S4, REP)), None)


def _certificate(spark, d):
    noisy = core_noisy(spark, d)
    return r6(fit.certificate(noisy, fit.l1(noisy, _S4, REP), _S4, REP))


QUERIES["fit_l1_certificate"] = (_certificate, None)


def _tiled(spark, d):
    from regioncount.operators import fit_tiled

    noisy = core_noisy(spark, d, reps=1).drop("rep")
    fitted, gap, rounds = fit_tiled.l1(noisy, _S4, tile=4, rounds=20, inner=1)
    return r6(fitted.withColumn("gap", F.lit(gap)).withColumn("rounds", F.lit(rounds)))


def _program(norm):
    def run(spark, d):
        rows = fit.program(x.exact(spark, d, CORE4), lattice.constraints(spark, _S4), norm)
        return rows.groupBy(F.split("constraint", ":")[0].alias("family")).agg(F.countDistinct("constraint").alias("constraints"), F.count(F.lit(1)).alias("terms"), F.round(F.sum("coef"), 6).alias("coefs"), F.round(F.sum("rhs"), 6).alias("rhs"))

    return run


_PROGRAM_SQL = f"""WITH {CORE_HIST}, {sql.constraints(4)}, t AS (SELECT sum(h)::DOUBLE AS s FROM hist)
SELECT 'over' AS family, 49::BIGINT AS constraints, 98::BIGINT AS terms, 0.0::DOUBLE AS coefs, 2 * s AS rhs FROM t UNION ALL SELECT 'under', 49, 98, -98.0, -2 * s FROM t UNION ALL SELECT 'sign', 49, 49, -49.0, 0.0
UNION ALL SELECT cls, count(*), 2 * count(*), 0.0, 0.0 FROM cons WHERE cls <> 'C3' GROUP BY cls UNION ALL SELECT cls, count(*), 9 * count(*), -1.0 * count(*), 0.0 FROM cons WHERE cls = 'C3' GROUP BY cls"""
QUERIES["fit_program_l1"] = (_program("l1"), _PROGRAM_SQL)
QUERIES["fit_program_linf"] = (_program("linf"), _PROGRAM_SQL)

ALL4 = [(100.0 * r * c / 16, r, c) for r in range(1, 5) for c in range(1, 5)]


def q4(spark):
    return workload.positions(spark, 4, ALL4)


_Q4 = sql.positions(4, ALL4)


def _covert(spark, d):
    made = integerise.round_counts(fit.linf(core_noisy(spark, d), REP))
    return integerise.check_covert(made, _S4, q4(spark), REP)


QUERIES["covert_check"] = (_covert, f"""WITH {_CORE_NOISY}, {sql.linf()}, {sql.rounded()}, {sql.constraints(4)}, {sql.violated('rounded', 'vio')}, {_Q4}, {sql.answers('rounded', 'ans')},
f AS (SELECT rep, min(h) >= 0 AS non_negative FROM rounded GROUP BY rep), b AS (SELECT rep, sum(violated)::BIGINT AS violated FROM vio GROUP BY rep), n AS (SELECT rep, round(avg((est < -1e-9)::INTEGER), 6) AS negative_answers FROM ans GROUP BY rep)
SELECT rep, true AS integer, non_negative, violated, negative_answers FROM f JOIN b USING (rep) JOIN n USING (rep)""")
QUERIES["violations"] = (lambda spark, d: r6(metrics.violations(core_noisy(spark, d), _S4, REP)), f"WITH {_CORE_NOISY}, {sql.constraints(4)}, {sql.violated('noisy', 'vio')} SELECT rep, cls, members, violated, round(100.0 * violated / members, 6) AS pct FROM vio")
QUERIES["properties"] = (
    lambda spark, d: metrics.properties(core_noisy(spark, d), _S4, REP),
    f"WITH {_CORE_NOISY}, {sql.constraints(4)}, {sql.violated('noisy', 'vio')}, f AS (SELECT rep, max(abs(h - round(h))) = 0 AS integers, min(h) >= 0 AS non_negative FROM noisy GROUP BY rep) SELECT rep, integers, non_negative, sum(violated) = 0 AS consistent FROM f JOIN vio USING (rep) GROUP BY rep, integers, non_negative",
)


def _distance(spark, d):
    noisy = core_noisy(spark, d)
    return r6(metrics.relative_distance(x.exact(spark, d, CORE4), noisy, fit.linf(noisy, REP), REP))


QUERIES["relative_distance"] = (_distance, f"WITH {_CORE_NOISY}, {sql.linf()} SELECT n.rep, round(100.0 * sum(abs(f.h - x.h)) / sum(abs(n.h - x.h)), 6) AS rel_distance FROM noisy n JOIN fitted f USING (rep, u, v) JOIN hist x USING (u, v) GROUP BY n.rep")

# ---------------------------------------------------------------- answers
_ANSWER_SQL = f"WITH {CORE_HIST}, {_Q4}, {sql.answers('hist', 'ans', keyed=False)} SELECT q_id, est::BIGINT AS est FROM ans"
_TRUE = "SELECT q_id, count(DISTINCT body_id)::BIGINT AS {} FROM queries_ q LEFT JOIN boxes b ON b.r0 <= q.r1 AND b.r1 >= q.r0 AND b.c0 <= q.c1 AND b.c1 >= q.c0 GROUP BY q_id"
_TRUE_SQL = f"WITH {CORE_BODIES}, {sql.boxes(4, 0.8)}, {_Q4} {_TRUE.format('est')}"
QUERIES["answer_sum"] = (lambda spark, d: answer.by_sum(x.exact(spark, d, CORE4), q4(spark)), _TRUE_SQL)
QUERIES["answer_prefix"] = (lambda spark, d: answer.by_prefix(answer.prefix(x.exact(spark, d, CORE4)), q4(spark)), _TRUE_SQL)
QUERIES["answer_true"] = (lambda spark, d: answer.true_count(footprint.box_runs(x.bodies(spark, d, "core"), _S4), q4(spark)).withColumnRenamed("truth", "est"), _ANSWER_SQL)
_RECTS = [(1, 0.1, 0.9, 0.0, 1.6), (2, 0.8, 1.6, 0.8, 3.2), (3, 1.1, 1.2, 2.5, 2.6), (4, 0.0, 3.2, 0.0, 3.2)]


def _snap(spark, d):
    rects = spark.createDataFrame([(i, *map(float, r)) for i, *r in _RECTS], "q_id long, x0 double, x1 double, y0 double, y1 double")
    q = answer.snap(rects, GridSpec(3.2, 4))
    return answer.by_prefix(answer.prefix(x.exact(spark, d, CORE4)), q).join(q, "q_id").select("q_id", "r0", "r1", "c0", "c1", "est")


_floor = lambda c: f"greatest(floor({c} / 0.8::DOUBLE), 0)::INTEGER"
_ceil = lambda a, b: f"least(greatest(ceil({a} / 0.8::DOUBLE) - 1, floor({b} / 0.8::DOUBLE)), 3)::INTEGER"
QUERIES["answer_snap"] = (_snap, f"""WITH {CORE_BODIES}, {sql.boxes(4, 0.8)}, rects(q_id, x0, x1, y0, y1) AS (VALUES {', '.join(f'({i}::BIGINT, ' + ', '.join(f'{v}::DOUBLE' for v in r) + ')' for i, *r in _RECTS)}),
queries_ AS (SELECT q_id, {_floor('y0')} AS r0, {_ceil('y1', 'y0')} AS r1, {_floor('x0')} AS c0, {_ceil('x1', 'x0')} AS c1 FROM rects), t AS ({_TRUE.format('est')})
SELECT q_id, r0, r1, c0, c1, est FROM queries_ JOIN t USING (q_id)""")


def _mask(spark, d):
    cells = spark.createDataFrame([(r, c) for r in range(3) for c in range(1, 3)], "r int, c int")
    return answer.by_mask(x.exact(spark, d, CORE4), cells)


QUERIES["answer_mask"] = (_mask, f"WITH {CORE_BODIES}, {sql.boxes(4, 0.8)} SELECT count(*)::BIGINT AS est FROM boxes WHERE r0 <= 2 AND c0 <= 2 AND c1 >= 1")


def _interval(spark, d):
    noisy = release.perturb(x.exact(spark, d, CORE4), 1.0, 49.0, seed="q0", truncate=False)
    return r6(answer.with_interval(answer.by_prefix(answer.prefix(noisy), q4(spark)), q4(spark), 49.0))


QUERIES["answer_interval"] = (_interval, f"""WITH {CORE_HIST}, {sql.noisy(49.0, 'q0', 1, truncate=False)}, {_Q4}, {sql.answers('noisy', 'ans')},
t AS (SELECT q_id, est, (2 * (r1 - r0) + 1) * (2 * (c1 - c0) + 1) AS terms FROM ans JOIN queries_ USING (q_id))
SELECT q_id, round(est, 6) AS est, terms::INTEGER AS terms, round(49 * sqrt(2.0 * terms), 6) AS sd, round(est - 1.96 * 49 * sqrt(2.0 * terms), 6) AS lo, round(est + 1.96 * 49 * sqrt(2.0 * terms), 6) AS hi, round(49 * terms * ln(terms / 0.05), 6) AS union_bound FROM t""")


def _udtf(spark, d):
    sqlapi.register(spark, x.exact(spark, d, CORE4), _S4, "core_release")
    return spark.sql("SELECT q.q_id, c.est FROM (SELECT CAST(id AS BIGINT) AS q_id, CAST(id % 4 AS INT) AS r FROM range(4)) q, LATERAL region_count(0, q.r, 1, 3) c")


QUERIES["answer_udtf"] = (_udtf, f"WITH {CORE_BODIES}, {sql.boxes(4, 0.8)} SELECT q AS q_id, (SELECT count(*) FROM boxes WHERE r0 <= q AND c1 >= 1)::DOUBLE AS est FROM range(4) t(q)")

# ---------------------------------------------------------------- baselines
_FACES = "faces AS (SELECT u, v, kind, CASE WHEN kind = 'face' THEN h ELSE 0 END AS h FROM hist)"
QUERIES["cell_sum"] = (lambda spark, d: baselines.cell_sum(x.exact(spark, d, CORE4), q4(spark)), f"WITH {CORE_HIST}, {_FACES}, {_Q4}, {sql.answers('faces', 'ans', keyed=False)} SELECT q_id, est::BIGINT AS est FROM ans")
QUERIES["cell_sum_private"] = (
    lambda spark, d: r6(baselines.cell_sum_private(x.exact(spark, d, CORE4), q4(spark), _S4, 2.0, 1.0)),
    f"WITH {CORE_HIST}, {sql.noisy(16.0, 'cells', 1, name='n0')}, noisy AS (SELECT rep, u, v, kind, CASE WHEN kind = 'face' THEN h ELSE 0 END AS h FROM n0), {_Q4}, {sql.answers('noisy', 'ans')} SELECT q_id, round(est, 6) + 0.0::DOUBLE AS est FROM ans",
)
_CENTRE = "pts AS (SELECT 2 * least(greatest(floor((ymin + ymax) / 2 / 0.8::DOUBLE), 0), 3)::INTEGER AS u, 2 * least(greatest(floor((xmin + xmax) / 2 / 0.8::DOUBLE), 0), 3)::INTEGER AS v, count(*) AS c FROM bodies GROUP BY 1, 2)"
_PHIST = f"{CORE_BODIES}, {sql.lattice(4)}, {_CENTRE}, phist AS (SELECT l.u, l.v, l.kind, coalesce(c, 0)::BIGINT AS h FROM lattice l LEFT JOIN pts USING (u, v))"
QUERIES["point_count"] = (lambda spark, d: baselines.point_count(x.bodies(spark, d, "core"), q4(spark), _S4), f"WITH {_PHIST}, {_Q4}, {sql.answers('phist', 'ans', keyed=False)} SELECT q_id, est::BIGINT AS est FROM ans")
QUERIES["point_count_private"] = (
    lambda spark, d: r6(baselines.point_count_private(x.bodies(spark, d, "core"), q4(spark), _S4, 1.0)),
    f"WITH {_PHIST}, {sql.noisy(1.0, 'points', 1, source='phist', name='n0')}, noisy AS (SELECT rep, u, v, kind, CASE WHEN kind = 'face' THEN h ELSE 0 END AS h FROM n0), {_Q4}, {sql.answers('noisy', 'ans')} SELECT q_id, round(est, 6) + 0.0::DOUBLE AS est FROM ans",
)
_IX = sql.u("'interactive:' || q_id")
QUERIES["interactive_private"] = (
    lambda spark, d: r6(baselines.interactive(answer.by_prefix(answer.prefix(x.exact(spark, d, CORE4)), q4(spark)), 1.0, 100)),
    f"WITH {CORE_HIST}, {_Q4}, {sql.answers('hist', 'ans', keyed=False)} SELECT q_id, round(est + -100.0::DOUBLE * sign({_IX} - 0.5) * ln(1 - 2 * abs({_IX} - 0.5)), 6) AS est FROM ans",
)
QUERIES["unbounded_noise"] = (
    lambda spark, d: r6(release.perturb(x.exact(spark, d, CORE4), 1.0, release.sensitivity(_S4, 2.0, "add_remove", "unbounded"), seed="q", reps=5), "rep", "u", "v", "kind", "h"),
    f"WITH {CORE_HIST}, {sql.noisy(49.0, 'q', 5)} SELECT rep, u, v, kind, round(h, 6) AS h FROM noisy",
)


def _extra(spark, d):
    noisy = core_noisy(spark, d)
    truth = answer.by_prefix(answer.prefix(x.exact(spark, d, CORE4)), q4(spark)).withColumnRenamed("est", "truth")
    a = answer.by_prefix(answer.prefix(noisy, REP), q4(spark), REP).join(truth, "q_id").join(q4(spark).select("q_id", "shape_r", "shape_c"), "q_id")
    return r6(metrics.extra(a, ["shape_r", "shape_c"]))


QUERIES["extra_measures"] = (_extra, f"""WITH {_CORE_NOISY}, {_Q4}, {sql.answers('noisy', 'ans')}, {sql.answers('hist', 'tru', keyed=False)},
e AS (SELECT shape_r, shape_c, a.est, t.est AS truth, a.est - t.est AS gap, abs(a.est - t.est) / greatest(t.est::DOUBLE, 1.0) AS rel FROM ans a JOIN tru t USING (q_id) JOIN queries_ USING (q_id))
SELECT shape_r, shape_c, round(avg(gap), 6) AS bias, round(sqrt(avg(gap * gap)), 6) AS rmse, round(quantile_cont(rel, 0.9), 6) AS p90_rel, round(avg((est < -1e-9)::INTEGER), 6) AS share_negative, round(avg((truth = 0)::INTEGER), 6) AS share_true_zero FROM e GROUP BY 1, 2""")
