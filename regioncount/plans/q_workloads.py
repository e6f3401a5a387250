"""Queries of the experiment workloads."""

from __future__ import annotations

import math

from pyspark.sql import functions as F

from regioncount.operators import bounds, metrics, workload
from regioncount.plans import experiments as x
from regioncount.plans import sqlparts as sql
from regioncount.sources.shared import cut

QUERIES: dict = {}
SQL_METHODS = ("noise", "linf", "round")


def _error_sql(s: x.Setting, wanted, by: list[str]) -> str:
    spec = s.spec
    ctes = [sql.bodies(s.role, s.body, spec.area), sql.hist(s.n, spec.d), sql.noisy(s.scale, s.seed, s.reps), sql.linf(), sql.rounded(), sql.positions(s.n, wanted), sql.answers("hist", "truth", keyed=False), sql.answers("noisy", "a_noise"), sql.answers("fitted", "a_linf"), sql.answers("rounded", "a_round")]
    columns = "".join(f", {c}" for c in by)
    union = " UNION ALL ".join(f"SELECT '{m}' AS method, q_id, est FROM a_{m}" for m in SQL_METHODS)
    return f"""WITH {(',' + chr(10)).join(ctes)},
e AS (SELECT method{columns}, abs(a.est - t.est) / greatest(t.est::DOUBLE, 1.0) AS rel, (t.est = 0)::INTEGER::DOUBLE AS zero FROM ({union}) a JOIN truth t USING (q_id) JOIN queries_ USING (q_id))
SELECT method{columns}, round(median(rel), 6) AS median_rel, round(avg(zero), 6) AS share_true_zero, count(*) AS answers FROM e GROUP BY method{columns}"""


def _add(name: str, s: x.Setting, percents: list[float], by: list[str]) -> None:
    wanted = workload.sizes(s.n, percents)
    QUERIES[name] = (lambda spark, d: x.errors(spark, d, s, wanted, SQL_METHODS, by), _error_sql(s, wanted, by))
    QUERIES[name + "_l1"] = (lambda spark, d: x.errors(spark, d, s, wanted, ("noise", "l1", "l1_round"), by), None)


SMALL, LARGE = [float(p) for p in range(1, 11)], [float(p) for p in range(10, 101, 10)]
SHAPE = ["pct", "shape_r", "shape_c"]
_add("w1_small_sizes", x.Setting("even", 20), SMALL, ["pct"])
_add("w2_large_sizes", x.Setting("even", 20), LARGE, ["pct"])
_add("w3_small_shapes", x.Setting("even", 20), [1.0, 3.0, 5.0, 10.0], SHAPE)
_add("w4_large_shapes", x.Setting("even", 20), [20.0, 50.0, 70.0], SHAPE)
_add("w5_dense_small_sizes", x.Setting("dense", 20), SMALL, ["pct"])
_add("w6_dense_large_sizes", x.Setting("dense", 20), LARGE, ["pct"])
_add("w7_dense_small_shapes", x.Setting("dense", 20), [1.0, 3.0, 5.0, 10.0], SHAPE)
_add("w8_dense_large_shapes", x.Setting("dense", 20), [20.0, 50.0, 70.0], SHAPE)
_add("w9_core_sizes", x.Setting("core", 4), LARGE, ["pct"])
_add("w10_core_shapes", x.Setting("core", 4), LARGE, SHAPE)


def _union(parts: list[tuple[str, object, str]]) -> str:
    """SQL of several sub-queries with a constant column each."""
    return "\nUNION ALL\n".join(f"SELECT {value} AS {column}, * FROM ({body})" for column, value, body in parts)


_RATIO = {n: x.Setting("even", n) for n in (10, 20, 30)}
_EPS = {e: x.Setting("even", 10, epsilon=e) for e in (0.1, 0.4, 0.7, 1.0)}


def _ratio(methods):
    def run(spark, d):
        out = None
        for n, s in _RATIO.items():
            part = x.errors(spark, d, s, workload.sizes(n, [1.0]), methods, []).select(F.lit(n).alias("n"), "*")
            out = part if out is None else out.union(part)
        return out

    return run


def _epsilon(methods):
    def run(spark, d):
        out = None
        for e, s in _EPS.items():
            part = x.errors(spark, d, s, workload.sizes(10, [1.0]), methods, []).select(F.lit(e).alias("epsilon"), "*")
            out = part if out is None else out.union(part)
        return out

    return run


QUERIES["w11_ratio"] = (_ratio(SQL_METHODS), _union([("n", f"{n}::INTEGER", _error_sql(s, workload.sizes(n, [1.0]), [])) for n, s in _RATIO.items()]))
QUERIES["w11_ratio_l1"] = (_ratio(("noise", "l1", "l1_round")), None)
QUERIES["w12_epsilon"] = (_epsilon(SQL_METHODS), _union([("epsilon", f"{e!r}::DOUBLE", _error_sql(s, workload.sizes(10, [1.0]), [])) for e, s in _EPS.items()]))
QUERIES["w12_epsilon_l1"] = (_epsilon(("noise", "l1", "l1_round")), None)

_ALL = {role: x.Setting(role, 20, reps=20) for role in x.AREAS}


def _roles(run_one):
    def run(spark, d):
        out = None
        for role, s in _ALL.items():
            part = run_one(spark, d, s).select(F.lit(role).alias("role"), "*")
            out = part if out is None else out.union(part)
        return out

    return run


def _release_ctes(s: x.Setting) -> list[str]:
    return [sql.bodies(s.role, s.body, s.spec.area), sql.hist(s.n, s.spec.d), sql.noisy(s.scale, s.seed, s.reps), sql.linf(), sql.clip(), sql.rounded()]


_MADE = {"noise": "noisy", "linf": "fitted", "clip": "clipped", "round": "rounded"}
_UNION_METHODS = " UNION ALL ".join(f"SELECT '{m}' AS method, rep, u, v, h::DOUBLE AS h FROM {t}" for m, t in _MADE.items())


def _distance_sql(s: x.Setting) -> str:
    return f"""WITH {(',' + chr(10)).join(_release_ctes(s))},
d AS (SELECT method, rep, sum(abs(m.h - x.h)) AS d FROM ({_UNION_METHODS}) m JOIN hist x USING (u, v) GROUP BY method, rep)
SELECT a.method, round(avg(100.0 * a.d / b.d), 6) AS rel_distance FROM d a JOIN d b ON b.method = 'noise' AND a.rep = b.rep GROUP BY a.method"""


def _violated_sql(s: x.Setting) -> str:
    parts = [sql.violated(t, f"v_{m}") for m, t in _MADE.items()]
    union = " UNION ALL ".join(f"SELECT '{m}' AS method, * FROM v_{m}" for m in _MADE)
    return f"""WITH {(',' + chr(10)).join([*_release_ctes(s), sql.constraints(s.n), *parts])}
SELECT method, cls, max(members) AS members, round(avg(violated), 6) AS violated FROM ({union}) GROUP BY method, cls"""


QUERIES["w13_distance"] = (_roles(lambda spark, d, s: x.distances(spark, d, s, ("linf", "clip", "round"))), _union([("role", f"'{r}'", _distance_sql(s)) for r, s in _ALL.items()]))
QUERIES["w13_distance_l1"] = (_roles(lambda spark, d, s: x.distances(spark, d, s, ("l1", "l1_round", "l2"))), None)
QUERIES["w14_violations"] = (_roles(lambda spark, d, s: x.violated(spark, d, s, tuple(_MADE))), _union([("role", f"'{r}'", _violated_sql(s)) for r, s in _ALL.items()]))
QUERIES["w14_violations_l1"] = (_roles(lambda spark, d, s: x.violated(spark, d, s, ("noise", "l1", "l1_round"))), None)
QUERIES["w15_running_time"] = (lambda spark, d: x.running_time(spark, d), None)
QUERIES["w16_worked_example"] = (lambda spark, d: x.worked_example(spark, cut(x.bodies(spark, d, "core")), x.Setting("core", 4).spec), f"""WITH {sql.bodies('core', x.BODY, 3.2)}, {sql.hist(4, 0.8)},
t AS (SELECT sum(h) FILTER (kind = 'face') AS faces, sum(h) FILTER (kind = 'edge') AS edges, sum(h) FILTER (kind = 'vertex') AS vertices FROM hist WHERE u <= 4 AND v <= 4)
SELECT faces::BIGINT AS faces, edges::BIGINT AS edges, vertices::BIGINT AS vertices, (faces - edges + vertices)::BIGINT AS answer, (SELECT count(*) FROM boxes WHERE r0 <= 2 AND c0 <= 2) AS truth FROM t""")


def _density(spark, d, s):
    return metrics.density(x.exact(spark, d, s))


QUERIES["w17_density"] = (_roles(_density), _union([("role", f"'{r}'", f"WITH {sql.bodies(r, x.BODY, s.spec.area)}, {sql.hist(20, s.spec.d)} SELECT (u // 2)::INTEGER AS r, (v // 2)::INTEGER AS c, h AS bodies FROM hist WHERE kind = 'face'") for r, s in _ALL.items()]))

_COVER = x.Setting("even", 20)
_DELTAS = [0.01, 0.05, 0.2, 0.5, 0.9]
QUERIES["w18_bound_coverage"] = (
    lambda spark, d: x.bound_coverage(spark, d, _COVER, _DELTAS),
    f"""WITH {sql.bodies('even', x.BODY, 20.0)}, {sql.hist(20, 1.0)}, {sql.noisy(_COVER.scale, _COVER.seed, _COVER.reps)},
deltas(delta, bound) AS (VALUES {', '.join(f'({d!r}::DOUBLE, {bounds.noise_bound(_COVER.scale, 1521, d)!r}::DOUBLE)' for d in _DELTAS)}),
worst AS (SELECT rep, max(abs(n.h - x.h)) AS w FROM noisy n JOIN hist x USING (u, v) GROUP BY rep)
SELECT delta, round(bound, 6) AS bound, count(*) AS repeats, round(avg((w <= bound)::INTEGER), 6) AS within FROM worst, deltas GROUP BY delta, bound""",
)


def _plane_sql(which: str) -> str:
    source = "SELECT o_custkey AS user_id, o_orderkey AS point_id, date_diff('day', DATE '1992-01-01', o_orderdate::DATE)::DOUBLE AS x, o_totalprice AS y FROM orders" if which == "orders" else "SELECT vec_id % 50 AS user_id, vec_id AS point_id, embedding[1]::DOUBLE AS x, embedding[2]::DOUBLE AS y FROM embeddings"
    half = x.BODY / (2 * math.sqrt(2))
    return f"""WITH o AS ({source}), lim AS (SELECT min(x) AS x0, max(x) AS x1, min(y) AS y0, max(y) AS y1 FROM o),
p AS (SELECT user_id, point_id, (x - x0) / (x1 - x0) * 9.999::DOUBLE AS x, (y - y0) / (y1 - y0) * 9.999::DOUBLE AS y FROM o, lim),
m AS (SELECT user_id, median(x) AS mx, median(y) AS my FROM p GROUP BY user_id),
bodies AS (SELECT user_id AS body_id, min(x) AS xmin, max(x) AS xmax, min(y) AS ymin, max(y) AS ymax, count(*) AS n_points FROM p JOIN m USING (user_id)
  WHERE abs(x - mx) <= {half!r}::DOUBLE AND abs(y - my) <= {half!r}::DOUBLE AND x >= 0 AND x < 10 AND y >= 0 AND y < 10 GROUP BY user_id),
{sql.hist(10, 1.0)}
SELECT u, v, kind, h FROM hist"""


def _plane(which: str):
    from regioncount.operators import euler
    from regioncount.operators.schemas import GridSpec

    return lambda spark, d: euler.histogram_boxes(x.planes(spark, d, which), GridSpec(10.0, 10))


QUERIES["w19_orders_plane"] = (_plane("orders"), _plane_sql("orders"))
QUERIES["w19_embedding_plane"] = (_plane("embeddings"), _plane_sql("embeddings"))


def _scale_sql(times: int, n: int) -> str:
    step = 20.0 / times / 2
    return f"""WITH {sql.bodies('even', x.BODY, 20.0)},
moved AS (SELECT body_id * {times} + k AS body_id, xmin + k * {step!r}::DOUBLE AS xmin, xmax + k * {step!r}::DOUBLE AS xmax, ymin + k * {step!r}::DOUBLE AS ymin, ymax + k * {step!r}::DOUBLE AS ymax FROM bodies, range({times}) r(k)),
{sql.hist(n, 20.0 / n, 'moved')}
SELECT kind, sum(h)::BIGINT AS total, max(h) AS most FROM hist GROUP BY kind"""


QUERIES["w20_scale"] = (lambda spark, d: x.replicated(spark, d, "even", 10, 100), _scale_sql(10, 100))
