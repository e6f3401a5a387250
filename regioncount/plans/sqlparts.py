"""DuckDB SQL for the same steps, in pieces (common table expressions) that the oracles put together."""

from __future__ import annotations

from regioncount.sources.points import HUBS


def u(key: str) -> str:
    return f"((('0x' || substr(md5({key}), 1, 13))::BIGINT + 0.5) / 4503599627370496.0::DOUBLE)"


def frac(a: str) -> str:
    return f"(((((({a}) % 1000) + 1000) % 1000)::DOUBLE + 0.5::DOUBLE) / 1000.0::DOUBLE - 0.5::DOUBLE)"


def _hub(k: int) -> str:
    return "CASE s_nationkey % 5 " + " ".join(f"WHEN {i} THEN {h[k]}::DOUBLE" for i, h in enumerate(HUBS)) + " END"


_HOMES = {
    "even": f"""SELECT o_custkey AS user_id, o_orderkey AS point_id, o_orderdate AS ts, 20.0::DOUBLE * {u("'ex:' || o_custkey")} AS hx, 20.0::DOUBLE * {u("'ey:' || o_custkey")} AS hy,
      round(o_totalprice * 100)::BIGINT AS a, (37 * date_diff('day', DATE '1995-01-01', o_orderdate::DATE))::BIGINT AS b FROM orders""",
    "core": f"""SELECT user_id, event_id AS point_id, ts, 1.6::DOUBLE + 0.8::DOUBLE * ({u("'cx1:' || user_id")} + {u("'cx2:' || user_id")} + {u("'cx3:' || user_id")} - 1.5::DOUBLE) AS hx,
      1.6::DOUBLE + 0.8::DOUBLE * ({u("'cy1:' || user_id")} + {u("'cy2:' || user_id")} + {u("'cy3:' || user_id")} - 1.5::DOUBLE) AS hy,
      round(value * 100)::BIGINT AS a, (37 * (floor(epoch(ts))::BIGINT - 1704067200))::BIGINT AS b FROM events""",
    "dense": f"""SELECT l_suppkey AS user_id, l_orderkey * 8 + l_linenumber AS point_id, l_shipdate AS ts, {_hub(0)} + 3.0::DOUBLE * ({u("'dx1:' || l_suppkey")} + {u("'dx2:' || l_suppkey")} - 1.0::DOUBLE) AS hx,
      {_hub(1)} + 3.0::DOUBLE * ({u("'dy1:' || l_suppkey")} + {u("'dy2:' || l_suppkey")} - 1.0::DOUBLE) AS hy,
      round(l_extendedprice * 100)::BIGINT AS a, (37 * date_diff('day', DATE '1995-01-01', l_shipdate::DATE))::BIGINT AS b FROM lineitem JOIN supplier ON l_suppkey = s_suppkey""",
}


def points(role: str) -> str:
    """CTEs homes, points."""
    w = f"(1.2::DOUBLE * (0.3::DOUBLE + 0.7::DOUBLE * {u(chr(39) + 's:' + chr(39) + ' || user_id')}))"
    w = f"(CASE WHEN point_id % 11 = 0 THEN {w} * 5.0::DOUBLE ELSE {w} END)"
    return f"homes AS ({_HOMES[role]}),\npoints AS (SELECT user_id, point_id, ts, hx + {w} * {frac('a')} AS x, hy + {w} * {frac('b')} AS y FROM homes)"


def bodies(role: str, body: float, area: float) -> str:
    """CTEs homes, points, modes, kept, bodies: boxes by median mode and bbox trimming."""
    half = f"({body}::DOUBLE / {2 * 2 ** 0.5!r}::DOUBLE)"
    return f"""{points(role)},
modes AS (SELECT user_id, median(x) AS mode_x, median(y) AS mode_y FROM points GROUP BY user_id),
kept AS (SELECT p.*, mode_x, mode_y FROM points p JOIN modes USING (user_id) WHERE abs(x - mode_x) <= {half} AND abs(y - mode_y) <= {half} AND x >= 0 AND x < {area} AND y >= 0 AND y < {area}),
bodies AS (SELECT user_id AS body_id, min(x) AS xmin, max(x) AS xmax, min(y) AS ymin, max(y) AS ymax, count(*) AS n_points FROM kept GROUP BY user_id)"""


def lattice(n: int) -> str:
    """CTE lattice (u, v, kind)."""
    s = 2 * n - 1
    return f"lattice AS (SELECT (i // {s})::INTEGER AS u, (i % {s})::INTEGER AS v, CASE WHEN (i // {s}) % 2 = 0 AND (i % {s}) % 2 = 0 THEN 'face' WHEN (i // {s}) % 2 = 1 AND (i % {s}) % 2 = 1 THEN 'vertex' ELSE 'edge' END AS kind FROM range({s * s}) r(i))"


def boxes(n: int, d: float, source: str = "bodies") -> str:
    """CTE boxes (body_id, r0, r1, c0, c1)."""
    at = lambda c: f"least(greatest(floor({c} / {d}::DOUBLE), 0), {n - 1})::INTEGER"
    a = n * d
    return f"boxes AS (SELECT body_id, {at('ymin')} AS r0, {at('ymax')} AS r1, {at('xmin')} AS c0, {at('xmax')} AS c1 FROM {source} WHERE xmax >= 0 AND xmin < {a} AND ymax >= 0 AND ymin < {a})"


def hist(n: int, d: float, source: str = "bodies") -> str:
    """CTEs lattice, boxes, touched, hist (u, v, kind, h): every touched count, literally."""
    return f"""{lattice(n)},
{boxes(n, d, source)},
rows_ AS (SELECT body_id, unnest(range(2 * r0, 2 * r1 + 1)) AS u, c0, c1 FROM boxes),
touched AS (SELECT u, unnest(range(2 * c0, 2 * c1 + 1)) AS v FROM rows_),
counted AS (SELECT u, v, count(*) AS c FROM touched GROUP BY u, v),
hist AS (SELECT l.u, l.v, kind, coalesce(c, 0)::BIGINT AS h FROM lattice l LEFT JOIN counted t ON l.u = t.u AND l.v = t.v)"""


def noisy(scale: float, seed: str, reps: int, truncate: bool = True, source: str = "hist", name: str = "noisy") -> str:
    """CTE noisy (rep, u, v, kind, h)."""
    x = f"({u(chr(39) + seed + ':' + chr(39) + ' || rep || ' + chr(39) + ':' + chr(39) + ' || u || ' + chr(39) + ':' + chr(39) + ' || v')} - 0.5::DOUBLE)"
    value = f"h::DOUBLE + -{scale!r}::DOUBLE * sign({x}) * ln(1.0::DOUBLE - 2.0::DOUBLE * abs({x}))"
    if truncate:
        value = f"greatest({value}, 0.0::DOUBLE)"
    return f"{name} AS MATERIALIZED (SELECT rep::INTEGER AS rep, u, v, kind, {value} AS h FROM {source}, range({reps}) r(rep))"


def near(source: str, name: str = "near") -> str:
    """CTE with neighbours of each node (null outside), and row-wise extremes."""
    return f"""{name}_r AS (SELECT *, lag(h) OVER a AS w, lead(h) OVER a AS e FROM {source} WINDOW a AS (PARTITION BY rep, u ORDER BY v)),
{name}_m AS (SELECT *, greatest(h, w, e) AS rmax, least(h, w, e) AS rmin FROM {name}_r),
{name} AS (SELECT *, lag(h) OVER b AS n, lead(h) OVER b AS s, lag(rmax) OVER b AS nmax, lead(rmax) OVER b AS smax, lag(rmin) OVER b AS nmin, lead(rmin) OVER b AS smin FROM {name}_m WINDOW b AS (PARTITION BY rep, v ORDER BY u))"""


def linf(source: str = "noisy", name: str = "fitted") -> str:
    """CTE fitted: max-norm fit."""
    return f"""{near(source, name + '_n')},
{name} AS MATERIALIZED (SELECT rep, u, v, kind, greatest(CASE WHEN kind = 'face' THEN (greatest(rmax, nmax, smax) + h) / 2 WHEN kind = 'vertex' THEN (h + least(rmin, nmin, smin)) / 2
  WHEN u % 2 = 0 THEN (greatest(h, n, s) + least(h, w, e)) / 2 ELSE (greatest(h, w, e) + least(h, n, s)) / 2 END, 0) AS h FROM {name}_n)"""


def clip(source: str = "noisy", name: str = "clipped") -> str:
    return f"""{near(source, name + '_a')},
{name}_e AS (SELECT rep, u, v, kind, greatest(CASE WHEN kind <> 'edge' THEN h WHEN u % 2 = 0 THEN least(h, w, e) ELSE least(h, n, s) END, 0) AS h FROM {name}_a),
{near(name + '_e', name + '_b')},
{name} AS MATERIALIZED (SELECT rep, u, v, kind, CASE WHEN kind = 'vertex' THEN least(h, w, e, n, s) ELSE h END AS h FROM {name}_b)"""


def rounded(source: str = "fitted", name: str = "rounded") -> str:
    return f"{name} AS (SELECT rep, u, v, kind, round(h)::BIGINT AS h FROM {source})"


def positions(n: int, wanted: list[tuple[float, int, int]]) -> str:
    """CTE queries_ (q_id, pct, shape_r, shape_c, r0, r1, c0, c1)."""
    rows = ", ".join(f"({k}, {float(p)}::DOUBLE, {r}, {c})" for k, (p, r, c) in enumerate(wanted))
    return f"""shapes(k, pct, shape_r, shape_c) AS (VALUES {rows}),
queries_ AS (SELECT ((k::BIGINT * {n} + r0) * {n} + c0)::BIGINT AS q_id, pct, shape_r, shape_c, r0::INTEGER AS r0, (r0 + shape_r - 1)::INTEGER AS r1, c0::INTEGER AS c0, (c0 + shape_c - 1)::INTEGER AS c1
  FROM shapes, range({n}) a(r0), range({n}) b(c0) WHERE r0 <= {n} - shape_r AND c0 <= {n} - shape_c)"""


def answers(source: str, name: str, keyed: bool = True) -> str:
    """CTE (rep, q_id, est): prefix sums and four look-ups."""
    key = "rep, " if keyed else ""
    part = "PARTITION BY rep, " if keyed else "PARTITION BY "
    return f"""{name}_s AS (SELECT {key}u, v, sum(CASE WHEN (u + v) % 2 = 0 THEN h ELSE -h END) OVER ({part}u ORDER BY v) AS s FROM {source}),
{name}_p AS MATERIALIZED (SELECT {key}u, v, sum(s) OVER ({part}v ORDER BY u) AS p FROM {name}_s),
{name}_c AS (SELECT q_id, 2 * r1 AS u, 2 * c1 AS v, 1 AS g FROM queries_ UNION ALL SELECT q_id, 2 * r0 - 1, 2 * c1, -1 FROM queries_ UNION ALL SELECT q_id, 2 * r1, 2 * c0 - 1, -1 FROM queries_ UNION ALL SELECT q_id, 2 * r0 - 1, 2 * c0 - 1, 1 FROM queries_),
{name} AS MATERIALIZED (SELECT {key}q_id, sum(g * p) AS est FROM {name}_c JOIN {name}_p USING (u, v) GROUP BY {key}q_id)"""


def constraints(n: int) -> str:
    """CTE cons (cls, lo_u, lo_v, hi_u, hi_v)."""
    top = 2 * n - 2
    return f"""steps(du, dv) AS (VALUES (0, -1), (0, 1), (-1, 0), (1, 0)),
cons AS (
  SELECT CASE WHEN kind = 'edge' THEN 'C1' ELSE 'C2' END AS cls, u AS lo_u, v AS lo_v, (u + du)::INTEGER AS hi_u, (v + dv)::INTEGER AS hi_v FROM lattice, steps
  WHERE u + du BETWEEN 0 AND {top} AND v + dv BETWEEN 0 AND {top} AND (kind = 'vertex' OR kind = 'edge' AND (u + du) % 2 = 0 AND (v + dv) % 2 = 0)
  UNION ALL SELECT 'C3', u, v, u, v FROM lattice WHERE kind = 'vertex')"""


def violated(source: str, name: str) -> str:
    """CTE (rep, cls, members, violated)."""
    return f"""{name}_3 AS (SELECT rep, lo_u, lo_v, sum(CASE WHEN (h.u + h.v) % 2 = 0 THEN h ELSE -h END) AS s FROM cons JOIN {source} h ON cls = 'C3' AND h.u BETWEEN lo_u - 1 AND lo_u + 1 AND h.v BETWEEN lo_v - 1 AND lo_v + 1 GROUP BY rep, lo_u, lo_v),
{name} AS (
  SELECT a.rep, cls, count(*) AS members, sum((a.h > b.h)::BIGINT)::BIGINT AS violated FROM cons JOIN {source} a ON cls <> 'C3' AND a.u = lo_u AND a.v = lo_v JOIN {source} b ON b.rep = a.rep AND b.u = hi_u AND b.v = hi_v GROUP BY a.rep, cls
  UNION ALL SELECT rep, 'C3', count(*), sum((s < -1e-9)::BIGINT)::BIGINT FROM {name}_3 GROUP BY rep)"""
