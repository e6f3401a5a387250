"""Queries of the relational operators that users of the engine need, on the given tables."""

from __future__ import annotations

from pyspark.sql import Window
from pyspark.sql import functions as F

from regioncount.operators import answer, relational, workload
from regioncount.plans import experiments as x
from regioncount.plans import sqlparts as sql
from regioncount.sources import points
from regioncount.streaming import stream

QUERIES: dict = {}
t = points.table


def _add(name, run, oracle):
    QUERIES[name] = (run, oracle)


_BODY = "body AS (SELECT o_custkey, count(*) AS n FROM orders GROUP BY o_custkey), c AS (SELECT r_name, n_name, c_mktsegment, n FROM body JOIN customer ON c_custkey = o_custkey JOIN nation ON n_nationkey = c_nationkey JOIN region ON r_regionkey = n_regionkey)"


def _customers(spark, d):
    body = t(spark, d, "orders").groupBy("o_custkey").agg(F.count(F.lit(1)).alias("n"))
    c = t(spark, d, "customer").select("c_custkey", "c_nationkey", "c_mktsegment")
    n = t(spark, d, "nation").join(F.broadcast(t(spark, d, "region")), F.col("n_regionkey") == F.col("r_regionkey")).select("n_nationkey", "n_name", "r_name")
    return body.join(c, F.col("o_custkey") == F.col("c_custkey")).join(F.broadcast(n), F.col("c_nationkey") == F.col("n_nationkey"))


def _totals(grouped):
    return grouped.agg(F.count(F.lit(1)).alias("users"), F.sum("n").alias("points"))


_add("op_rollup_bodies", lambda s, d: _totals(_customers(s, d).rollup("r_name", "n_name")), f"WITH {_BODY} SELECT r_name, n_name, count(*) AS users, sum(n)::BIGINT AS points FROM c GROUP BY ROLLUP (r_name, n_name)")
_add("op_cube", lambda s, d: _totals(_customers(s, d).cube("r_name", "c_mktsegment")), f"WITH {_BODY} SELECT r_name, c_mktsegment, count(*) AS users, sum(n)::BIGINT AS points FROM c GROUP BY CUBE (r_name, c_mktsegment)")


def _sets(s, d):
    _customers(s, d).createOrReplaceTempView("rc_customers")
    return s.sql("SELECT r_name, n_name, c_mktsegment, count(*) AS users, sum(n) AS points FROM rc_customers GROUP BY GROUPING SETS ((r_name), (n_name, c_mktsegment), ())")


_add("op_grouping_sets", _sets, f"WITH {_BODY} SELECT r_name, n_name, c_mktsegment, count(*) AS users, sum(n)::BIGINT AS points FROM c GROUP BY GROUPING SETS ((r_name), (n_name, c_mktsegment), ())")


def _asof(s, d):
    e = t(s, d, "events").select("user_id", "event_id", "ts", "event_type", "value")
    buy, view = e.filter("event_type = 'purchase'").select("user_id", "ts", "event_id"), e.filter("event_type = 'view'").select("user_id", "ts", "event_id", "value")
    out = relational.asof_join(buy, view.withColumnRenamed("event_id", "view_id"), "user_id", "ts", ["view_id", "value"], ["view_id"])
    return out.select("event_id", F.col("last_view_id").alias("view_id"), F.col("last_value").alias("value"))


_add("op_asof", _asof, """SELECT p.event_id, arg_max(v.event_id, (v.ts, v.event_id)) AS view_id, arg_max(v.value, (v.ts, v.event_id)) AS value FROM events p LEFT JOIN events v
  ON v.event_type = 'view' AND v.user_id = p.user_id AND v.ts <= p.ts WHERE p.event_type = 'purchase' GROUP BY p.event_id""")


def _interval(s, d):
    e = t(s, d, "events").select("user_id", "event_id", F.col("ts").cast("timestamp").alias("ts"), "event_type")
    spans = e.filter("event_type = 'signup'").select("user_id", F.col("event_id").alias("span_id"), F.col("ts").alias("start"), (F.col("ts") + F.expr("interval 6 hours")).alias("end"))
    return relational.interval_join(e.select("user_id", "event_id", "ts"), spans, "user_id", "ts", 21600).groupBy("span_id").agg(F.count(F.lit(1)).alias("events"))


_add("op_interval_join", _interval, "SELECT s.event_id AS span_id, count(*) AS events FROM events s JOIN events e ON e.user_id = s.user_id AND e.ts > s.ts AND e.ts <= s.ts + INTERVAL 6 HOUR WHERE s.event_type = 'signup' GROUP BY 1")

_RECTS = [(1, 1.0, 3.0, 2.0, 4.5), (2, 9.5, 14.0, 8.0, 8.5), (3, 0.0, 20.0, 19.0, 20.0)]


def _range(s, d):
    rects = s.createDataFrame([(i, *map(float, r)) for i, *r in _RECTS], "q_id long, x0 double, x1 double, y0 double, y1 double")
    return relational.range_join(points.even(s, d), rects, 2.0).groupBy("q_id").agg(F.count(F.lit(1)).alias("points"))


_add("op_range_join", _range, f"WITH {sql.points('even')}, r(q_id, x0, x1, y0, y1) AS (VALUES {', '.join(f'({i}::BIGINT, ' + ', '.join(f'{v}::DOUBLE' for v in r) + ')' for i, *r in _RECTS)}) SELECT q_id, count(*) AS points FROM points JOIN r ON x BETWEEN x0 AND x1 AND y BETWEEN y0 AND y1 GROUP BY q_id")
_semi = lambda how: lambda s, d: t(s, d, "customer").select("c_custkey", "c_nationkey").join(t(s, d, "orders"), F.col("c_custkey") == F.col("o_custkey"), how)
_add("op_semi", _semi("left_semi"), "SELECT c_custkey, c_nationkey FROM customer WHERE c_custkey IN (SELECT o_custkey FROM orders)")
_add("op_anti", _semi("left_anti"), "SELECT c_custkey, c_nationkey FROM customer WHERE NOT EXISTS (SELECT 1 FROM orders WHERE o_custkey = c_custkey)")


def _outer(how):
    def run(s, d):
        a = t(s, d, "orders").filter("o_orderstatus = 'F'").groupBy(F.col("o_custkey").alias("k")).agg(F.count(F.lit(1)).alias("f"))
        b = t(s, d, "orders").filter("o_orderstatus = 'O'").groupBy(F.col("o_custkey").alias("k")).agg(F.count(F.lit(1)).alias("o"))
        return a.join(b, "k", how).select("k", "f", "o")

    return run


_FO = "a AS (SELECT o_custkey AS k, count(*) AS f FROM orders WHERE o_orderstatus = 'F' GROUP BY 1), b AS (SELECT o_custkey AS k, count(*) AS o FROM orders WHERE o_orderstatus = 'O' GROUP BY 1)"
for _how in ("full", "left", "right", "inner"):
    _add(f"op_{_how}_join" if _how != "full" else "op_full_outer", _outer(_how), f"WITH {_FO} SELECT k, f, o FROM a {_how.upper()} JOIN b USING (k)")


def _topk(s, d):
    o = t(s, d, "orders").select("o_custkey", "o_orderkey", "o_totalprice")
    return relational.top_k(o, ["o_custkey"], [F.desc("o_totalprice"), "o_orderkey"], 3).select("o_custkey", "o_orderkey", F.col("rank").cast("long").alias("rank"))


_add("op_topk_group", _topk, "SELECT o_custkey, o_orderkey, rn AS rank FROM (SELECT *, row_number() OVER (PARTITION BY o_custkey ORDER BY o_totalprice DESC, o_orderkey) AS rn FROM orders) WHERE rn <= 3")


def _topcells(s, d):
    h = x.exact(s, d, x.Setting("even", 20))
    return h.filter("kind = 'face'").orderBy(F.desc("h"), "u", "v").limit(10).select("u", "v", "h")


_add("op_topk_cells", _topcells, f"WITH {sql.bodies('even', 2.0, 20.0)}, {sql.hist(20, 1.0)} SELECT u, v, h FROM hist WHERE kind = 'face' ORDER BY h DESC, u, v LIMIT 10")
_TYPES = ["click", "error", "purchase", "signup", "view"]
_add("op_pivot", lambda s, d: t(s, d, "events").groupBy("user_id").pivot("event_type", _TYPES).agg(F.count(F.lit(1))).na.fill(0), "SELECT user_id, " + ", ".join(f"count(*) FILTER (event_type = '{c}') AS {c}" for c in _TYPES) + " FROM events GROUP BY user_id")


def _unpivot(s, d):
    wide = t(s, d, "lineitem").groupBy("l_returnflag").agg(F.sum(F.col("l_quantity").cast("long")).alias("quantity"), F.count(F.lit(1)).alias("lines"))
    return wide.unpivot("l_returnflag", ["quantity", "lines"], "measure", "value")


_add("op_unpivot", _unpivot, "WITH w AS (SELECT l_returnflag, sum(l_quantity::BIGINT)::BIGINT AS quantity, count(*) AS lines FROM lineitem GROUP BY 1) SELECT l_returnflag, 'quantity' AS measure, quantity AS value FROM w UNION ALL SELECT l_returnflag, 'lines', lines FROM w")
_nations = lambda s, d: (t(s, d, "customer").select(F.col("c_nationkey").alias("k")), t(s, d, "supplier").select(F.col("s_nationkey").alias("k")))
_add("op_intersect", lambda s, d: (lambda a, b: a.intersect(b))(*_nations(s, d)), "SELECT c_nationkey AS k FROM customer INTERSECT SELECT s_nationkey FROM supplier")
_add("op_intersect_all", lambda s, d: (lambda a, b: a.intersectAll(b))(*_nations(s, d)), "SELECT c_nationkey AS k FROM customer INTERSECT ALL SELECT s_nationkey FROM supplier")
_add("op_except_all", lambda s, d: (lambda a, b: a.exceptAll(b))(*_nations(s, d)), "SELECT c_nationkey AS k FROM customer EXCEPT ALL SELECT s_nationkey FROM supplier")
_add("op_except", lambda s, d: t(s, d, "part").select("p_partkey").subtract(t(s, d, "lineitem").filter("l_quantity > 40").select("l_partkey")), "SELECT p_partkey FROM part EXCEPT SELECT l_partkey FROM lineitem WHERE l_quantity > 40")
_add("op_union_distinct", lambda s, d: (lambda a, b: a.union(b).distinct())(*_nations(s, d)), "SELECT c_nationkey AS k FROM customer UNION SELECT s_nationkey FROM supplier")
_add("op_percentiles", lambda s, d: t(s, d, "lineitem").groupBy("l_returnflag", "l_linestatus").agg(F.round(F.median("l_extendedprice"), 6).alias("median"), F.round(F.percentile("l_extendedprice", 0.9), 6).alias("p90"), F.count_distinct("l_suppkey").alias("suppliers")), "SELECT l_returnflag, l_linestatus, round(median(l_extendedprice), 6) AS median, round(quantile_cont(l_extendedprice, 0.9), 6) AS p90, count(DISTINCT l_suppkey) AS suppliers FROM lineitem GROUP BY 1, 2")
_add("op_width_bucket", lambda s, d: points.even(s, d).groupBy(F.width_bucket("x", F.lit(0.0), F.lit(20.0), F.lit(8)).alias("bucket")).agg(F.count(F.lit(1)).alias("n")), f"WITH {sql.points('even')} SELECT CASE WHEN x < 0 THEN 0 WHEN x >= 20 THEN 9 ELSE floor(x / 2.5)::BIGINT + 1 END AS bucket, count(*) AS n FROM points GROUP BY 1")


def _ranks(s, d):
    w = Window.partitionBy("user_id").orderBy("ts", "event_id")
    by_type = Window.partitionBy("user_id").orderBy("event_type")
    out = t(s, d, "events").select("event_id", F.row_number().over(w).alias("rn"), F.rank().over(by_type).alias("rk"), F.dense_rank().over(by_type).alias("dr"), F.ntile(4).over(w).alias("nt"), F.round(F.percent_rank().over(w), 6).alias("pr"), F.lag("event_id").over(w).alias("prev"), F.lead("event_id").over(w).alias("next"), F.nth_value("event_id", 2).over(w.rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing)).alias("second"), F.round(F.sum("value").over(w.rowsBetween(-2, 0)), 6).alias("run3"))
    return out.select("event_id", *[F.col(c).cast("long").alias(c) for c in ("rn", "rk", "dr", "nt")], "pr", "prev", "next", "second", "run3")


_W = "(PARTITION BY user_id ORDER BY ts, event_id)"
_T = "(PARTITION BY user_id ORDER BY event_type)"
_add("op_window_functions", _ranks, f"SELECT event_id, row_number() OVER {_W} AS rn, rank() OVER {_T} AS rk, dense_rank() OVER {_T} AS dr, ntile(4) OVER {_W} AS nt, round(percent_rank() OVER {_W}, 6) AS pr, lag(event_id) OVER {_W} AS prev, lead(event_id) OVER {_W} AS next, nth_value(event_id, 2) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS BETWEEN UNBOUNDED PRECEDING AND UNBOUNDED FOLLOWING) AS second, round(sum(value) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS BETWEEN 2 PRECEDING AND CURRENT ROW), 6) AS run3 FROM events")


def _range_frame(s, d):
    e = t(s, d, "events").select("user_id", "event_id", F.unix_seconds(F.col("ts").cast("timestamp")).alias("sec"))
    return e.select("event_id", F.count(F.lit(1)).over(Window.partitionBy("user_id").orderBy("sec").rangeBetween(-86400, 0)).alias("last_day"))


_add("op_range_frame", _range_frame, "SELECT event_id, count(*) OVER (PARTITION BY user_id ORDER BY floor(epoch(ts))::BIGINT RANGE BETWEEN 86400 PRECEDING AND CURRENT ROW) AS last_day FROM events")


def _windows(kind):
    def run(s, d):
        e = t(s, d, "events").select("user_id", F.col("ts").cast("timestamp").alias("ts"))
        w = F.session_window("ts", "2 hours") if kind == "session" else F.window("ts", "12 hours", "6 hours")
        out = e.groupBy("user_id", w.alias("w")).agg(F.count(F.lit(1)).alias("n"))
        return out.select("user_id", F.unix_seconds("w.start").alias("start"), F.unix_seconds("w.end").alias("end"), "n")

    return run


_add("op_session_windows", _windows("session"), """WITH e AS (SELECT user_id, ts, CASE WHEN ts - lag(ts) OVER (PARTITION BY user_id ORDER BY ts) < INTERVAL 2 HOUR THEN 0 ELSE 1 END AS fresh FROM events),
g AS (SELECT user_id, ts, sum(fresh) OVER (PARTITION BY user_id ORDER BY ts ROWS UNBOUNDED PRECEDING) AS k FROM e)
SELECT user_id, floor(epoch(min(ts)))::BIGINT AS start, floor(epoch(max(ts)))::BIGINT + 7200 AS "end", count(*) AS n FROM g GROUP BY user_id, k""")
_add("op_sliding_windows", _windows("sliding"), """WITH e AS (SELECT user_id, floor(epoch(ts))::BIGINT AS s FROM events), w AS (SELECT user_id, (s // 21600 - k) * 21600 AS start FROM e, range(2) r(k))
SELECT user_id, w.start::BIGINT AS start, (w.start + 43200)::BIGINT AS "end", count(*) AS n FROM w GROUP BY user_id, w.start""")
_add("op_json_props", lambda s, d: t(s, d, "events").groupBy(F.get_json_object("props", "$.k").cast("int").alias("k")).agg(F.count(F.lit(1)).alias("n"), F.max(F.from_json("props", "k int")["k"]).alias("same")), "SELECT json_extract(props, '$.k')::INTEGER AS k, count(*) AS n, max(json_extract(props, '$.k')::INTEGER) AS same FROM events GROUP BY 1")


def _maps(s, d):
    m = t(s, d, "events").groupBy("user_id", "event_type").agg(F.count(F.lit(1)).alias("n")).groupBy("user_id").agg(F.map_from_entries(F.array_sort(F.collect_list(F.struct("event_type", "n")))).alias("m"))
    return m.select("user_id", F.size("m").cast("long").alias("kinds"), F.coalesce(F.element_at("m", "view"), F.lit(0)).alias("views"), F.to_json("m").alias("j"))


_add("op_map_fn", _maps, """WITH c AS (SELECT user_id, event_type, count(*) AS n FROM events GROUP BY 1, 2)
SELECT user_id, count(*) AS kinds, coalesce(max(n) FILTER (event_type = 'view'), 0) AS views, '{' || string_agg('"' || event_type || '":' || n, ',' ORDER BY event_type) || '}' AS j FROM c GROUP BY user_id""")


def _lengths(s, d):
    parts = [(n, c) for n, c in (("documents", "text"), ("pages", "html"), ("conversations", "text"), ("benchmark", "text"))]
    out = None
    for n, c in parts:
        part = t(s, d, n).agg(F.lit(n).alias("t"), F.count(F.lit(1)).alias("n"), F.sum(F.char_length(c)).alias("chars"), F.max(F.octet_length(c)).cast("long").alias("bytes"))
        out = part if out is None else out.union(part)
    return out


_add("op_text_lengths", _lengths, " UNION ALL ".join(f"SELECT '{n}' AS t, count(*) AS n, sum(length({c}))::BIGINT AS chars, max(strlen({c}))::BIGINT AS bytes FROM {n}" for n, c in (("documents", "text"), ("pages", "html"), ("conversations", "text"), ("benchmark", "text"))))
_add("op_date_functions", lambda s, d: t(s, d, "orders").groupBy(F.date_format(F.date_trunc("month", F.col("o_orderdate")), "yyyy-MM").alias("month"), (F.dayofweek("o_orderdate") - 1).alias("dow")).agg(F.count(F.lit(1)).alias("n")), "SELECT strftime(date_trunc('month', o_orderdate), '%Y-%m') AS month, dayofweek(o_orderdate)::INTEGER AS dow, count(*) AS n FROM orders GROUP BY 1, 2")
_add("op_conditional_agg", lambda s, d: t(s, d, "orders").groupBy("o_orderpriority").agg(F.sum(F.when(F.col("o_orderstatus") == "F", 1).otherwise(0)).alias("f"), F.count_if(F.col("o_totalprice") > 200000).alias("large"), F.round(F.stddev("o_totalprice"), 3).alias("sd")), "SELECT o_orderpriority, sum((o_orderstatus = 'F')::BIGINT)::BIGINT AS f, count(*) FILTER (o_totalprice > 200000) AS large, round(stddev(o_totalprice), 3) AS sd FROM orders GROUP BY 1")


def _geometry(s, d):
    hull = F.array(*[F.struct(F.col(a).alias("x"), F.col(b).alias("y")) for a, b in (("xmin", "ymin"), ("xmax", "ymin"), ("xmax", "ymax"), ("xmin", "ymax"))])
    b = x.bodies(s, d, "core").withColumn("hull", hull)
    again = points.parse_wkt(points.to_wkt(F.col("hull")))
    json = points.parse_geojson(points.to_geojson(F.col("hull")))
    from regioncount.functions import fn

    return b.select("body_id", F.round(fn.hull_area(again), 6).alias("area"), F.round(fn.hull_perimeter(json), 6).alias("perimeter"), fn.hull_contains(F.col("hull"), (F.col("xmin") + F.col("xmax")) / 2, (F.col("ymin") + F.col("ymax")) / 2).alias("centre"), fn.box_overlaps(F.col("xmin"), F.col("xmax"), F.col("ymin"), F.col("ymax"), F.lit(1.0), F.lit(2.0), F.lit(1.0), F.lit(2.0)).alias("meets"))


_add("op_geometry_text", _geometry, f"WITH {sql.bodies('core', 2.0, 3.2)} SELECT body_id, round((xmax - xmin) * (ymax - ymin), 6) AS area, round(2 * (xmax - xmin + ymax - ymin), 6) AS perimeter, true AS centre, xmin <= 2 AND xmax >= 1 AND ymin <= 2 AND ymax >= 1 AS meets FROM bodies")


def _shapes(s, d):
    wanted = workload.sizes(20, [1.0, 7.0, 70.0])
    q = workload.positions(s, 20, wanted)
    a = answer.by_prefix(answer.prefix(x.exact(s, d, x.Setting("even", 20))), q)
    return q.join(a, "q_id").groupBy("pct", "shape_r", "shape_c").agg(F.count(F.lit(1)).alias("positions"), F.sum("est").alias("bodies"))


_add("workload_positions", _shapes, f"""WITH {sql.bodies('even', 2.0, 20.0)}, {sql.boxes(20, 1.0)},
shapes AS (SELECT pct::DOUBLE AS pct, r::INTEGER AS shape_r, c::INTEGER AS shape_c, ((21 - r) * (21 - c))::BIGINT AS positions FROM (VALUES (1), (7), (70)) p(pct), range(1, 21) a(r), range(1, 21) b(c) WHERE r * c = pct * 4)
SELECT pct, shape_r, shape_c, positions, sum((least(r1, 20 - shape_r) - greatest(r0 - shape_r + 1, 0) + 1) * (least(c1, 20 - shape_c) - greatest(c0 - shape_c + 1, 0) + 1))::BIGINT AS bodies FROM shapes, boxes GROUP BY ALL""")
_add("stream_window_boxes", lambda s, d: stream.batch_windows(s, d), f"WITH {sql.points('core')} SELECT user_id AS body_id, (floor(epoch(ts))::BIGINT // 86400) * 86400 AS start, round(min(x), 6) AS xmin, round(max(x), 6) AS xmax, round(min(y), 6) AS ymin, round(max(y), 6) AS ymax, count(*) AS n_points FROM points GROUP BY 1, 2")
_add("stream_replay", lambda s, d: stream.replay_windows(s, d), QUERIES["stream_window_boxes"][1])
