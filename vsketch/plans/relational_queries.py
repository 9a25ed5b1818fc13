"""Queries of sources, sinks, joins, aggregates, windows, sets, scalars, SQL and streams around the methods."""

from __future__ import annotations

import uuid

from pyspark.sql import Window
from pyspark.sql import functions as F

from ..functions.hashing import hash_word, index_of, rank_of
from ..functions.spec import PORTABLE8
from ..operators import balls, exact, measures, triangles, twins, vst
from ..sources import build, io
from ..sources.graphs import graph
from ..streaming import live
from . import sql as S
from . import surface
from .graph_queries import _twins, _vst
from .registry import registry

QUERIES, SQL, add = registry()
t = lambda s, d, n: s.read.parquet(f"{d}/{n}.parquet")


def _path(s) -> str:
    root = s.conf.get("spark.checkpoint.dir", None) or s.conf.get("spark.sql.warehouse.dir")
    return f"{root.rstrip('/')}/vsketch/io-{uuid.uuid4().hex}"


def _round_trip(form):
    def run(s, d):
        path = _path(s)
        io.write_edges(graph(s, d, "event_prox60"), path, form)
        return io.read_edges(s, path, form)

    return run


for _form, _name in (("parquet", "scan_edges_parquet"), ("text", "scan_edge_text"), ("csv", "scan_edges_csv"), ("json", "scan_edges_json"), ("orc", "scan_edges_orc")):
    add(_name, _round_trip(_form), S.head("event_prox60") + "SELECT u, v FROM e")


def _layers(s, d):
    edges, table = _vst(s, d, "event_prox60")
    path = _path(s)
    balls.ball_sizes(edges, table, 2).save(path)
    return balls.load_layers(s, path, 2).select("x", "j", "rho")


add("save_load_layers", _layers, S.head("event_prox60", *S.layers(2)) + "SELECT x, j, rho FROM l2")


def _saved(s, d):
    path = _path(s)
    _vst(s, d, "geo_tree")[1].save(path)
    return vst.load(s, path).degree().select("x", F.round("d_est", 6).alias("d_est"))


add("save_load_table", _saved, S.head("geo_tree") + S.measured("reg", name="d_est"))
add("filter_degree_range", lambda s, d: exact.degrees(graph(s, d, "copart")).filter(F.col("d").between(100, 120) & ~F.col("x").isin(1, 2, 3)), S.head("copart", S.DEGREE) + "SELECT * FROM deg WHERE d BETWEEN 100 AND 120 AND x NOT IN (1, 2, 3)")

# joins
add("join_broadcast_nation", lambda s, d: t(s, d, "customer").join(F.broadcast(t(s, d, "nation")), F.col("c_nationkey") == F.col("n_nationkey")).select((F.col("c_custkey") * 4).alias("x"), "n_name"), "SELECT c_custkey * 4 AS x, n_name FROM customer JOIN nation ON c_nationkey = n_nationkey")


def _asof(s, d):
    """The last order before each event, by day, for the event's user: keys meet in a union and the last value is carried."""
    orders = t(s, d, "orders").groupBy(F.col("o_custkey").alias("k"), F.col("o_orderdate").alias("at")).agg(F.max("o_orderkey").alias("version"))
    asks = t(s, d, "events").select(F.col("user_id").alias("k"), F.col("ts").alias("at"), "event_id")
    rows = orders.select("k", "at", F.lit(0).alias("side"), "version", F.lit(None).cast("long").alias("event_id")).unionByName(asks.select("k", "at", F.lit(1).alias("side"), F.lit(None).cast("long").alias("version"), "event_id"))
    last = F.last("version", ignorenulls=True).over(Window.partitionBy("k").orderBy("at", "side").rowsBetween(Window.unboundedPreceding, 0))
    return rows.withColumn("version", last).filter("side = 1").select("event_id", "version")


add("join_asof_version", _asof, "SELECT event_id, version FROM events e ASOF LEFT JOIN (SELECT o_custkey AS k, o_orderdate AS at, max(o_orderkey) AS version FROM orders GROUP BY 1, 2) o ON o.k = e.user_id AND e.ts >= o.at")


def _closed(s, d):
    o = build.arcs(graph(s, d, "event_prox60"))
    wedges = o.select(F.col("x").alias("c"), F.col("y").alias("u")).join(o.select(F.col("x").alias("c"), F.col("y").alias("v")), "c").filter("u < v")
    return wedges.join(graph(s, d, "event_prox60"), ["u", "v"], "left_semi").groupBy("c").agg(F.count("*").alias("t"))


add("join_semi_closed_wedges", _closed, S.head("event_prox60") + "SELECT a.x AS c, count(*) AS t FROM arcs a JOIN arcs b ON a.x = b.x AND a.y < b.y WHERE EXISTS (SELECT 1 FROM e WHERE e.u = a.y AND e.v = b.y) GROUP BY 1")


def _frontier(s, d):
    a = build.arcs(graph(s, d, "event_prox60"))
    two = a.join(a.select(F.col("x").alias("y"), F.col("y").alias("z")), "y").filter("x <> z").select("x", "z").distinct()
    return two.join(a.select("x", F.col("y").alias("z")), ["x", "z"], "left_anti").groupBy("x").agg(F.count("*").alias("n"))


add("join_anti_new_frontier", _frontier, S.head("event_prox60") + "SELECT x, count(*) AS n FROM (SELECT DISTINCT a.x, b.y AS z FROM arcs a JOIN arcs b ON b.x = a.y AND b.y <> a.x) f WHERE NOT EXISTS (SELECT 1 FROM arcs k WHERE k.x = f.x AND k.y = f.z) GROUP BY 1")
add("join_interval_events", lambda s, d: build.proximity(t(s, d, "events"), "ts", "user_id", 30), S.graph_sql("event_prox60").replace("60000000", "30000000"))


def _full(s, d):
    regs = _vst(s, d, "event_prox60")[1].regs
    a, b = (regs.filter(F.pmod("x", F.lit(2)) == i).groupBy("j").agg(F.max("rho").alias(n)) for i, n in ((0, "a"), (1, "b")))
    return a.join(b, "j", "full_outer").select("j", F.coalesce("a", F.lit(0)).alias("a"), F.coalesce("b", F.lit(0)).alias("b"))


add("join_full_registers", _full, S.head("event_prox60") + "SELECT j, coalesce(a, 0) AS a, coalesce(b, 0) AS b FROM (SELECT j, max(rho) AS a FROM reg WHERE x % 2 = 0 GROUP BY 1) FULL JOIN (SELECT j, max(rho) AS b FROM reg WHERE x % 2 = 1 GROUP BY 1) USING (j)")

# aggregates
add("agg_max_register", lambda s, d: _vst(s, d, "copart")[1].regs.groupBy("j").agg(F.max("rho").alias("rho"), F.count("*").alias("n")), S.head("copart") + "SELECT j, max(rho) AS rho, count(*) AS n FROM reg GROUP BY j")


def _cube(s, d):
    local = exact.balls(graph(s, d, "geo_tree"), 2).join(t(s, d, "customer").select((F.col("c_custkey") * 4).alias("x"), F.col("c_mktsegment").alias("colour")), "x")
    return local.cube("colour", "t").agg(F.count("*").alias("vertices"), F.sum("n").alias("reach"))


_BALLS2 = " UNION ALL ".join(f"SELECT x, {k} AS t, count(*) AS n FROM b{k} GROUP BY x" for k in (1, 2))
add("agg_cube_colour_hop", _cube, S.head("geo_tree", *S.exact_balls(2)) + f"SELECT colour, t, count(*) AS vertices, CAST(sum(n) AS BIGINT) AS reach FROM ({_BALLS2}) JOIN (SELECT c_custkey * 4 AS x, c_mktsegment AS colour FROM customer) USING (x) GROUP BY CUBE (colour, t)")
add("agg_rollup_geo", lambda s, d: t(s, d, "customer").join(t(s, d, "nation"), F.col("c_nationkey") == F.col("n_nationkey")).rollup("n_regionkey", "c_nationkey").agg(F.count("*").alias("n")), "SELECT n_regionkey, c_nationkey, count(*) AS n FROM customer JOIN nation ON c_nationkey = n_nationkey GROUP BY ROLLUP (n_regionkey, c_nationkey)")
add("agg_distinct_exact", lambda s, d: t(s, d, "lineitem").groupBy("l_suppkey").agg(F.countDistinct("l_partkey").alias("parts"), F.count(F.when(F.col("l_quantity") > 25, 1)).alias("large")), "SELECT l_suppkey, count(DISTINCT l_partkey) AS parts, count(*) FILTER (WHERE l_quantity > 25) AS large FROM lineitem GROUP BY 1")
add("agg_error_percentiles", lambda s, d: measures.relative_errors(_vst(s, d, "copart")[1].degree(), exact.degrees(graph(s, d, "copart")), ["x"], "d_est", "d").agg(*(F.round(F.percentile("error", p), 6).alias(f"p{int(p * 100)}") for p in (0.5, 0.9, 0.99))), S.head("copart", S.DEGREE, f"er AS (SELECT abs(est - d) / d AS err FROM deg JOIN (SELECT x, {S.est('tt', 'ff')} AS est FROM (SELECT x, sum(pow(2.0, -rho)) AS tt, count(*)::DOUBLE AS ff FROM reg GROUP BY x)) USING (x))") + "SELECT round(quantile_cont(err, 0.5), 6) AS p50, round(quantile_cont(err, 0.9), 6) AS p90, round(quantile_cont(err, 0.99), 6) AS p99 FROM er")

# windows
add("win_rank_ties", lambda s, d: exact.edge_triangles(graph(s, d, "event_prox60")).withColumn("rank", F.rank().over(Window.partitionBy("u").orderBy(F.desc("t")))).withColumn("dense", F.dense_rank().over(Window.partitionBy("u").orderBy(F.desc("t")))).select("u", "v", "t", "rank", "dense"), S.head("event_prox60", S.TRI, S.EXACT_EDGE) + "SELECT u, v, t, CAST(rank() OVER (PARTITION BY u ORDER BY t DESC) AS INTEGER) AS rank, CAST(dense_rank() OVER (PARTITION BY u ORDER BY t DESC) AS INTEGER) AS dense FROM exact")
add("win_hop_growth", lambda s, d: exact.balls(graph(s, d, "geo_tree"), 3).withColumn("grown", F.col("n") - F.lag("n", 1, 1).over(Window.partitionBy("x").orderBy("t"))), S.head("geo_tree", *S.exact_balls(3)) + "SELECT x, t, n, n - lag(n, 1, 1) OVER (PARTITION BY x ORDER BY t) AS grown FROM (" + " UNION ALL ".join(f"SELECT x, {k} AS t, count(*) AS n FROM b{k} GROUP BY x" for k in (1, 2, 3)) + ")")


def _running(s, d):
    edges, table = _vst(s, d, "event_prox60")
    top = triangles.top_edges(triangles.edge_triangles(edges, table, "ie"), 200).join(exact.edge_triangles(edges), ["u", "v"])
    w = Window.partitionBy(F.lit(0)).orderBy(F.desc("t_est"), "u", "v")  # 200 rows
    return top.select("u", "v", F.row_number().over(w).alias("rank"), F.sum((F.col("t") >= 8).cast("int")).over(w.rowsBetween(Window.unboundedPreceding, 0)).alias("hits"))


add("win_running_pr", _running, S.head("event_prox60", *S.EDGE_T, S.TRI, S.EXACT_EDGE) + "SELECT u, v, CAST(row_number() OVER w AS INTEGER) AS rank, CAST(sum(CASE WHEN t >= 8 THEN 1 ELSE 0 END) OVER w AS BIGINT) AS hits FROM (SELECT * FROM per_edge ORDER BY t_est DESC, u, v LIMIT 200) JOIN exact USING (u, v) WINDOW w AS (ORDER BY t_est DESC, u, v)")


def _range_events(s, d):
    at = F.unix_micros(F.col("ts").cast("timestamp"))
    w = Window.partitionBy("user_id").orderBy("at").rangeBetween(-3_600_000_000, 0)
    return t(s, d, "events").withColumn("at", at).select("event_id", F.count("*").over(w).alias("last_hour"))


add("win_range_events", _range_events, "SELECT event_id, count(*) OVER (PARTITION BY user_id ORDER BY epoch_us(ts) RANGE BETWEEN 3600000000 PRECEDING AND CURRENT ROW) AS last_hour FROM events")
add("topk_edges", lambda s, d: exact.edge_triangles(graph(s, d, "event_prox300")).orderBy(F.desc("t"), "u", "v").offset(10).limit(20), S.head("event_prox300", S.TRI, S.EXACT_EDGE) + "SELECT * FROM exact ORDER BY t DESC, u, v LIMIT 20 OFFSET 10")


def _sets(s, d):
    edges, table = _vst(s, d, "docline")
    e = triangles.top_edges(triangles.edge_triangles(edges, table, "ie"), 100).select("u", "v")
    h = triangles.top_edges(exact.edge_triangles(edges), 100, value="t").select("u", "v")
    name = lambda f, n: f.agg(F.count("*").alias("n")).select(F.lit(n).alias("cell"), "n")
    return name(e.intersect(h), "tp").union(name(e.subtract(h), "fp")).union(name(h.subtract(e), "fn"))


add("set_tp_fp_fn", _sets, S.head("docline", *S.EDGE_T, S.TRI, S.EXACT_EDGE, "es AS MATERIALIZED (SELECT u, v FROM per_edge ORDER BY t_est DESC, u, v LIMIT 100)", "hs AS MATERIALIZED (SELECT u, v FROM exact ORDER BY t DESC, u, v LIMIT 100)") + "SELECT 'tp' AS cell, count(*) AS n FROM (SELECT * FROM es INTERSECT SELECT * FROM hs) UNION ALL SELECT 'fp', count(*) FROM (SELECT * FROM es EXCEPT SELECT * FROM hs) UNION ALL SELECT 'fn', count(*) FROM (SELECT * FROM hs EXCEPT SELECT * FROM es)")

# scalars
add("str_lines", lambda s, d: build.document_lines(t(s, d, "documents")).groupBy("line").agg(F.countDistinct("doc_id").alias("docs")).filter("docs > 1"), "SELECT line, count(DISTINCT doc_id) AS docs FROM (SELECT doc_id, trim(line, ' ') AS line FROM (SELECT doc_id, unnest(string_split(text, chr(10))) AS line FROM documents)) WHERE length(line) >= 12 GROUP BY 1 HAVING docs > 1")
add("str_hrefs", lambda s, d: t(s, d, "pages").select(F.explode(F.regexp_extract_all("html", F.lit('href="([^"]+)"'), F.lit(1))).alias("target")).groupBy(F.lower("target").alias("target")).agg(F.count("*").alias("n")), """SELECT lower(t) AS target, count(*) AS n FROM (SELECT unnest(regexp_extract_all(html, 'href="([^"]+)"', 1)) AS t FROM pages) GROUP BY 1""")
add("date_hourly_edges", lambda s, d: t(s, d, "events").groupBy(F.date_trunc("hour", "ts").cast("timestamp_ntz").alias("hour")).agg(F.countDistinct("user_id").alias("users"), F.count("*").alias("n")), "SELECT date_trunc('hour', ts) AS hour, count(DISTINCT user_id) AS users, count(*) AS n FROM events GROUP BY 1")
add("math_rank_bits", lambda s, d: t(s, d, "part").select(rank_of(hash_word(F.col("p_partkey"), PORTABLE8), PORTABLE8).alias("rho")).groupBy("rho").agg(F.count("*").alias("n"), F.round(F.count("*") * F.pow(F.lit(2.0), "rho"), 6).alias("scaled")), f"SELECT rho, count(*) AS n, round(count(*) * pow(2.0, rho), 6) AS scaled FROM (SELECT {S.rank('w', PORTABLE8)} AS rho FROM (SELECT {S.word('p_partkey')} AS w FROM part)) GROUP BY 1")
add("arr_adjacency_intersect", lambda s, d: twins.edge_triangles(*_twins(s, d)), S.head("event_prox60", S.TRI, S.EXACT_EDGE) + "SELECT * FROM exact")
add("map_registers", lambda s, d: _vst(s, d, "event_prox60")[1].regs.groupBy("x").agg(F.map_from_entries(F.collect_list(F.struct("j", "rho"))).alias("r")).select("x", F.size("r").alias("nz"), F.aggregate(F.map_values("r"), F.lit(0), lambda a, b: a + b).alias("ranks")), S.head("event_prox60") + "SELECT x, CAST(count(*) AS INTEGER) AS nz, CAST(sum(rho) AS INTEGER) AS ranks FROM reg GROUP BY x")
add("json_event_key", lambda s, d: t(s, d, "events").groupBy(F.get_json_object("props", "$.k").cast("int").alias("k")).agg(F.count("*").alias("n")), "SELECT CAST(json_extract_string(props, '$.k') AS INTEGER) AS k, count(*) AS n FROM events GROUP BY 1")


# SQL surface
def _sql_degree(s, d):
    edges, table = _vst(s, d, "event_prox60")
    surface.register(s, edges, table)
    return s.sql("SELECT x, count(*) AS nz, sum(power(2.0, -rho)) AS total FROM vst GROUP BY x")


add("sql_degree", _sql_degree, S.head("event_prox60") + "SELECT x, count(*) AS nz, sum(pow(2.0, -rho)) AS total FROM reg GROUP BY x")


def _by_sql(text: str):
    """A statement over the views and functions of the sketch table of event_prox60."""

    def query(s, d):
        surface.register(s, *_vst(s, d, "event_prox60"))
        return s.sql(text)

    return query


_SIDES = "FROM edges JOIN vst_packed a ON a.x = u JOIN vst_packed b ON b.x = v"
_SIZED = S.head("event_prox60", "pairs AS (SELECT * FROM e)", S.SIDES, S.sizes(), *S.joint_ml())
add("sql_joint", _by_sql(f"SELECT u, v, round(j.inter, 2) AS inter FROM (SELECT u, v, vs_joint(a.mode, a.regs, b.mode, b.regs) AS j {_SIDES})"), _SIZED + "SELECT u, v, round(inter, 2) AS inter FROM ml")
add("sql_estimate", _by_sql("SELECT x, round(vs_estimate(mode, regs), 6) AS d_est FROM vst_packed"), S.head("event_prox60") + S.measured("reg", name="d_est"))
add("sql_merge", _by_sql(f"SELECT u, v, round(vs_estimate(CAST(1 AS TINYINT), vs_merge(a.mode, a.regs, b.mode, b.regs)), 6) AS n_union {_SIDES}"), _SIZED + "SELECT u, v, round(n_union, 6) AS n_union FROM sized")
add("point_neighbourhood", lambda s, d: surface.neighbourhood(graph(s, d, "geo_tree"), 4, 2), S.head("geo_tree", "one AS (SELECT y AS z FROM arcs WHERE x = 4)", "two AS (SELECT DISTINCT a.y AS z FROM arcs a JOIN one ON a.x = one.z)") + "SELECT CAST(4 AS BIGINT) AS z, 0 AS t UNION ALL SELECT z, 1 FROM one UNION ALL SELECT z, 2 FROM two WHERE z <> 4 AND z NOT IN (SELECT z FROM one)")

# streams
add("s_accumulate_available_now", lambda s, d: live.accumulate_stream(live.edge_stream(graph(s, d, "event_prox300")), PORTABLE8).regs, S.head("event_prox300") + "SELECT x, j, rho FROM reg")
_ev = lambda s, d: live.events_stream(s, d)
_ntz = lambda f: f.withColumns({c: F.col(c).cast("timestamp_ntz") for c in ("start", "end")})
add("s_window_tumbling", lambda s, d: _ntz(live.run_now(live.windowed_degrees(_ev(s, d), F.window("ts", "1 day")), "complete", True)), "SELECT time_bucket(INTERVAL 1 DAY, ts, TIMESTAMP '1970-01-01') AS start, time_bucket(INTERVAL 1 DAY, ts, TIMESTAMP '1970-01-01') + INTERVAL 1 DAY AS \"end\", user_id, count(*) AS n, max(value) AS top FROM events GROUP BY 1, 2, 3")
add("s_window_sliding", lambda s, d: _ntz(live.run_now(live.windowed_degrees(_ev(s, d), F.window("ts", "2 days", "1 day")), "complete", True)), "SELECT s AS start, s + INTERVAL 2 DAY AS \"end\", user_id, count(*) AS n, max(value) AS top FROM (SELECT unnest([time_bucket(INTERVAL 1 DAY, ts, TIMESTAMP '1970-01-01'), time_bucket(INTERVAL 1 DAY, ts, TIMESTAMP '1970-01-01') - INTERVAL 1 DAY]) AS s, user_id, value FROM events) GROUP BY 1, 2, 3")
add("s_window_session", lambda s, d: _ntz(live.run_now(live.windowed_degrees(_ev(s, d), F.session_window("ts", "30 minutes")), "complete", True)), "SELECT min(ts) AS start, max(ts) + INTERVAL 30 MINUTE AS \"end\", user_id, count(*) AS n, max(value) AS top FROM (SELECT *, sum(fresh) OVER (PARTITION BY user_id ORDER BY ts) AS g FROM (SELECT *, CASE WHEN ts < lag(ts) OVER (PARTITION BY user_id ORDER BY ts) + INTERVAL 30 MINUTE THEN 0 ELSE 1 END AS fresh FROM events)) GROUP BY user_id, g")
add("s_dedup_late", lambda s, d: live.run_now(live.without_repeats(_ev(s, d).select("ts", "event_id"), ["event_id"])).select("event_id"), "SELECT DISTINCT event_id FROM events")
add("s_interval_join", lambda s, d: live.run_now(live.live_proximity(_ev(s, d), 60)).distinct(), S.graph_sql("event_prox60"))
