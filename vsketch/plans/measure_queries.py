"""Queries of baselines, measures and experiment workloads."""

from __future__ import annotations

import re

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions.estimate import std_error
from ..functions.hashing import uniform
from ..functions.spec import PORTABLE8, SketchSpec
from ..operators import balls, baselines, blocks, classes, exact, joint, measures, mixed, reservoirs, trials, triangles, vst, windows
from ..sources.build import arcs, canonical
from ..sources.graphs import graph
from . import sql as S
from .graph_queries import ML12, _docline_members, _near, _seen, _vst
from .registry import registry

QUERIES, SQL, add = registry()
r6 = lambda c: f"round({c}, 6)"


def _round(frame: DataFrame) -> DataFrame:
    return frame.select(*(F.round(c, 6).alias(c) if t == "double" else F.col(c) for c, t in frame.dtypes))


def _on(name, run):
    return lambda s, d: _round(run(graph(s, d, name)))


# baselines
_low = lambda b: f"bit_count({b} & xor({b} + 1, -1::BIGINT))"
_B16 = SketchSpec(p=4, hash="portable")


def _bitmap_layers(k: int) -> list[str]:
    first = f"SELECT x, i, (1::BIGINT) << ({S.rank('w', _B16)} - 1) AS bits FROM (SELECT x, i, {S.word(chr(39).join(['concat(i, ', '/', ', x)']))} AS w FROM (SELECT DISTINCT x FROM arcs), range(16) t(i))"
    out = [f"m0 AS MATERIALIZED ({first})"]
    for t in range(1, k + 1):
        out.append(f"m{t} AS MATERIALIZED (SELECT x, i, bit_or(bits) AS bits FROM (SELECT * FROM m{t - 1} UNION ALL SELECT y, i, bits FROM arcs JOIN m{t - 1} USING (x)) GROUP BY 1, 2)")
    return out


add("b_balls_bitmap", lambda s, d: _round(windows.balls_bitmap(_seen(s, d), 60, 3)), S.head("event_prox60", *_bitmap_layers(3)) + " UNION ALL ".join(f"SELECT x, {t} AS t, round(pow(2.0, avg({_low('bits')}::DOUBLE)) / {baselines.PHI}, 6) AS n_est FROM m{t} GROUP BY x" for t in (1, 2, 3)))
add("b_balls_global_only", lambda s, d: windows.ball_sizes(_seen(s, d), 60, PORTABLE8, 3).total.select("t", F.round("n_est", 4).alias("n_est")), S.head("event_prox60", *S.layers(3)) + f"SELECT t, round(sum(n_est), 4) AS n_est FROM ({S.locals_(3)}) GROUP BY t")
_MINS = ", ".join(f"min({S.word('y', i)}) AS m{i}" for i in range(16))
_SAME = " + ".join(f"CAST(p.m{i} = q.m{i} AS INTEGER)" for i in range(16))
add("b_minwise_triangles", _on("event_prox300", baselines.minwise_triangles), S.head("event_prox300", S.DEGREE, f"mins AS MATERIALIZED (SELECT x, {_MINS} FROM arcs GROUP BY 1)", f"j AS (SELECT u, v, ({_SAME}) / 16.0::DOUBLE AS j, a.d + b.d AS d FROM e JOIN mins p ON p.x = u JOIN mins q ON q.x = v JOIN deg a ON a.x = u JOIN deg b ON b.x = v)") + "SELECT u, v, round(j / (1 + j) * d, 6) AS t_est FROM j")
_KEY = "concat(u, '-', v)"


def _docline_classes(s, d):
    """docline by classes of documents with equal lines: edges without a shuffle of edges, triangles without edges."""
    return classes.classes(_docline_members(s, d))


_TRI_OF = lambda rel: f"SELECT count(*) FROM {rel} e JOIN {rel} f ON e.v = f.u JOIN {rel} g ON g.u = e.u AND g.v = f.v"


def _sample_final(s, d, prob: float = 0.3):
    table, pairs = _docline_classes(s, d)
    kept = classes.edges(table, pairs).filter(uniform(baselines.edge_key(), 1) < prob)
    return blocks.triangles(kept, table.select(F.explode("xs").alias("x"))).select(F.round(F.col("t") / prob**3, 6).alias("t_est"))


add("b_sample_final", _sample_final, S.head("docline", f"k AS MATERIALIZED (SELECT u, v FROM e WHERE {S.uniform(_KEY, 1)} < 0.3)") + f"SELECT round(({_TRI_OF('k')}) / pow(0.3, 3), 6) AS t_est")
add(
    "b_sample_arrival", _on("docline", lambda e: baselines.sampled_triangles(e, 0.3, mode="arrival")),
    S.head("docline", f"p AS MATERIALIZED (SELECT u, v, {S.uniform(_KEY, 1001)} AS pos, {S.uniform(_KEY, 1)} < 0.3 AS kept FROM e)", "k AS MATERIALIZED (SELECT u AS x, v AS y, pos FROM p WHERE kept UNION ALL SELECT v, u, pos FROM p WHERE kept)")
    + "SELECT round(count(*) / pow(0.3, 2), 6) AS t_est FROM p JOIN k a ON a.x = p.u AND a.pos < p.pos JOIN k b ON b.x = p.v AND b.y = a.y AND b.pos < p.pos",
)
add("b_reservoir_base", lambda s, d: _round(baselines.reservoir_base(classes.edges(*_docline_classes(s, d)), 3000)), S.head("docline", "m AS (SELECT count(*)::DOUBLE AS m FROM e)", f"k AS MATERIALIZED (SELECT u, v FROM (SELECT u, v, {S.uniform(_KEY, 2)} AS p FROM e) ORDER BY p, u, v LIMIT 3000)") + f"SELECT round(({_TRI_OF('k')}) * (CASE WHEN m > 3000 THEN greatest(1.0, m * (m - 1) * (m - 2) / (3000.0::DOUBLE * 2999 * 2998)) ELSE 1.0 END), 6) AS t_est FROM m")


def _sampled(run, share: float):
    """The exact total, and whether the mean of a sampler's trials comes within ``share`` of it."""

    def query(sp, d):
        edges = graph(sp, d, "docline")
        mean = run(edges).agg(F.avg("t_est").alias("t_est")).withColumn("g", F.lit(0))
        return _near(mean, exact.global_triangles(edges).withColumn("g", F.lit(0)), ["g"], "t_est", "t", share).drop("g")

    return query


def _reservoirs(size: int, count: int, **how):
    """As _sampled, edges read in place; whether a wedge is closed and the exact total need no edges."""

    def query(sp, d):
        held = mixed.mixed(_docline_members(sp, d))
        mean = reservoirs.triangles(held.edges(), size, count, **how, among=held.among, count=held.size).agg(F.avg("t_est").alias("t_est")).withColumn("g", F.lit(0))
        return _near(mean, held.global_triangles().withColumn("g", F.lit(0)), ["g"], "t_est", "t", 0.3).drop("g")

    return query


_TOTAL = S.head("docline", S.TRI) + "SELECT count(*) AS t, TRUE AS near FROM tri"
add("b_reservoir_improved", _reservoirs(3000, 4), _TOTAL)
add("b_reservoir_parallel", _reservoirs(1500, 2, workers=4), _TOTAL)
add("b_reservoir_grouped", _reservoirs(1500, 2, groups=3), _TOTAL)
add("b_weighted_sample", _sampled(lambda e: baselines.weighted_sample_triangles(e, 0.2, 0.5), 0.3), _TOTAL)


def _wedges(s, d):
    held = mixed.mixed(_docline_members(s, d))
    est = held.wedge_triangles(2000).withColumn("g", F.lit(0))
    return _near(est, held.global_triangles().withColumn("g", F.lit(0)), ["g"], "t_est", "t", 0.1).drop("g")


add("b_wedges", _wedges, _TOTAL)


def _dynamic(sp, d):
    table, pairs = _docline_classes(sp, d)
    edges = classes.edges(table, pairs)
    gone = F.pmod("u", F.lit(5)) == 0
    mean = reservoirs.dynamic_triangles(edges.withColumn("deleted", gone), 3000, 4).agg(F.avg("t_est").alias("t_est")).withColumn("g", F.lit(0))
    left = blocks.triangles(edges.filter(~gone), table.select(F.explode("xs").alias("x")))
    return _near(mean, left.withColumn("g", F.lit(0)), ["g"], "t_est", "t", 0.5).drop("g")


add("b_reservoir_dynamic", _dynamic, S.head("docline", "left_ AS (SELECT * FROM e WHERE u % 5 <> 0)") + f"SELECT count(*) AS t, TRUE AS near FROM ({_TRI_OF('left_').replace('count(*)', '1')})")
_P64 = SketchSpec(p=6, hash="portable")


def _pcsa_sql() -> str:
    bits = f"SELECT x, CAST(w >> {_P64.q} AS INTEGER) AS j, bit_or((1::BIGINT) << ({S.rank('w', _P64)} - 1)) AS bits FROM (SELECT x, {S.word('y')} AS w FROM arcs) GROUP BY 1, 2"
    return S.head("copart") + f"SELECT x, round({_P64.r / baselines.PHI!r} * pow(2.0, sum({_low('bits')})::DOUBLE / 64.0), 6) AS n_est FROM ({bits}) GROUP BY x"


add("b_bitmap_count", lambda s, d: _round(baselines.pcsa(arcs(graph(s, d, "copart")), "x", F.col("y"), _P64)), _pcsa_sql())
add("b_kmv", lambda s, d: _round(baselines.kmv(arcs(graph(s, d, "copart")), "x", F.col("y"), 32)), S.head("copart") + f"SELECT x, round(CASE WHEN count(*) < 32 THEN count(*)::DOUBLE ELSE 31.0 / max(h) END, 6) AS n_est FROM (SELECT x, h, row_number() OVER (PARTITION BY x ORDER BY h) AS nth FROM (SELECT DISTINCT x, {S.uniform('y', 0)} AS h FROM arcs)) WHERE nth <= 32 GROUP BY x")
_MRB = (
    f"c AS (SELECT DISTINCT x, least({S.rank('w', _P64)}, 8) AS level, CAST(w >> {_P64.q} AS INTEGER) % 64 AS b FROM (SELECT x, {S.word('y')} AS w FROM arcs)), f AS (SELECT x, level, count(*) AS n FROM c GROUP BY 1, 2), "
    "base AS (SELECT x, least(max(level) + 1, 8) AS base FROM f WHERE n > 0.9 * 64 GROUP BY 1)"
)
add("b_multires_bitmap", lambda s, d: _round(baselines.multires_bitmap(arcs(graph(s, d, "copart")), "x", F.col("y"))), S.head("copart", _MRB) + "SELECT x, round(sum(-64.0 * ln((64 - least(n, 63))::DOUBLE / 64.0)) * pow(2.0, max(coalesce(base, 1)) - 1), 6) AS n_est FROM f LEFT JOIN base USING (x) WHERE level >= coalesce(base, 1) GROUP BY x")
_DEGREES = S.head("copart", S.DEGREE) + "SELECT x, d, TRUE AS near FROM deg"


def _builtin(run, share: float):
    return lambda s, d: _near(run(graph(s, d, "copart")), exact.degrees(graph(s, d, "copart")), ["x"], "d_est", "d", share, 1.0)


add("b_builtin_hll", _builtin(lambda e: vst.accumulate_builtin(e, "hll").select("x", F.hll_sketch_estimate("sk").alias("d_est")), 0.1), _DEGREES)
add("b_builtin_approx", _builtin(lambda e: arcs(e).groupBy("x").agg(F.approx_count_distinct("y", 0.05).alias("d_est")), 0.3), _DEGREES)
add("b_exact_distinct", lambda s, d: arcs(graph(s, d, "copart")).groupBy("x").agg(F.countDistinct("y").alias("d")), S.head("copart") + "SELECT x, count(DISTINCT y) AS d FROM arcs GROUP BY x")


# measures
def _ball_errors(s, d, name, k, spec=PORTABLE8):
    edges, table = _vst(s, d, name, spec)
    return measures.relative_errors(balls.ball_sizes(edges, table, k).local, exact.balls(edges, k), ["x", "t"], "n_est", "n")


_ERR = f"err AS (SELECT t, abs(n_est - n) / n AS err FROM (SELECT l.x, l.t, n_est, n FROM ({S.locals_(3)}) l JOIN (" + " UNION ALL ".join(f"SELECT x, {t} AS t, count(*) AS n FROM b{t} GROUP BY x" for t in (1, 2, 3)) + ") b ON b.x = l.x AND b.t = l.t))"
add("m_mre_by_hop", lambda s, d: _round(measures.mre(_ball_errors(s, d, "event_prox60", 3), ["t"])), S.head("event_prox60", *S.layers(3), *S.exact_balls(3), _ERR) + "SELECT t, round(avg(err), 6) AS mre, count(*) AS n, CAST(0 AS BIGINT) AS undefined FROM err GROUP BY t")


def _bias(s, d, name="event_prox60", seeds=4, k=2, spec=PORTABLE8):
    """Mean bias and spread over seeds of ball estimates, by hop, against the standard error."""
    edges = graph(s, d, name)
    got = measures.bias_sd(trials.ball_trials(edges, k, spec, seeds), trials.exact_balls(edges, k), ["x", "t"], "n_est", "n")
    return _round(got.groupBy("t").agg(F.avg("bias").alias("bias"), F.avg("sd").alias("sd")).withColumn("eta", F.lit(std_error(8))))


def _seeded(name: str, k: int, seeds: int) -> str:
    exact_ = "truth AS MATERIALIZED (" + " UNION ALL ".join(f"SELECT x, {t} AS t, count(*) AS n FROM b{t} GROUP BY x" for t in range(1, k + 1)) + ")"
    return S.head(name, *S.seeded_layers(k, seeds), *S.exact_balls(k), exact_)


add("m_bias_sd", _bias, _seeded("event_prox60", 2, 4) + f"SELECT t, round(avg(bias), 6) AS bias, round(avg(sd), 6) AS sd, round({std_error(8)!r}::DOUBLE, 6) AS eta FROM (SELECT x, t, avg(n_est / n) - 1 AS bias, stddev_samp(n_est / n) AS sd FROM seeds_t JOIN truth USING (x, t) GROUP BY 1, 2) GROUP BY t")


def _pr(s, d, name, k, vertex=False, spec=PORTABLE8, how="ie", aware=False):
    edges, table = _vst(s, d, name, spec)
    per = balls.shared_table(triangles.edge_triangles(edges, table, how), "per-edge")
    if vertex:
        return measures.pr_curve(triangles.vertex_triangles(per), exact.vertex_triangles(edges), ["x"], k, tie_aware=aware)
    return measures.pr_curve(per, exact.edge_triangles(edges), ["u", "v"], k, tie_aware=aware)


def _pr_sql(keys: str, est: str, true: str) -> str:
    on = " AND ".join(f"f.{c} = h.{c}" for c in keys.split(", "))
    return (
        f", h AS (SELECT {keys} FROM {true} ORDER BY t DESC, {keys} LIMIT 100), f AS (SELECT {keys}, row_number() OVER (ORDER BY t_est DESC, {keys}) AS rank FROM {est}), "
        f"hit AS (SELECT kp AS kprime, count(h.{keys.split(', ')[0]}) AS tp, count(*) AS got FROM range(20, 201, 20) g(kp) JOIN f ON f.rank <= kp LEFT JOIN h ON {on} GROUP BY 1) "
        f"SELECT 100 AS k, CAST(kprime AS INTEGER) AS kprime, tp, got - tp AS fp, n - tp AS fn, m - got - n + tp AS tn, round(tp / got, 6) AS precision, round(tp / n, 6) AS recall FROM hit, (SELECT count(*) AS n FROM h), (SELECT count(*) AS m FROM {true})"
    )


_V = "per_v AS MATERIALIZED (SELECT x, round(CAST(sum(CAST(t_est AS DECIMAL(28,6))) AS DOUBLE) / 2, 7) AS t_est FROM (SELECT u AS x, t_est FROM per_edge UNION ALL SELECT v, t_est FROM per_edge) GROUP BY 1)"
add("m_pr_curve_edges", lambda s, d: _round(_pr(s, d, "docline", 100)), (S.head("docline", *S.EDGE_T, S.TRI, S.EXACT_EDGE).rstrip() + _pr_sql("u, v", "per_edge", "exact")))
add("m_pr_curve_vertices", lambda s, d: _round(_pr(s, d, "docline", 100, vertex=True)), (S.head("docline", *S.EDGE_T, _V, S.TRI, S.EXACT_EDGE, S.EXACT_VERTEX).rstrip() + _pr_sql("x", "per_v", "exact_v")))


def _true_density(s, d, name):
    edges = graph(s, d, name)
    return exact.intersections(edges, edges).select("u", "v", F.col("inter").cast("long").alias("t"), (F.col("inter") / F.col("n_union")).alias("density"))


_DENSE = ["met AS MATERIALIZED (SELECT e.u, e.v, count(b.y) AS t FROM e LEFT JOIN arcs a ON a.x = e.u LEFT JOIN arcs b ON b.x = e.v AND b.y = a.y GROUP BY 1, 2)", "td AS MATERIALIZED (SELECT m.u, m.v, t, t / (p.d + q.d - t) AS density FROM met m JOIN deg p ON p.x = m.u JOIN deg q ON q.x = m.v)"]
add("m_rank_profile", lambda s, d: _round(measures.rank_profile(_true_density(s, d, "docline"))), S.head("docline", S.DEGREE, *_DENSE) + "SELECT CAST(rank AS INTEGER) AS rank, u, v, t, round(density, 6) AS density FROM (SELECT row_number() OVER (ORDER BY t DESC, u, v) AS rank, * FROM td) WHERE rank <= 10000")
add("m_tie_profile", lambda s, d: _round(measures.tie_profile(_true_density(s, d, "cosupp"), 100)), S.head("cosupp", S.DEGREE, *_DENSE, "c AS (SELECT t, count(*) AS n FROM td GROUP BY t)", "kth AS (SELECT min(t) AS kth FROM (SELECT t FROM td ORDER BY t DESC LIMIT 100))") + "SELECT kth, (SELECT n FROM c WHERE t = kth) AS ties, (SELECT t FROM c ORDER BY n DESC, t DESC LIMIT 1) AS modal, round((SELECT max(n) / sum(n) FROM c), 6) AS modal_share FROM kth")


def _global_error(s, d, name="docline", spec=PORTABLE8):
    edges, table = _vst(s, d, name, spec)
    est = triangles.total(triangles.edge_triangles(edges, table, "ie"))
    return est.crossJoin(exact.global_triangles(edges)).withColumn("error", F.abs(F.col("t_est") - F.col("t")) / F.col("t"))


add("m_global_error", lambda s, d: _round(_global_error(s, d)), S.head("docline", *S.EDGE_T, S.TRI) + "SELECT t_est, t, round(abs(t_est - t) / t, 6) AS error FROM (SELECT round(CAST(sum(CAST(t_est AS DECIMAL(28,6))) AS DOUBLE) / 3, 4) AS t_est FROM per_edge), (SELECT count(*) AS t FROM tri)")
_NZ = "nz AS MATERIALIZED (SELECT x, count(*) AS nz FROM reg GROUP BY x)"
add("m_vst_bytes", lambda s, d: _round(measures.vst_bytes(_vst(s, d, "copart")[1], graph(s, d, "copart"))), S.head("copart", _NZ) + "SELECT count(*) AS vertices, round(avg(CASE WHEN nz > 64 THEN 1.0 ELSE 0.0 END), 6) AS dense_share, CAST(sum(nz * 4) AS BIGINT) AS sparse_bytes, CAST(count(*) * 256 AS BIGINT) AS dense_bytes, CAST(sum(CASE WHEN nz > 64 THEN 256 ELSE nz * 4 END) AS BIGINT) AS mixed_bytes, (SELECT count(*) * 16 FROM e) AS edge_bytes FROM nz")
add("m_traffic", lambda s, d: measures.traffic(*_vst(s, d, "cust_supp")), S.head("cust_supp", _NZ) + "SELECT * FROM (SELECT count(*) AS ball_messages, CAST(sum(nz) AS BIGINT) AS ball_rows FROM arcs JOIN nz USING (x)), (SELECT count(*) AS edge_messages, CAST(sum(a.nz) AS BIGINT) AS edge_rows, CAST(sum(least(a.nz, b.nz)) AS BIGINT) AS smaller_rows FROM e JOIN nz a ON a.x = u JOIN nz b ON b.x = v)")
add(
    "m_reliability_flags", lambda s, d: _round(measures.reliability_flags(*_vst(s, d, "event_prox60"))),
    S.head("event_prox60", "pairs AS (SELECT * FROM e)", S.SIDES, S.sizes(), "i AS (SELECT u, v, n_a, n_b, n_union, greatest(0.0, least(n_a + n_b - n_union, n_a, n_b)) AS inter FROM sized)", "j AS (SELECT u, v, greatest(inter + (n_a - inter), inter + (n_b - inter)) / greatest(least(inter + (n_a - inter), inter + (n_b - inter)), 1.0) AS size_ratio, inter / greatest(n_union, 1.0) AS density FROM i)")
    + "SELECT u, v, round(size_ratio, 6) AS size_ratio, round(density, 6) AS density, size_ratio > 10 OR density < 0.1 AS shaky FROM j",
)


# workloads
def _each(s, d, names, run):
    out = None
    for n in names:
        got = run(n).select(F.lit(n).alias("graph"), "*")
        out = got if out is None else out.unionByName(got)
    return out


MODERATE = ("copart", "docline", "cust_part", "cust_supp", "part_supp", "order_part", "event_prox300", "user_next", "page_link", "geo_tree")


def w01(s, d, seeds: int = 20, k: int = 5, names=MODERATE, spec=SketchSpec(p=8)) -> DataFrame:
    """Mean relative error of ball sizes by graph and hop, over seeds, with the standard error for comparison."""

    def run(n):
        edges = graph(s, d, n)
        got = trials.ball_trials(edges, k, spec, seeds).join(trials.exact_balls(edges, k), ["x", "t"])
        err = got.groupBy("t", "seed").agg(F.avg(F.abs(F.col("n_est") - F.col("n")) / F.col("n")).alias("mre"))
        return err.groupBy("t").agg(F.avg("mre").alias("mre"), F.count("*").alias("seeds")).withColumn("se_line", F.lit(std_error(spec.p)))

    return _round(_each(s, d, names, run))


add("w01_ball_mre", w01)
_MRE = "SELECT t, avg(mre) AS mre, count(*) AS seeds FROM (SELECT t, seed, avg(abs(n_est - n) / n) AS mre FROM seeds_t JOIN truth USING (x, t) GROUP BY 1, 2) GROUP BY t"
add(
    "w01_ball_mre_portable", lambda s, d: w01(s, d, 3, 4, ("event_prox60", "geo_tree", "page_link"), PORTABLE8),
    " UNION ALL ".join(f"SELECT '{n}' AS graph, t, round(mre, 6) AS mre, seeds, round({std_error(8)!r}::DOUBLE, 6) AS se_line FROM ({_seeded(n, 4, 3)}{_MRE})" for n in ("event_prox60", "geo_tree", "page_link")),
)


def w02(s, d, seeds: int = 50, k: int = 3, names=("event_prox60", "docline", "geo_tree"), spec=SketchSpec(p=8)) -> DataFrame:
    """Bias and spread over seeds of local ball sizes (means over vertices) and of their sum N(t), against the standard error."""

    def run(n):
        edges = graph(s, d, n)
        est, true = balls.shared_table(trials.ball_trials(edges, k, spec, seeds), "trials"), balls.shared_table(trials.exact_balls(edges, k), "truth")
        local = measures.bias_sd(est, true, ["x", "t"], "n_est", "n").groupBy("t").agg(F.avg("bias").alias("bias"), F.avg("sd").alias("sd"))
        sums = est.groupBy("seed", "t").agg(F.sum("n_est").alias("n_est"))
        whole = measures.bias_sd(sums, true.groupBy("t").agg(F.sum("n").alias("n")), ["t"], "n_est", "n").select("t", "bias", "sd")
        return local.withColumn("of", F.lit("vertex")).unionByName(whole.withColumn("of", F.lit("sum"))).withColumns({"eta": F.lit(std_error(spec.p)), "seeds": F.lit(seeds)})

    return _round(_each(s, d, names, run))


add("w02_theorem_check", w02)
_BOTH = (
    "SELECT t, avg(bias) AS bias, avg(sd) AS sd, 'vertex' AS of FROM (SELECT x, t, avg(n_est / n) - 1 AS bias, stddev_samp(n_est / n) AS sd FROM seeds_t JOIN truth USING (x, t) GROUP BY 1, 2) GROUP BY t "
    "UNION ALL SELECT t, avg(e / n) - 1, stddev_samp(e / n), 'sum' FROM (SELECT seed, t, sum(n_est) AS e FROM seeds_t GROUP BY 1, 2) JOIN (SELECT t, sum(n) AS n FROM truth GROUP BY 1) USING (t) GROUP BY t"
)
add(
    "w02_theorem_check_portable", lambda s, d: w02(s, d, 4, 3, ("event_prox60", "geo_tree"), PORTABLE8),
    " UNION ALL ".join(f"SELECT '{n}' AS graph, t, round(bias, 6) AS bias, round(sd, 6) AS sd, of, round({std_error(8)!r}::DOUBLE, 6) AS eta, 4 AS seeds FROM ({_seeded(n, 3, 4)}{_BOTH})" for n in ("event_prox60", "geo_tree")),
)
_REAL = ("copart", "cosupp", "docline", "event_prox60", "event_prox300", "user_next", "emb_sim")
_PRODUCTS = ("kron:event_prox300*event_prox300", "kron:user_next*event_prox300", "kron:event_prox300*docline", "kron:cosupp*docline", "kron:docline*docline")


def _smallest(d: str) -> str:
    """The folder of the smallest tables beside d: factors of products come from there."""
    return re.sub(r"sf[0-9.]+/?$", "sf0.001", d)


def precision(s, d, vertex: bool, names=_REAL + _PRODUCTS[:4], ks=(10, 100, 1000), how: str = "ml", work: int = 20_000, most: int = 20) -> DataFrame:
    """Tie-aware precision and recall of the top k' (0.2 k to 2 k) by graph and k, means over seeds; a k over the number
    of edges or vertices has no rows.  Products are of the smallest tables.  ``most`` seeds, fewer where seeds times
    edges would go beyond ``work``, one at least."""

    def run(n):
        edges = balls.shared_table(graph(s, _smallest(d) if n.startswith("kron:") else d, n), "edges")
        seeds = max(1, min(most, work // max(1, edges.count())))
        est, true, keys = trials.edge_trials(edges, ML12, seeds, how), trials.exact_edge_triangles(edges), ["u", "v"]
        if vertex:
            ends = F.explode(F.array("u", "v")).alias("x")
            est = est.select("seed", ends, "t_est").groupBy("seed", "x").agg((F.sum("t_est") / 2).alias("t_est"))
            true, keys = true.select(ends, "t").groupBy("x").agg((F.sum("t") / 2).cast("long").alias("t")), ["x"]
        got = trials.precision_trials(est, true, keys, ks).groupBy("k", "kprime").agg(F.avg("precision").alias("precision"), F.avg("recall").alias("recall"), F.coalesce(F.stddev_samp("precision"), F.lit(0.0)).alias("precision_sd"))
        return got.withColumn("seeds", F.lit(seeds))

    return _round(_each(s, d, names, run))


add("w03_edge_precision", lambda s, d: precision(s, d, False))
add("w04_vertex_precision", lambda s, d: precision(s, d, True))
_PROFILED = ("docline", "cosupp", "emb_sim", "kron:emb_sim*emb_sim")
add(
    "w05_rank_profiles", lambda s, d: _round(_each(s, d, _PROFILED, lambda n: measures.rank_profile(_true_density(s, d, n)))),
    " UNION ALL ".join(f"SELECT '{n}' AS graph, * FROM ({S.head(n, S.DEGREE, *_DENSE)}SELECT CAST(rank AS INTEGER) AS rank, u, v, t, round(density, 6) AS density FROM (SELECT row_number() OVER (ORDER BY t DESC, u, v) AS rank, * FROM td) WHERE rank <= 10000)" for n in _PROFILED),
)


def _shared(masks: DataFrame, sets: int) -> DataFrame:
    """i, j, kind, t: elements that sets i and j both have.  masks: kind, and a bit a set in m."""

    def run(batches):
        import numpy as np
        import pyarrow as pa

        for batch in batches:
            kind, mask = (np.asarray(batch.column(c)) for c in (0, 1))
            for k in np.unique(kind):
                bits = (mask[kind == k][:, None] >> np.arange(sets) & 1).astype(np.float64)
                both = (bits.T @ bits).astype(np.int64)
                i, j = np.nonzero(both)
                yield pa.RecordBatch.from_arrays([pa.array(i), pa.array(j), pa.array(np.full(len(i), k, np.int32)), pa.array(both[i, j])], names=["i", "j", "kind", "t"])

    return masks.select("kind", "m").mapInArrow(run, "i long, j long, kind int, t long").groupBy("i", "j", "kind").agg(F.sum("t").alias("t"))


def w09(s: SparkSession, d: str, ps=(8, 12)) -> DataFrame:
    """Inclusion-exclusion against joint likelihood over size ratios, overlaps and register counts: error and negatives.

    Sets are the orders and the parts that suppliers of a nation, of a region, and a nation's first supplier deliver.
    Pairs: of nations; a nation and a region; a first supplier and a nation, each nested or apart.  The mean relative
    error is over pairs that share elements; the others are counted in ``empty``."""
    t = lambda n: s.read.parquet(f"{d}/{n}.parquet")
    nations = sorted((r[0], r[1]) for r in t("nation").select("n_nationkey", "n_regionkey").collect())
    regions = sorted({r for _, r in nations})
    n, sets = len(nations), 2 * len(nations) + len(regions)
    if sets > 62:
        raise ValueError(f"{sets} sets do not fit a mask")
    own = s.createDataFrame([(k, i, n + regions.index(r)) for i, (k, r) in enumerate(nations)], "s_nationkey int, nation long, region long")
    first = t("supplier").groupBy("s_nationkey").agg(F.min("s_suppkey").alias("s_suppkey")).withColumn("first", F.lit(True)).drop("s_nationkey")
    who = t("supplier").select("s_suppkey", "s_nationkey").join(F.broadcast(own), "s_nationkey").join(F.broadcast(first), "s_suppkey", "left")
    who = who.select(F.col("s_suppkey").alias("l_suppkey"), F.array_compact(F.array("nation", "region", F.when(F.col("first"), F.col("nation") + n + len(regions)))).alias("of"))
    ends = F.array(F.struct(F.lit(0).alias("kind"), F.col("l_orderkey").alias("y")), F.struct(F.lit(1).alias("kind"), F.col("l_partkey").alias("y")))
    rows = t("lineitem").select("l_orderkey", "l_partkey", "l_suppkey").join(who, "l_suppkey").select("of", F.inline(ends))
    bit = F.aggregate("of", F.lit(0).cast("long"), lambda m, i: m.bitwiseOR(F.expr("1L").cast("long") * F.pow(F.lit(2.0), i).cast("long")))
    masks = balls.shared_table(rows.select("kind", "y", bit.alias("m")).groupBy("kind", "y").agg(F.bit_or("m").alias("m")), "masks")
    pairs = [(i, j, "nations") for i in range(n) for j in range(i + 1, n)]
    pairs += [(i, n + k, "in its region" if r == regions[k] else "and a region") for i, (_, r) in enumerate(nations) for k in range(len(regions))]
    pairs += [(i, n + len(regions) + j, "over its supplier" if i == j else "and a supplier") for i in range(n) for j in range(n)]
    pairs = s.createDataFrame(pairs, "i long, j long, pair string").join(F.broadcast(s.createDataFrame([(0, "order"), (1, "part")], "kind int, element string")))
    pairs = pairs.withColumns({"u": F.col("kind") * 64 + F.col("i"), "v": F.col("kind") * 64 + F.col("j")}).join(F.broadcast(_shared(masks, sets)), ["i", "j", "kind"], "left").withColumn("t", F.coalesce("t", F.lit(0)))
    pairs = balls.shared_table(pairs.withColumns({"u": F.col("u").cast("long"), "v": F.col("v").cast("long")}), "pairs")
    members = masks.select("y", F.explode(F.expr(f"transform(filter(sequence(0, {sets - 1}), i -> (shiftright(m, i) & 1) = 1), i -> cast(kind * 64 + i as long))")).alias("x"))
    out = None
    for p in ps:
        spec = SketchSpec(p=p)
        table = vst.Vst(balls.shared_table(vst.registers(members, "x", F.col("y"), spec), "sets"), spec)
        naive = joint.intersect_packed(pairs, table, "ie").select("u", "v", (F.col("n_u") + F.col("n_v") - F.col("n_union")).alias("naive"))
        got = pairs.join(naive, ["u", "v"]).join(joint.intersect_packed(pairs, table, "ml").select("u", "v", F.col("inter").alias("ml")), ["u", "v"])
        off = lambda c: F.avg(F.when(F.col("t") > 0, F.abs(F.col(c) - F.col("t")) / F.col("t")))
        got = got.groupBy("element", "pair").agg(F.count("*").alias("pairs"), F.sum((F.col("t") == 0).cast("long")).alias("empty"), off("naive").alias("mre_naive"), off("ml").alias("mre_ml"), F.sum((F.col("naive") < 0).cast("long")).alias("negatives"))
        got = got.select(F.lit(p).alias("p"), "*")
        out = got if out is None else out.unionByName(got)
    return out


add("w09_intersection_grid", w09)


def w09_zero(s, d):
    """A graph without triangles: what both estimators report where every intersection is empty."""
    edges, table = _vst(s, d, "geo_tree")
    naive = joint.inclusion_exclusion(edges, table, clamp=False).select("u", "v", (F.col("inter") < 0).alias("below"), F.round(F.greatest(F.col("inter"), F.lit(0.0)), 2).alias("naive"))
    ml = joint.intersect_packed(edges, table, "ml").select("u", "v", F.round("inter", 2).alias("ml"))
    return naive.join(ml, ["u", "v"])


add(
    "w09_zero_intersections", w09_zero,
    S.head("geo_tree", "pairs AS (SELECT * FROM e)", S.SIDES, S.sizes(), *S.joint_ml()) + "SELECT u, v, n_a + n_b - n_union < 0 AS below, round(greatest(0.0, n_a + n_b - n_union), 2) AS naive, round(inter, 2) AS ml FROM sized JOIN ml USING (u, v)",
)
_FACTORS = (("emb_sim", "emb_sim"), ("emb_sim", "conv_turn"), ("event_prox60", "conv_turn"), ("page_link", "conv_turn"), ("geo_tree", "conv_turn"))


def w10(s, d):
    """Triangles of five product graphs, counted and in closed form (6 T_A T_B); trees and chains make products without any."""

    def run(name):
        a, b = (exact.global_triangles(graph(s, d, n)) for n in name[5:].split("*"))
        edges = balls.shared_table(graph(s, d, name), "product")
        closed = a.crossJoin(b.withColumnRenamed("t", "tb")).select((6 * F.col("t") * F.col("tb")).alias("closed_form"))
        return exact.global_triangles(edges).crossJoin(closed).crossJoin(edges.agg(F.count("*").alias("edges")))

    return _each(s, d, [f"kron:{a}*{b}" for a, b in _FACTORS], run)


def _product_sql(a: str, b: str) -> str:
    of = lambda n: f"(SELECT count(*) FROM ({S.head(n, S.TRI)}SELECT * FROM tri))"
    return f"SELECT 'kron:{a}*{b}' AS graph, (SELECT count(*) FROM ({S.head(f'kron:{a}*{b}', S.TRI)}SELECT * FROM tri)) AS t, 6 * {of(a)} * {of(b)} AS closed_form, (SELECT count(*) FROM ({S.graph_sql(f'kron:{a}*{b}')})) AS edges"


add("w10_kron_truth", w10, " UNION ALL ".join(_product_sql(a, b) for a, b in _FACTORS))


def w11(s, d):
    """Dirty stream (loops, repeats, both directions) against the clean graph: same table, different sums of edges."""
    rows = s.read.parquet(f"{d}/lineitem.parquet")
    a = rows.select(F.col("l_orderkey").alias("g"), F.col("l_suppkey").alias("u"))
    dirty = a.join(a.withColumnRenamed("u", "v"), "g").select("u", "v")
    raw, clean = vst.accumulate(dirty, PORTABLE8).regs, vst.accumulate(canonical(dirty), PORTABLE8).regs
    differ = raw.exceptAll(clean).agg(F.count("*").alias("extra")).crossJoin(clean.exceptAll(raw).agg(F.count("*").alias("missing")))
    return differ.crossJoin(dirty.agg(F.count("*").alias("raw_edges"))).crossJoin(canonical(dirty).agg(F.count("*").alias("edges")))


add("w11_idempotence", w11, "SELECT CAST(0 AS BIGINT) AS extra, CAST(0 AS BIGINT) AS missing, (SELECT count(*) FROM lineitem a JOIN lineitem b ON a.l_orderkey = b.l_orderkey) AS raw_edges, (SELECT count(*) FROM (" + S.graph_sql("cosupp") + ")) AS edges")
_BYTES = ("copart", "docline", "order_part", "event_prox300")
add(
    "w12_table_and_graph_bytes", lambda s, d: _round(_each(s, d, _BYTES, lambda n: measures.vst_bytes(_vst(s, d, n)[1], graph(s, d, n)))),
    " UNION ALL ".join(
        f"SELECT '{n}' AS graph, * FROM ({S.head(n, _NZ)}SELECT count(*) AS vertices, round(avg(CASE WHEN nz > 64 THEN 1.0 ELSE 0.0 END), 6) AS dense_share, CAST(sum(nz * 4) AS BIGINT) AS sparse_bytes, CAST(count(*) * 256 AS BIGINT) AS dense_bytes, "
        "CAST(sum(CASE WHEN nz > 64 THEN 256 ELSE nz * 4 END) AS BIGINT) AS mixed_bytes, (SELECT count(*) * 16 FROM e) AS edge_bytes FROM nz)" for n in _BYTES
    ),
)
_ERROR_P, _ERROR_GRAPHS = (8, 10, 12), ("docline", "event_prox300", "event_prox60")


def w13(s, d):
    """Error of the total number of triangles by graph and register count."""
    out = None
    for p in _ERROR_P:
        spec = SketchSpec(p=p, hash="portable")
        got = _each(s, d, _ERROR_GRAPHS, lambda n: _global_error(s, d, n, spec)).withColumn("p", F.lit(p))  # noqa: B023
        out = got if out is None else out.unionByName(got)
    return _round(out)


add(
    "w13_global_error", w13,
    " UNION ALL ".join(
        f"SELECT '{n}' AS graph, * FROM ({S.head(n, *S.edge_t(SketchSpec(p=p, hash='portable')), S.TRI, spec=SketchSpec(p=p, hash='portable'))}SELECT t_est, t, round(abs(t_est - t) / t, 6) AS error, {p} AS p "
        "FROM (SELECT round(CAST(sum(CAST(t_est AS DECIMAL(28,6))) AS DOUBLE) / 3, 4) AS t_est FROM per_edge), (SELECT count(*) AS t FROM tri))" for p in _ERROR_P for n in _ERROR_GRAPHS
    ),
)
EDGE_BYTES, WEDGE_BYTES, HASH_BYTES = 16, 24, 8  # two ids; three ids; a hash


def w14(s, d, name: str = "docline") -> DataFrame:
    """Total triangles by samplers that may hold as many bytes as the sketch table does: method, bytes held at most, items,
    estimate, error.  A sampler that would hold the whole graph in fewer bytes does so and is exact."""
    e, spec = balls.shared_table(graph(s, d, name), "edges"), PORTABLE8
    table = vst.accumulate(e, spec)
    sizes = measures.vst_bytes(table, e).first()
    budget, m, n = int(sizes["mixed_bytes"]), int(sizes["edge_bytes"]) // EDGE_BYTES, int(sizes["vertices"])
    size, hashes, wedges = max(3, min(m, budget // EDGE_BYTES)), max(1, budget // (HASH_BYTES * n)), max(1, budget // WEDGE_BYTES)
    share = size / m
    truth = exact.global_triangles(e).first()[0]
    runs = {
        "sketch table": (budget, n, triangles.total(triangles.edge_triangles(e, table, "ie"))), "sketch table, likelihood": (budget, n, triangles.total(triangles.edge_triangles(e, table, "ml"))),
        "minwise": (hashes * HASH_BYTES * n, hashes, baselines.minwise_triangles(e, hashes).agg((F.sum("t_est") / 3).alias("t_est"))),
        "edges, final": (size * EDGE_BYTES, size, baselines.sampled_triangles(e, share)), "edges, arrival": (size * EDGE_BYTES, size, baselines.sampled_triangles(e, share, mode="arrival")),
        "reservoir": (size * EDGE_BYTES, size, baselines.reservoir_base(e, size)), "reservoir, improved": (size * EDGE_BYTES, size, baselines.reservoir_triangles(e, size, 1).select("t_est")),
        "weighted": (size * EDGE_BYTES, size, baselines.weighted_sample_triangles(e, share / 2, share, 1).select("t_est")), "wedges": (wedges * WEDGE_BYTES, wedges, baselines.wedge_triangles(e, wedges)),
    }
    out = None
    for method, (held, items, got) in runs.items():
        row = got.select(F.lit(method).alias("method"), F.lit(held).cast("long").alias("bytes"), F.lit(items).cast("long").alias("items"), F.col("t_est").cast("double").alias("t_est"))
        out = row if out is None else out.unionByName(row)
    return _round(out.withColumn("error", F.abs(F.col("t_est") - truth) / truth))


add("w14_sampling_equal_bytes", w14)
