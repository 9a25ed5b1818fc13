"""Queries of graphs, sketches, the sketch table, balls, intersections, triangles and exact answers."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions.estimate import alpha
from ..functions.hashing import hash_word, index_of, rank_of
from ..functions.spec import PORTABLE8, SketchSpec
from ..operators import balls, exact, groups, joint, packed, triangles, twins, vst, windows
from ..sources import build
from ..sources.graphs import GRAPHS, graph
from . import sql as S
from .registry import registry

QUERIES, SQL, add = registry()
ML12 = SketchSpec(p=12)


def _vst(s: SparkSession, d: str, name: str, spec: SketchSpec = PORTABLE8) -> tuple[DataFrame, vst.Vst]:
    edges = graph(s, d, name)
    return edges, vst.accumulate(edges, spec)


def _rounded(frame: DataFrame, *names: str) -> DataFrame:
    return frame.withColumns({n: F.round(n, 6) for n in names})


# builders
for _name in GRAPHS:
    add(f"g_{_name}", lambda s, d, n=_name: graph(s, d, n), f"SELECT u, v FROM ({S.graph_sql(_name)})")
add("g_kron", lambda s, d: graph(s, d, "kron:emb_sim*conv_turn"), f"SELECT u, v FROM ({S.graph_sql('kron:emb_sim*conv_turn')})")
add(
    "g_canonical_dirty",
    lambda s, d: build.canonical(s.read.parquet(f"{d}/lineitem.parquet").select(F.col("l_partkey").alias("u"), F.col("l_suppkey").alias("v"))),
    "SELECT DISTINCT least(l_partkey, l_suppkey) AS u, greatest(l_partkey, l_suppkey) AS v FROM lineitem WHERE l_partkey <> l_suppkey",
)


# sketch operations
def _words(s, d):
    parts = s.read.parquet(f"{d}/part.parquet").select("p_partkey")
    w = hash_word(F.col("p_partkey"), PORTABLE8)
    return parts.select("p_partkey", w.alias("w"), index_of(w, PORTABLE8).alias("j"), rank_of(w, PORTABLE8).alias("rho"))


add("k_hash_index_rank", _words, f"SELECT p_partkey, w, CAST(w >> 52 AS INTEGER) AS j, {S.rank('w', PORTABLE8)} AS rho FROM (SELECT p_partkey, {S.word('p_partkey')} AS w FROM part)")
add("k_registers", lambda s, d: _vst(s, d, "geo_tree")[1].regs, S.head("geo_tree") + "SELECT x, j, rho FROM reg")


def _merge(s, d):
    edges = graph(s, d, "copart")
    halves = [vst.accumulate(edges.filter(F.pmod(F.col("u"), F.lit(2)) == i), PORTABLE8) for i in (0, 1)]
    return halves[0].merged(halves[1]).regs


add("k_merge", _merge, S.head("copart") + "SELECT x, j, rho FROM reg")



def _packed_merge(s, d):
    """Sparse and dense binaries of two halves of the edges, merged and unpacked again."""
    edges = graph(s, d, "copart")
    one, two = (packed.pack(vst.accumulate(edges.filter(F.pmod(F.col("u"), F.lit(3)) == i), PORTABLE8).regs, PORTABLE8, dense_only=i == 1) for i in (0, 1))
    three = packed.pack(vst.accumulate(edges.filter(F.pmod(F.col("u"), F.lit(3)) == 2), PORTABLE8).regs, PORTABLE8)
    return packed.unpack(packed.merge_packed(one.unionByName(two).unionByName(three), PORTABLE8, salts=2), PORTABLE8)


add("k_packed_merge", _packed_merge, S.head("copart") + "SELECT x, j, rho FROM reg")


def _packed_estimate(s, d):
    both = [packed.measure_packed(packed.pack(_vst(s, d, "copart")[1].regs, PORTABLE8, dense_only=dense), PORTABLE8, name=n) for dense, n in ((False, "sparse"), (True, "dense"))]
    return _rounded(both[0].join(both[1], "x"), "sparse", "dense")


add("k_sparse_equals_dense", _packed_estimate, S.head("copart") + "SELECT x, n_est AS sparse, n_est AS dense FROM (" + S.measured("reg") + ")")


def _alphas(s, d):
    """Bias constants, and with each the raw estimate of the customers that ordered: one scan for all register counts."""
    specs = [SketchSpec(p=p, hash="portable") for p in range(4, 19)]
    who = s.read.parquet(f"{d}/orders.parquet").select("o_custkey").filter("o_custkey is not null").distinct()
    word = F.col("w")
    cells = F.array(*(F.struct(F.lit(x.p).alias("p"), F.lit(round(alpha(x.r), 9)).alias("alpha"), index_of(word, x).alias("j"), rank_of(word, x).alias("rho")) for x in specs))
    regs = who.select(hash_word(F.col("o_custkey"), specs[0]).alias("w")).select(F.inline(cells)).groupBy("p", "alpha", "j").agg(F.max("rho").alias("rho"))
    r = F.pow(F.lit(2.0), "p")
    return regs.groupBy("p", "alpha").agg((F.sum(F.pow(F.lit(2.0), -F.col("rho"))) - F.count("*")).alias("t")).select("p", "alpha", F.round(F.col("alpha") * r * r / (F.col("t") + r), 2).alias("raw"))


add(
    "k_alpha_integral", _alphas,
    "WITH g AS (SELECT CAST(p AS INTEGER) AS p, pow(2.0, p) AS r, i, i * 0.002::DOUBLE AS w FROM range(4, 19) a(p), range(0, 200001) b(i)), "
    "a AS (SELECT p, round(1 / sum(pow(log2((2 + w / r) / (1 + w / r)), r) * CASE WHEN i IN (0, 200000) THEN 1 WHEN i % 2 = 1 THEN 4 ELSE 2 END * 0.002::DOUBLE / 3), 9) AS alpha FROM g GROUP BY p), "
    f"c AS (SELECT DISTINCT {S.word('o_custkey')} AS w FROM orders WHERE o_custkey IS NOT NULL), "
    "reg AS (SELECT CAST(p AS INTEGER) AS p, w >> (60 - p) AS j, max(62 - p - length(bin(2 * (w & ((1::BIGINT << (60 - p)) - 1)) + 1))) AS rho FROM (SELECT w, p::INTEGER AS p FROM c, range(4, 19) t(p)) GROUP BY 1, 2) "
    "SELECT p, alpha, round(alpha * pow(2.0, p) * pow(2.0, p) / (sum(pow(2.0, -rho)) - count(*) + pow(2.0, p)), 2) AS raw FROM reg JOIN a USING (p) GROUP BY p, alpha",
)
for _how in ("raw", "linear", "beta", "geo"):
    add(f"k_estimate_{_how}", lambda s, d, h=_how: _rounded(_vst(s, d, "copart")[1].degree(h), "d_est"), S.head("copart") + S.measured("reg", how=_how, name="d_est"))
_W32 = SketchSpec(p=8, hash="portable", bits=32)


def _word32(s, d):
    return _rounded(_vst(s, d, "geo_tree", _W32)[1].degree("large"), "d_est")


def _word32_sql() -> str:
    w = f"({S.word('y')} >> 28)"
    r = f"SELECT x, CAST(w >> 24 AS INTEGER) AS j, max(CAST(26 - length(bin(2 * (w & {(1 << 24) - 1}) + 1)) AS INTEGER)) AS rho FROM (SELECT x, {w} AS w FROM arcs) GROUP BY 1, 2"
    return S.head("geo_tree", f"reg32 AS MATERIALIZED ({r})") + S.measured("reg32", how="linear", name="d_est")


add("k_estimate_word32", _word32, _word32_sql())
add(
    "k_sparse_vs_dense_fill",
    lambda s, d: _vst(s, d, "copart")[1].regs.groupBy("x").agg(F.count("*").alias("nz")).select("x", "nz", (F.col("nz") > PORTABLE8.dense_at * PORTABLE8.r).alias("dense")),
    S.head("copart") + "SELECT x, count(*) AS nz, count(*) > 64 AS dense FROM reg GROUP BY x",
)


def _std_errors(s, d):
    """Standard error by register count: relative, and in customers for a sketch of those that ordered."""
    n = s.read.parquet(f"{d}/orders.parquet").agg(F.countDistinct("o_custkey").alias("n"))
    se = F.lit(1.04) / F.sqrt(F.pow(F.lit(2.0), "p"))
    return s.range(4, 19).select(F.col("id").cast("int").alias("p")).crossJoin(n).select("p", F.round(se, 9).alias("se"), "n", F.round(se * F.col("n"), 6).alias("off"))


add("k_std_error", _std_errors, "SELECT CAST(p AS INTEGER) AS p, round(1.04 / sqrt(pow(2.0, p)), 9) AS se, n, round(1.04 / sqrt(pow(2.0, p)) * n, 6) AS off FROM range(4, 19) t(p), (SELECT count(DISTINCT o_custkey) AS n FROM orders)")


# the sketch table
add("vst_accumulate", lambda s, d: _vst(s, d, "copart")[1].regs, S.head("copart") + "SELECT x, j, rho FROM reg")
add("vst_degree", lambda s, d: _rounded(_vst(s, d, "event_prox300")[1].degree(), "d_est"), S.head("event_prox300") + S.measured("reg", name="d_est"))


def _by_brand(s, d):
    groups = s.read.parquet(f"{d}/part.parquet").select(F.col("p_brand").alias("gid"), F.col("p_partkey").alias("x"))
    return _rounded(_vst(s, d, "copart")[1].union_size(groups), "n_est")


add("vst_union_by_brand", _by_brand, S.head("copart", "m AS (SELECT p_brand AS gid, j, max(rho) AS rho FROM part JOIN reg ON reg.x = p_partkey GROUP BY 1, 2)") + S.measured("m", "gid"))


def _next_parts(s, d, pairs=None):
    pairs = s.range(0, 200).select(F.col("id").alias("u"), (F.col("id") + 1).alias("v")) if pairs is None else pairs
    got = joint.inclusion_exclusion(pairs, _vst(s, d, "copart")[1])
    return _rounded(got, "inter", "a_only", "b_only", "n_union")


def _all_next_parts(s, d):
    return _next_parts(s, d, s.read.parquet(f"{d}/part.parquet").select(F.col("p_partkey").alias("u"), (F.col("p_partkey") + 1).alias("v")))


_CLAMPED = "greatest(0.0, least(n_a + n_b - n_union, n_a, n_b))"
add("vst_intersect_pairs", _next_parts, S.head("copart", "pairs AS (SELECT p AS u, p + 1 AS v FROM range(0, 200) t(p))", S.SIDES, S.sizes()) + f"SELECT u, v, round({_CLAMPED}, 6) AS inter, round(n_a - {_CLAMPED}, 6) AS a_only, round(n_b - {_CLAMPED}, 6) AS b_only, round(n_union, 6) AS n_union FROM sized")
add("vst_intersect_all_parts", _all_next_parts, S.head("copart", "pairs AS (SELECT p_partkey AS u, p_partkey + 1 AS v FROM part)", S.SIDES, S.sizes()) + f"SELECT u, v, round({_CLAMPED}, 6) AS inter, round(n_a - {_CLAMPED}, 6) AS a_only, round(n_b - {_CLAMPED}, 6) AS b_only, round(n_union, 6) AS n_union FROM sized")


def _absorbed(s, d):
    edges = graph(s, d, "copart")
    old = vst.accumulate(edges.filter("u % 3 <> 0"), PORTABLE8)
    return old.absorb(edges.filter("u % 3 = 0")).regs


add("vst_absorb_increment", _absorbed, S.head("copart") + "SELECT x, j, rho FROM reg")


# balls
def _balls(name, k, **how):
    def run(s, d):
        edges, table = _vst(s, d, name)
        return _rounded(balls.ball_sizes(edges, table, k, **how).local, "n_est")

    return run


add("balls_local_k3", _balls("geo_tree", 3), S.head("geo_tree", *S.layers(3)) + S.locals_(3))


def _docline_members(s, d):
    return groups.memberships(build.document_lines(s.read.parquet(f"{d}/documents.parquet")), "line", "doc_id")


def _line_balls(k, **how):
    """Balls of docline from its lines: the edges grow with the square of a line's documents."""
    return lambda s, d: _rounded(groups.ball_sizes(_docline_members(s, d), PORTABLE8, k, **how).local, "n_est")


add("balls_beta_k2", _line_balls(2, how="beta"), S.head("docline", *S.layers(2)) + S.locals_(2, "beta"))


def _seen(s, d, seconds: int = 60):
    return windows.sightings(s.read.parquet(f"{d}/events.parquet"), "ts", "user_id", seconds)


def _window_balls(k, **how):
    """Balls of event_prox60 from its events: the edges grow with the square of a minute's events."""
    return lambda s, d: _rounded(windows.ball_sizes(_seen(s, d), 60, PORTABLE8, k, **how).local, "n_est")


def _total(s, d):
    return windows.ball_sizes(_seen(s, d), 60, PORTABLE8, 3).total.select("t", F.round("n_est", 4).alias("n_est"))


add("balls_total_k3", _total, S.head("event_prox60", *S.layers(3)) + f"SELECT t, round(sum(n_est), 4) AS n_est FROM ({S.locals_(3)}) GROUP BY t")
add("balls_as_printed_k2", _window_balls(2, ball="as_printed"), S.head("event_prox60", *S.layers(2, closed=False)) + S.locals_(2))
add("balls_delta_k3", _line_balls(3, active="changed"), S.head("docline", *S.layers(3)) + S.locals_(3))
_GREW = " AND ".join
add(
    "balls_until_stable", _window_balls(6, until_stable=True),
    S.head("event_prox60", *S.layers(6), *(f"grew{t} AS (SELECT count(*) > 0 AS yes FROM (SELECT * FROM l{t} EXCEPT SELECT * FROM l{t - 1}))" for t in range(2, 7)))
    + " UNION ALL ".join(f"SELECT x, t, n_est FROM (SELECT x, {t} AS t, n_est FROM ({S.measured(f'l{t}')}))" + (" WHERE " + _GREW(f"(SELECT yes FROM grew{i})" for i in range(2, t + 1)) if t > 1 else "") for t in range(1, 7)),
)
add("balls_packed_k3", _line_balls(3), S.head("docline", *S.layers(3)) + S.locals_(3))
add("balls_auto_k3", _window_balls(3), S.head("event_prox60", *S.layers(3)) + S.locals_(3))


def _two_hop(s, d):
    return _rounded(groups.two_hop(_docline_members(s, d), PORTABLE8), "n2")


add("balls_two_hop", _two_hop, S.head("docline", "h AS (SELECT y AS x, j, max(rho) AS rho FROM arcs JOIN reg USING (x) GROUP BY 1, 2)") + S.measured("h", name="n2"))


def _colours(s, d):
    return s.read.parquet(f"{d}/customer.parquet").select((F.col("c_custkey") * 4).alias("x"), F.col("c_mktsegment").alias("colour"))


def _coloured(**which):
    return lambda s, d: _rounded(balls.coloured_ball_sizes(graph(s, d, "geo_tree"), _colours(s, d), 2, PORTABLE8, **which), "n_est")


def _coloured_sql(where: str) -> str:
    first = S.regs(f"(SELECT DISTINCT x FROM arcs WHERE {where})", element="x")
    step = lambda a: f"SELECT x, j, max(rho) AS rho FROM (SELECT * FROM {a} UNION ALL SELECT y, j, rho FROM arcs JOIN {a} USING (x)) GROUP BY 1, 2"
    return S.head("geo_tree", f"l0 AS ({first})", f"l1 AS MATERIALIZED ({step('l0')})", f"l2 AS MATERIALIZED ({step('l1')})") + S.locals_(2)


_BUILD = "x IN (SELECT c_custkey * 4 FROM customer WHERE c_mktsegment = 'BUILDING')"
add("balls_coloured_segment", _coloured(all_of=["BUILDING"]), _coloured_sql(_BUILD))
add("balls_coloured_not", _coloured(none_of=["BUILDING"]), _coloured_sql(f"NOT ({_BUILD})"))


def _near(est: DataFrame, truth: DataFrame, keys: list[str], value: str, true: str, share: float, plus: float = 0.0) -> DataFrame:
    """keys.., the exact answer, and whether the estimate is as near to it as it should be: for sketches and samplers
    whose numbers no other engine repeats."""
    rows = truth.join(est, keys, "left")
    return rows.select(*keys, F.col(true), (F.abs(F.coalesce(F.col(value), F.lit(0.0)) - F.col(true)) <= share * F.col(true) + plus).alias("near"))


def _twins(s, d, seconds: int = 60):
    return twins.twins(s.read.parquet(f"{d}/events.parquet"), "ts", "user_id", seconds)


def _builtin_balls(s, d):
    held = _twins(s, d)
    return _near(twins.builtin_sizes(*held, 2), twins.exact_sizes(*held, 2), ["x", "t"], "n_est", "n", 0.1, 1.0)


add("balls_builtin_hll", _builtin_balls, S.head("event_prox60", *S.exact_balls(2)) + " UNION ALL ".join(f"SELECT x, {t} AS t, count(*) AS n, TRUE AS near FROM b{t} GROUP BY x" for t in (1, 2)))


def _diameter(s, d):
    edges, table = _vst(s, d, "order_part")
    out = balls.effective_diameter(balls.ball_sizes(edges, table, 3).total)
    return _rounded(out, "d_eff", "mean_far_distance")


add(
    "effective_diameter", _diameter,
    S.head("order_part", *S.layers(3), f"tot AS (SELECT t, sum(n_est) AS n FROM ({S.locals_(3)}) GROUP BY t)", "w AS (SELECT t, n, lag(n, 1, 0.0) OVER (ORDER BY t) AS b, max(n) OVER () AS m FROM tot)")
    + "SELECT round(min(CASE WHEN n >= 0.9 * m AND b < 0.9 * m THEN t - 1 + CASE WHEN n > b THEN (0.9 * m - b) / (n - b) ELSE 0.0 END END), 6) AS d_eff, round(sum(CASE WHEN t > 1 THEN greatest(n - b, 0.0) * t ELSE 0.0 END) / sum(CASE WHEN t > 1 THEN greatest(n - b, 0.0) ELSE 0.0 END), 6) AS mean_far_distance FROM w",
)


# intersections
def _pairs(name, run):
    def query(s, d):
        edges, table = _vst(s, d, name)
        return run(edges, table)

    return query


_IE = [S.SIDES, S.sizes()]
add("i_inclusion_exclusion", _pairs("docline", lambda e, t: _rounded(joint.inclusion_exclusion(e, t).select("u", "v", "inter", "n_union"), "inter", "n_union")), S.head("docline", "pairs AS (SELECT * FROM e)", *_IE) + f"SELECT u, v, round({_CLAMPED}, 6) AS inter, round(n_union, 6) AS n_union FROM sized")
add("i_inclusion_exclusion_raw", _pairs("event_prox300", lambda e, t: _rounded(joint.inclusion_exclusion(e, t, clamp=False).select("u", "v", "inter"), "inter")), S.head("event_prox300", "pairs AS (SELECT * FROM e)", *_IE) + "SELECT u, v, round(n_a + n_b - n_union, 6) AS inter FROM sized")
_KIND = "SELECT u, v, {k} AS kind, {c} AS k FROM sides WHERE {w}"
_COUNTS = " UNION ALL ".join(_KIND.format(k=f"'{k}'", c=c, w=w) for k, c, w in (("a_lt", "a", "a < b"), ("b_gt", "b", "a < b"), ("a_gt", "a", "a > b"), ("b_lt", "b", "a > b"), ("eq", "a", "a = b")))
add("i_joint_counts", _pairs("event_prox60", lambda e, t: joint.joint_counts(e, t)), S.head("event_prox60", "pairs AS (SELECT * FROM e)", S.SIDES) + f"SELECT u, v, kind, k, count(*) AS cnt FROM ({_COUNTS}) GROUP BY 1, 2, 3, 4 UNION ALL SELECT u, v, 'eq', 0, 256 - count(*) FROM sides GROUP BY 1, 2 HAVING count(*) < 256")


def _joint_ml(s, d):
    """Sizes where the joint likelihood is highest, and the standard error where the intersection is not next to none."""
    got = joint.intersect_packed(*_vst(s, d, "event_prox60"), "ml")
    return got.select("u", "v", *(F.round(c, 2).alias(c) for c in ("inter", "a_only", "b_only")), F.round(F.when(F.col("inter") >= 1, F.col("se")), 2).alias("se"))


add("i_joint_ml", _joint_ml, S.head("event_prox60", "pairs AS (SELECT * FROM e)", *_IE, *S.joint_ml()) + "SELECT u, v, round(inter, 2) AS inter, round(a_only, 2) AS a_only, round(b_only, 2) AS b_only, round(CASE WHEN inter >= 1 THEN se END, 2) AS se FROM ml")
_EXACT_PAIRS = "met AS (SELECT e.u, e.v, count(b.y) AS n FROM e LEFT JOIN arcs a ON a.x = e.u LEFT JOIN arcs b ON b.x = e.v AND b.y = a.y GROUP BY 1, 2)"


def _near_theta(edges: DataFrame) -> DataFrame:
    truth = exact.intersections(edges, edges).select("u", "v", F.col("inter").cast("long").alias("t"))
    return _near(joint.intersect_theta(edges, edges), truth, ["u", "v"], "inter", "t", 0.1, 1.0)


add("i_theta", lambda s, d: _near_theta(graph(s, d, "event_prox300")), S.head("event_prox300", _EXACT_PAIRS) + "SELECT u, v, n AS t, TRUE AS near FROM met")
add("i_exact", lambda s, d: exact.intersections(graph(s, d, "docline"), graph(s, d, "docline")), S.head("docline", S.DEGREE, _EXACT_PAIRS) + "SELECT m.u, m.v, CAST(n AS DOUBLE) AS inter, CAST(p.d + q.d - n AS DOUBLE) AS n_union FROM met m JOIN deg p ON p.x = m.u JOIN deg q ON q.x = m.v")


# triangles
def _tri(name, then, spec=PORTABLE8, how="ie"):
    def run(s, d):
        edges, table = _vst(s, d, name, spec)
        return then(triangles.edge_triangles(edges, table, how), edges)

    return run


_E = lambda name, *more: S.head(name, *S.EDGE_T, *more)
_V = "per_v AS MATERIALIZED (SELECT x, round(CAST(sum(CAST(t_est AS DECIMAL(28,6))) AS DOUBLE) / 2, 7) AS t_est FROM (SELECT u AS x, t_est FROM per_edge UNION ALL SELECT v, t_est FROM per_edge) GROUP BY 1)"
add("tri_edges_ie", _tri("docline", lambda p, e: p), _E("docline") + "SELECT * FROM per_edge")
add("tri_edge_top100_ie", _tri("copart", lambda p, e: triangles.top_edges(p, 100)), _E("copart") + "SELECT * FROM per_edge ORDER BY t_est DESC, u, v LIMIT 100")
add("tri_edge_top100_ties", _tri("docline", lambda p, e: triangles.top_edges(p, 100, "keep")), _E("docline") + "SELECT * FROM per_edge WHERE t_est >= (SELECT min(t_est) FROM (SELECT t_est FROM per_edge ORDER BY t_est DESC, u, v LIMIT 100))")
add("tri_vertex_top100_ie", _tri("docline", lambda p, e: triangles.top_vertices(triangles.vertex_triangles(p), 100)), _E("docline", _V) + "SELECT * FROM per_v ORDER BY t_est DESC, x LIMIT 100")
add("tri_vertex_all_ie", _tri("event_prox300", lambda p, e: triangles.vertex_triangles(p)), _E("event_prox300", _V) + "SELECT * FROM per_v")
add("tri_global_ie", _tri("copart", lambda p, e: triangles.total(p)), _E("copart") + "SELECT round(coalesce(CAST(sum(CAST(t_est AS DECIMAL(28,6))) AS DOUBLE), 0.0) / 3, 4) AS t_est FROM per_edge")
add("tri_density", _tri("event_prox60", lambda p, e: p.select("u", "v", "density")), _E("event_prox60") + "SELECT u, v, density FROM per_edge")
add("tri_support_filter", _tri("docline", lambda p, e: triangles.support_filter(p, 20)), _E("docline") + "SELECT u, v FROM per_edge WHERE t_est >= 20")
add("clustering_local", _tri("docline", lambda p, e: triangles.clustering(triangles.vertex_triangles(p), e)), _E("docline", S.DEGREE, _V) + "SELECT x, round(coalesce(CASE WHEN d > 1 THEN 2 * t_est / (d::DOUBLE * (d - 1)) ELSE 0.0 END, 0.0), 6) AS cc FROM deg LEFT JOIN per_v USING (x)")
add("transitivity", _tri("event_prox300", lambda p, e: triangles.transitivity(p, e)), _E("event_prox300", S.DEGREE) + "SELECT round(3 * round(CAST(sum(CAST(t_est AS DECIMAL(28,6))) AS DOUBLE) / 3, 4) / (SELECT sum(d * (d - 1) / 2) FROM deg), 6) AS transitivity FROM per_edge")
add("topk_edges_per_vertex", _tri("event_prox60", lambda p, e: triangles.top_edges_by_vertex(p, 3)), _E("event_prox60") + "SELECT * FROM (SELECT x, u, v, t_est, CAST(row_number() OVER (PARTITION BY x ORDER BY t_est DESC, u, v) AS INTEGER) AS nth FROM (SELECT u AS x, u, v, t_est FROM per_edge UNION ALL SELECT v, u, v, t_est FROM per_edge)) WHERE nth <= 3")
add("tri_edge_top100_pruned", lambda s, d: triangles.top_edges_pruned(*_vst(s, d, "docline"), 100, "ie"), _E("docline") + "SELECT * FROM per_edge ORDER BY t_est DESC, u, v LIMIT 100")
_M = lambda name, *more: S.head(name, *S.edge_ml(), *more)
add("tri_edge_top100_ml", _tri("docline", lambda p, e: triangles.top_edges(p, 100), how="ml"), _M("docline") + "SELECT * FROM per_edge ORDER BY t_est DESC, u, v LIMIT 100")
add("tri_vertex_top100_ml", _tri("event_prox60", lambda p, e: triangles.top_vertices(triangles.vertex_triangles(p), 100), how="ml"), _M("event_prox60", _V) + "SELECT * FROM per_v ORDER BY t_est DESC, x LIMIT 100")
add("tri_global_ml", _tri("event_prox60", lambda p, e: triangles.total(p), how="ml"), _M("event_prox60") + "SELECT round(coalesce(CAST(sum(CAST(t_est AS DECIMAL(28,6))) AS DOUBLE), 0.0) / 3, 4) AS t_est FROM per_edge")


def _heavy_hitters(s, d):
    """The three answers of one pass, as rows: kind, first and second vertex (or none), estimate."""
    edges, table = _vst(s, d, "event_prox60")
    e, v, t = triangles.heavy_hitters(edges, table, 20, "ml")
    none = F.lit(None).cast("long")
    rows = e.select(F.lit("edge").alias("kind"), "u", "v", "t_est").unionByName(v.select(F.lit("vertex").alias("kind"), F.col("x").alias("u"), none.alias("v"), "t_est"))
    return rows.unionByName(t.select(F.lit("total").alias("kind"), none.alias("u"), none.alias("v"), "t_est"))


add(
    "tri_heavy_hitters_ml", _heavy_hitters,
    _M("event_prox60", _V) + "SELECT * FROM (SELECT 'edge' AS kind, u, v, t_est FROM per_edge ORDER BY t_est DESC, u, v LIMIT 20) UNION ALL SELECT * FROM (SELECT 'vertex', x, NULL, t_est FROM per_v ORDER BY t_est DESC, x LIMIT 20) "
    "UNION ALL SELECT 'total', NULL, NULL, round(coalesce(CAST(sum(CAST(t_est AS DECIMAL(28,6))) AS DOUBLE), 0.0) / 3, 4) FROM per_edge",
)
add("tri_edges_rows", _tri("docline", lambda p, e: p, how="ie_rows"), _E("docline") + "SELECT * FROM per_edge")

# exact
add("x_degree", lambda s, d: exact.degrees(graph(s, d, "copart")), S.head("copart", S.DEGREE) + "SELECT * FROM deg")
add("x_balls_k3", lambda s, d: exact.balls(graph(s, d, "event_prox60"), 3), S.head("event_prox60", *S.exact_balls(3)) + " UNION ALL ".join(f"SELECT x, {t} AS t, count(*) AS n FROM b{t} GROUP BY x" for t in (1, 2, 3)))
for _how, _name in (("adjacency", "event_prox300"), ("oriented", "copart"), ("arrays", "docline")):
    add(f"x_edge_triangles_{_how}", lambda s, d, h=_how, n=_name: exact.edge_triangles(graph(s, d, n), h), S.head(_name, S.TRI, S.EXACT_EDGE) + "SELECT * FROM exact")
add("x_vertex_triangles", lambda s, d: exact.vertex_triangles(graph(s, d, "docline")), S.head("docline", S.TRI, S.EXACT_EDGE, S.EXACT_VERTEX) + "SELECT * FROM exact_v")
add("x_global_triangles", lambda s, d: exact.global_triangles(graph(s, d, "copart")), S.head("copart", S.TRI) + "SELECT count(*) AS t FROM tri")
add("x_edge_top100", lambda s, d: triangles.top_edges(exact.edge_triangles(graph(s, d, "docline")), 100, value="t"), S.head("docline", S.TRI, S.EXACT_EDGE) + "SELECT * FROM exact ORDER BY t DESC, u, v LIMIT 100")
add("x_vertex_top100", lambda s, d: exact.vertex_triangles(graph(s, d, "docline")).orderBy(F.desc("t"), "x").limit(100), S.head("docline", S.TRI, S.EXACT_EDGE, S.EXACT_VERTEX) + "SELECT * FROM exact_v ORDER BY t DESC, x LIMIT 100")
