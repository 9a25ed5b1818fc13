"""SQL text with which another engine recomputes a query: graph, registers, merges and estimates."""

from __future__ import annotations

from dataclasses import replace

from ..functions.estimate import GEO, alpha
from ..functions.constants import BETA
from ..functions.spec import PORTABLE8, SketchSpec
from ..sources.graphs import sql as graph_sql


def word(element: str, seed: int = 0) -> str:
    return f"('0x' || substr(md5(concat('s{seed}:', {element})), 1, 15))::BIGINT"


def uniform(element: str, seed: int) -> str:
    return f"(('0x' || substr(md5(concat('s{seed}:', {element})), 1, 13))::BIGINT)::DOUBLE / {float(1 << 52)!r}"


def rank(w: str, spec: SketchSpec) -> str:
    return f"CAST({spec.q + 2} - length(bin(2 * ({w} & {(1 << spec.q) - 1}) + 1)) AS INTEGER)"


def regs(rows: str, key: str = "x", element: str = "y", spec: SketchSpec = PORTABLE8) -> str:
    """key, j, rho from a relation."""
    return f"SELECT {key}, CAST(w >> {spec.q} AS INTEGER) AS j, max({rank('w', spec)}) AS rho FROM (SELECT {key}, {word(element, spec.seed)} AS w FROM {rows}) GROUP BY 1, 2"


def est(total: str, filled: str, spec: SketchSpec = PORTABLE8, how: str = "beta") -> str:
    r = float(spec.r)
    z = f"({r!r} - {filled})"
    raw = f"({alpha(spec.r) * r * r!r} / ({total} + {z}))"
    if how == "raw":
        return raw
    if how in ("linear", "large"):
        return f"CASE WHEN {raw} <= {2.5 * r!r} AND {z} > 0 THEN {r!r} * ln({r!r} / greatest({z}, 1e-9)) ELSE {raw} END"
    weights, log, bias = BETA[spec.p], f"ln({z} + 1)", "0.0"
    for w in reversed(weights[1:]):
        bias = f"(({bias} + {w!r}::DOUBLE) * {log})"
    return f"({alpha(spec.r) * r!r} * ({r!r} - {z}) / ({bias} + {weights[0]!r}::DOUBLE * {z} + {total} + {z}))"


def measured(rel: str, keys: str = "x", how: str = "beta", name: str = "n_est", spec: SketchSpec = PORTABLE8) -> str:
    if how == "geo":
        return f"SELECT {keys}, round({GEO * spec.r!r} * pow(2.0, sum(rho)::DOUBLE / {float(spec.r)!r}), 6) AS {name} FROM {rel} GROUP BY {keys}"
    inner = f"SELECT {keys}, sum(pow(2.0, -rho)) AS tt, count(*)::DOUBLE AS ff FROM {rel} GROUP BY {keys}"
    return f"SELECT {keys}, round({est('tt', 'ff', spec, how)}, 6) AS {name} FROM ({inner})"


def head(name: str, *more: str, spec: SketchSpec = PORTABLE8) -> str:
    """WITH e (edges), arcs, reg (hop-1 registers of open sketches)."""
    parts = [f"e AS MATERIALIZED ({graph_sql(name)})", "arcs AS MATERIALIZED (SELECT u AS x, v AS y FROM e UNION ALL SELECT v, u FROM e)", f"reg AS MATERIALIZED ({regs('arcs', spec=spec)})", *more]
    return "WITH RECURSIVE " + ", ".join(parts) + " "


def layers(k: int, closed: bool = True) -> list[str]:
    """l1..lk: registers of ball sketches."""
    first = f"SELECT x, j, max(rho) AS rho FROM (SELECT * FROM reg UNION ALL ({regs('(SELECT DISTINCT x FROM arcs)', element='x')})) GROUP BY 1, 2" if closed else "SELECT * FROM reg"
    out = [f"l1 AS MATERIALIZED ({first})"]
    for t in range(2, k + 1):
        out.append(f"l{t} AS MATERIALIZED (SELECT x, j, max(rho) AS rho FROM (SELECT * FROM l{t - 1} UNION ALL SELECT y, j, rho FROM arcs JOIN l{t - 1} USING (x)) GROUP BY 1, 2)")
    return out


def seeded_layers(k: int, seeds: int, spec: SketchSpec = PORTABLE8) -> list[str]:
    """seeds_t: seed, x, t, n_est of closed balls for seeds 0..seeds - 1."""
    out = []
    for seed in range(seeds):
        own = replace(spec, seed=seed)
        first = f"SELECT x, j, max(rho) AS rho FROM (({regs('arcs', spec=own)}) UNION ALL ({regs('(SELECT DISTINCT x FROM arcs)', element='x', spec=own)})) GROUP BY 1, 2"
        out.append(f"s{seed}_1 AS MATERIALIZED ({first})")
        for t in range(2, k + 1):
            out.append(f"s{seed}_{t} AS MATERIALIZED (SELECT x, j, max(rho) AS rho FROM (SELECT * FROM s{seed}_{t - 1} UNION ALL SELECT y, j, rho FROM arcs JOIN s{seed}_{t - 1} USING (x)) GROUP BY 1, 2)")
    every = " UNION ALL ".join(f"SELECT {seed} AS seed, x, {t} AS t, n_est FROM ({measured(f's{seed}_{t}', spec=spec)})" for seed in range(seeds) for t in range(1, k + 1))
    return [*out, f"seeds_t AS MATERIALIZED ({every})"]


def locals_(k: int, how: str = "beta") -> str:
    return " UNION ALL ".join(f"SELECT x, {t} AS t, n_est FROM ({measured(f'l{t}', how=how)})" for t in range(1, k + 1))


SIDES = "sides AS MATERIALIZED (SELECT u, v, j, max(a) AS a, max(b) AS b FROM (SELECT u, v, j, rho AS a, 0 AS b FROM pairs JOIN reg ON reg.x = u UNION ALL SELECT u, v, j, 0, rho FROM pairs JOIN reg ON reg.x = v) GROUP BY 1, 2, 3)"


def sizes(how: str = "beta", spec: SketchSpec = PORTABLE8) -> str:
    s = lambda c, n: f"sum(CASE WHEN {c} > 0 THEN pow(2.0, -{c}) ELSE 0.0 END) AS {n}_t, sum(CASE WHEN {c} > 0 THEN 1.0 ELSE 0.0 END)::DOUBLE AS {n}_f"
    inner = f"SELECT u, v, {s('a', 'a')}, {s('b', 'b')}, {s('greatest(a, b)', 'o')} FROM sides GROUP BY 1, 2"
    return f"sized AS MATERIALIZED (SELECT u, v, {est('a_t', 'a_f', spec, how)} AS n_a, {est('b_t', 'b_f', spec, how)} AS n_b, {est('o_t', 'o_f', spec, how)} AS n_union FROM ({inner}))"


def edge_t(spec: SketchSpec = PORTABLE8) -> list[str]:
    """per_edge by inclusion and exclusion."""
    return ["pairs AS (SELECT * FROM e)", SIDES, sizes(spec=spec), *_PER_EDGE]


_PER_EDGE = [
    "per AS MATERIALIZED (SELECT u, v, round(greatest(0.0, least(greatest(0.0, least(n_a + n_b - n_union, n_a, n_b)), n_a - 1, n_b - 1)), 6) AS t_est, n_union FROM sized)",
    "per_edge AS MATERIALIZED (SELECT u, v, t_est, round(CASE WHEN n_union > 0 THEN t_est / n_union ELSE 0.0 END, 6) AS density FROM per)",
]
EDGE_T = edge_t()
TRI = "tri AS MATERIALIZED (SELECT e.u AS a, e.v AS b, f.v AS c FROM e JOIN e f ON e.v = f.u JOIN e g ON g.u = e.u AND g.v = f.v)"
EXACT_EDGE = "exact AS MATERIALIZED (SELECT e.u, e.v, count(s.u) AS t FROM e LEFT JOIN (SELECT a AS u, b AS v FROM tri UNION ALL SELECT a, c FROM tri UNION ALL SELECT b, c FROM tri) s ON s.u = e.u AND s.v = e.v GROUP BY 1, 2)"
EXACT_VERTEX = "exact_v AS MATERIALIZED (SELECT x, CAST(sum(t) / 2 AS BIGINT) AS t FROM (SELECT u AS x, t FROM exact UNION ALL SELECT v, t FROM exact) GROUP BY 1)"
DEGREE = "deg AS MATERIALIZED (SELECT x, count(*) AS d FROM arcs GROUP BY 1)"


def exact_balls(k: int) -> list[str]:
    out = ["b0 AS (SELECT DISTINCT x, x AS z FROM arcs)"]
    for t in range(1, k + 1):
        out.append(f"b{t} AS MATERIALIZED (SELECT x, z FROM b{t - 1} UNION SELECT b.x, a.y FROM b{t - 1} b JOIN arcs a ON a.x = b.z)")
    return out


#: Joint likelihood of pairs, as another engine's Newton iteration.  Needs ``sides`` and ``sized``.
_CELLS = " UNION ALL ".join(f"SELECT u, v, '{k}' AS kind, {c} AS k FROM sides WHERE {w}" for k, c, w in (("a_lt", "a", "a < b"), ("b_gt", "b", "a < b"), ("a_gt", "a", "a > b"), ("b_lt", "b", "a > b"), ("eq", "a", "a = b")))
_GROWN = "CASE WHEN {v} < 1e-5 THEN {v} + {v} * {v} / 2 + {v} * {v} * {v} / 6 ELSE exp(least({v}, 700.0::DOUBLE)) - 1 END"
_GONE = "CASE WHEN {v} < 1e-5 THEN {v} - {v} * {v} / 2 + {v} * {v} * {v} / 6 ELSE 1 - exp(-{v}) END"


def _sums(source: str, spec: SketchSpec) -> str:
    """Gradient g* and Hessian h* (by log sizes) of each pair of ``source`` (u, v, ta, tb, tx, i)."""
    top = spec.q
    sized_ = f"SELECT c.*, n.ta, n.tb, n.tx, n.i, exp(n.ta) AS la, exp(n.tb) AS lb, exp(n.tx) AS lx, 1 / ({float(spec.r)!r}::DOUBLE * pow(2.0::DOUBLE, least(k, {top}))) AS s FROM {source} n JOIN cells c ON c.u = n.u AND c.v = n.v"
    values = f"SELECT *, greatest(1e-300::DOUBLE, s * (CASE kind WHEN 'a_lt' THEN la + lx WHEN 'a_gt' THEN la WHEN 'b_lt' THEN lb + lx WHEN 'b_gt' THEN lb ELSE 1 END)) AS w, la * s AS a, lb * s AS b, lx * s AS x FROM ({sized_})"
    parts = f"SELECT *, {_GROWN.format(v='w')} AS up, {_GONE.format(v='w')} AS down, {_GONE.format(v='a')} AS ga_, {_GONE.format(v='b')} AS gb_, {_GONE.format(v='x')} AS gx_ FROM ({values})"
    bits = "SELECT *, greatest(1e-300::DOUBLE, gx_ + (1 - gx_) * ga_ * gb_) AS bracket, exp(-a - x) * gb_ AS oa, exp(-b - x) * ga_ AS ob, exp(-a - b - x) AS al FROM (" + parts + ")"
    slopes = (
        f"SELECT *, CASE WHEN k = 0 THEN 0.0 ELSE s / up END - CASE WHEN k <= {top} THEN s ELSE 0.0 END AS d1, CASE WHEN k = 0 THEN 0.0 ELSE -s * s / (up * down) END AS d2, "
        f"oa / bracket AS ra, ob / bracket AS rb, (oa + ob + al) / bracket AS rx, al / bracket AS rr, CASE WHEN k > 0 THEN 1.0 ELSE 0.0 END AS live, CASE WHEN k <= {top} THEN s ELSE 0.0 END AS flat FROM ({bits})"
    )

    def first(of: str, kinds: str) -> str:
        return f"sum(cnt * CASE WHEN kind = 'eq' THEN live * s * r{of} - flat WHEN kind IN ({kinds}) THEN d1 ELSE 0.0 END)"

    def second(of: str, eq: str, kinds: str) -> str:
        return f"sum(cnt * CASE WHEN kind = 'eq' THEN live * s * s * ({eq}) WHEN kind IN ({kinds or chr(39) * 2}) THEN d2 ELSE 0.0 END) AS w{of}"

    a, b, x = "'a_lt', 'a_gt'", "'b_lt', 'b_gt'", "'a_lt', 'b_lt'"
    grouped = (
        "SELECT u, v, i, any_value(ta) AS ta, any_value(tb) AS tb, any_value(tx) AS tx, any_value(la) AS la, any_value(lb) AS lb, any_value(lx) AS lx, "
        f"{first('a', a)} AS da, {first('b', b)} AS db, {first('x', x)} AS dx, {second('aa', '-ra - ra * ra', a)}, {second('bb', '-rb - rb * rb', b)}, {second('xx', '-rx - rx * rx', x)}, "
        f"{second('ab', 'rr - ra * rb', '')}, {second('ax', '-ra - ra * rx', chr(39) + 'a_lt' + chr(39))}, {second('bx', '-rb - rb * rx', chr(39) + 'b_lt' + chr(39))} FROM ({slopes}) GROUP BY u, v, i"
    )
    return (
        "SELECT u, v, i, ta, tb, tx, la * da AS ga, lb * db AS gb, lx * dx AS gx, -(waa * la * la + la * da) AS aa, -(wbb * lb * lb + lb * db) AS bb, -(wxx * lx * lx + lx * dx) AS xx, "
        f"-wab * la * lb AS ab, -wax * la * lx AS ax, -wbx * lb * lx AS bx FROM ({grouped})"
    )


def _determinant(shift: str) -> str:
    p, q, r = (f"({d} + {shift})" for d in ("aa", "bb", "xx"))
    return f"({p} * ({q} * {r} - bx * bx) - ab * (ab * {r} - bx * ax) + ax * (ab * bx - {q} * ax))"


def joint_ml(spec: SketchSpec = PORTABLE8, rounds: int = 60) -> list[str]:
    """ml: u, v, a_only, b_only, inter, se.  Where the curvature is not that of a top, its diagonal is raised."""
    low, high = -9.0, 25.0
    start = lambda c: f"least({high!r}::DOUBLE, greatest({low!r}::DOUBLE, ln(greatest({c}, 1.0::DOUBLE))))"
    naive = "(n_a + n_b - n_union)"
    begin = f"SELECT u, v, {start(f'n_a - {naive}')} AS ta, {start(f'n_b - {naive}')} AS tb, {start(naive)} AS tx, 0 AS i FROM sized"
    det, fine = _determinant("lift"), "aa > 1e-12 AND aa * bb - ab * ab > 1e-12 * aa * bb AND " + _determinant("0.0") + " > 1e-12 * aa * bb * xx"
    lift = f"CASE WHEN {fine} THEN 0.0 ELSE greatest(0.0, abs(ab) + abs(ax) - aa, abs(ab) + abs(bx) - bb, abs(ax) + abs(bx) - xx) + 1e-6 END"
    p, q, r = "(aa + lift)", "(bb + lift)", "(xx + lift)"
    solved = {
        "ta": f"(ga * ({q} * {r} - bx * bx) - ab * (gb * {r} - bx * gx) + ax * (gb * bx - {q} * gx)) / {det}",
        "tb": f"({p} * (gb * {r} - bx * gx) - ga * (ab * {r} - bx * ax) + ax * (ab * gx - gb * ax)) / {det}",
        "tx": f"({p} * ({q} * gx - gb * bx) - ab * (ab * gx - gb * ax) + ga * (ab * bx - {q} * ax)) / {det}",
    }
    move = lambda c: f"least({high!r}::DOUBLE, greatest({low!r}::DOUBLE, {c} + least(1.0::DOUBLE, greatest(-1.0::DOUBLE, {solved[c]}))))"
    step = f"SELECT u, v, {move('ta')} AS ta, {move('tb')} AS tb, {move('tx')} AS tx, i + 1 AS i FROM (SELECT *, {lift} AS lift FROM ({_sums('newton', spec)})) WHERE i < {rounds}"
    last = f"SELECT u, v, ta, tb, tx, sqrt((aa * bb - ab * ab) / nullif({_determinant('0.0')}, 0.0)) AS spread FROM ({_sums('(SELECT * FROM newton WHERE i = ' + str(rounds) + ')', spec)})"
    size = lambda c: f"CASE WHEN exp({c}) < 1e-3 THEN 0.0 ELSE exp({c}) END"
    return [
        f"cells AS MATERIALIZED (SELECT u, v, kind, k, count(*)::DOUBLE AS cnt FROM ({_CELLS}) GROUP BY 1, 2, 3, 4 UNION ALL SELECT u, v, 'eq', 0, ({spec.r} - count(*))::DOUBLE FROM sides GROUP BY 1, 2 HAVING count(*) < {spec.r})",
        f"newton AS ({begin} UNION ALL {step})",
        f"ml AS MATERIALIZED (SELECT u, v, {size('ta')} AS a_only, {size('tb')} AS b_only, {size('tx')} AS inter, exp(tx) * spread AS se FROM ({last}))",
    ]


def edge_ml(spec: SketchSpec = PORTABLE8) -> list[str]:
    """per_edge by joint likelihood."""
    t = "round(greatest(0.0, least(m.inter, n_a - 1, n_b - 1)), 2)"
    both = "m.inter + m.a_only + m.b_only"
    return [
        "pairs AS (SELECT * FROM e)", SIDES, sizes(), *joint_ml(spec),
        f"per AS MATERIALIZED (SELECT u, v, {t} AS t_est, {both} AS n_union FROM ml m JOIN sized USING (u, v))",
        "per_edge AS MATERIALIZED (SELECT u, v, t_est, round(CASE WHEN n_union > 0 THEN t_est / n_union ELSE 0.0 END, 2) AS density FROM per)",
    ]
