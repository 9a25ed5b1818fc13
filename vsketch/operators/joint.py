"""Intersections of sketched sets: inclusion-exclusion, joint register statistics, joint maximum likelihood."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..functions.estimate import estimate, estimate_array
from ..functions.spec import SketchSpec
from .packed import pack, to_dense
from .vst import Vst

KINDS = ("a_lt", "a_gt", "b_lt", "b_gt", "eq")


def side_by_side(pairs: DataFrame, vst: Vst) -> DataFrame:
    """u, v, j, a, b: both register values where either is not zero (a union and a maximum: one shuffle by pair)."""
    pairs = pairs.select("u", "v")
    one = pairs.join(vst.regs.withColumnRenamed("x", "u"), "u").select("u", "v", "j", F.col("rho").alias("a"), F.lit(0).alias("b"))
    two = pairs.join(vst.regs.withColumnRenamed("x", "v"), "v").select("u", "v", "j", F.lit(0).alias("a"), F.col("rho").alias("b"))
    return one.unionByName(two).groupBy("u", "v", "j").agg(F.max("a").alias("a"), F.max("b").alias("b"))


def _sizes(rows: DataFrame, spec: SketchSpec, how: str) -> DataFrame:
    """u, v, n_a, n_b, n_union: estimates of both sets and their union."""

    def sums(c: Column, name: str) -> list[Column]:
        return [F.sum(F.when(c > 0, F.pow(F.lit(2.0), -c)).otherwise(0.0)).alias(f"{name}_t"), F.sum((c > 0).cast("double")).alias(f"{name}_f")]

    a, b = F.col("a"), F.col("b")
    got = rows.groupBy("u", "v").agg(*sums(a, "a"), *sums(b, "b"), *sums(F.greatest(a, b), "o"))
    return got.select("u", "v", *(estimate(F.col(f"{c}_t"), F.col(f"{c}_f"), spec, how).alias(n) for c, n in (("a", "n_a"), ("b", "n_b"), ("o", "n_union"))))


def inclusion_exclusion(pairs: DataFrame, vst: Vst, how: str = "beta", clamp: bool = True) -> DataFrame:
    """u, v, inter, a_only, b_only, n_union.  clamp: into [0, smaller set]; without, it may be negative."""
    got = _sizes(side_by_side(pairs, vst), vst.spec, how)
    inter = F.col("n_a") + F.col("n_b") - F.col("n_union")
    if clamp:
        inter = F.greatest(F.lit(0.0), F.least(inter, F.col("n_a"), F.col("n_b")))
    return got.select("u", "v", inter.alias("inter"), (F.col("n_a") - inter).alias("a_only"), (F.col("n_b") - inter).alias("b_only"), "n_union")


def joint_counts(pairs: DataFrame, vst: Vst) -> DataFrame:
    """u, v, kind, k, cnt: at how many registers A is smaller or larger (at A's and at B's value), or both are equal."""
    rows = side_by_side(pairs, vst)
    kind = lambda name, k: F.struct(F.lit(name).alias("kind"), F.col(k).alias("k"))
    cells = F.when(F.col("a") < F.col("b"), F.array(kind("a_lt", "a"), kind("b_gt", "b"))).when(F.col("a") > F.col("b"), F.array(kind("a_gt", "a"), kind("b_lt", "b"))).otherwise(F.array(kind("eq", "a")))
    counts = rows.select("u", "v", F.inline(cells)).groupBy("u", "v", "kind", "k").agg(F.count("*").alias("cnt"))
    empty = rows.groupBy("u", "v").agg((F.lit(vst.spec.r) - F.count("*")).alias("cnt")).filter("cnt > 0")
    return counts.unionByName(empty.select("u", "v", F.lit("eq").alias("kind"), F.lit(0).alias("k"), F.col("cnt").cast("long").alias("cnt")))


def count_arrays(a: np.ndarray, b: np.ndarray, top: int) -> np.ndarray:
    """The same from dense registers: pairs x kinds x (top + 1)."""
    n, r = a.shape
    k = int(max(a.max(initial=0), b.max(initial=0))) + 1
    less, equal, rows = np.triu(np.ones((k, k)), 1), np.arange(k), max(1, (1 << 17) // r)  # rows that a core's cache holds
    out = np.zeros((n, 5, top + 1))
    for lo in range(0, n, rows):
        one, two = a[lo : lo + rows], b[lo : lo + rows]
        code = one.astype(np.int64) * k + two + (np.arange(len(one)) * (k * k))[:, None]
        both = np.bincount(code.ravel(), minlength=len(one) * k * k).reshape(len(one), k, k)  # registers with A at i and B at j
        part = out[lo : lo + rows]
        part[:, 0, :k], part[:, 3, :k] = (both * less).sum(2), (both * less).sum(1)
        part[:, 1, :k], part[:, 2, :k] = (both * less.T).sum(2), (both * less.T).sum(1)
        part[:, 4, :k] = both[:, equal, equal]
    return out


def _log_f(lam: np.ndarray, k: np.ndarray, r: int, q: int) -> np.ndarray:
    """Log probability that a Poissonised maximum with mean lam equals k (rows x levels)."""
    v = lam[:, None] / (r * np.exp2(np.minimum(k, q))[None, :])
    some = np.log(-np.expm1(-np.maximum(v, 1e-300)))
    return np.where(k == 0, -v, np.where(k <= q, some - v, some))


def log_likelihood(theta: np.ndarray, counts: np.ndarray, r: int, q: int) -> np.ndarray:
    """theta: logs of the means of A only, B only, both (rows x 3)."""
    k = np.arange(counts.shape[2])
    la, lb, lx = np.exp(np.clip(theta, -30, 40)).T
    out = (counts[:, 0] * _log_f(la + lx, k, r, q)).sum(1) + (counts[:, 1] * _log_f(la, k, r, q)).sum(1)
    out += (counts[:, 2] * _log_f(lb + lx, k, r, q)).sum(1) + (counts[:, 3] * _log_f(lb, k, r, q)).sum(1)
    scale = 1 / (r * np.exp2(np.minimum(k, q)))
    a, b, x = (l[:, None] * scale for l in (la, lb, lx))
    bracket = -np.expm1(-x) + np.exp(-x) * np.expm1(-a) * np.expm1(-b)
    equal = np.log(np.maximum(bracket, 1e-300)) - np.where(k <= q, a + b + x, 0)
    return out + (counts[:, 4] * np.where(k == 0, -(a + b + x), equal)).sum(1)


def _slopes(lam: np.ndarray, k: np.ndarray, r: int, q: int) -> tuple[np.ndarray, np.ndarray]:
    """First and second derivative of _log_f by lam (rows x levels)."""
    s = 1 / (r * np.exp2(np.minimum(k, q)))[None, :]
    v = np.maximum(lam[:, None] * s, 1e-300)
    grown = np.expm1(np.minimum(v, 700.0))
    first = np.where(k == 0, 0.0, s / grown) - np.where(k <= q, s, 0.0)
    return first, np.where(k == 0, 0.0, s * s / (grown * np.expm1(-np.minimum(v, 700.0))))


def derivatives(theta: np.ndarray, counts: np.ndarray, r: int, q: int) -> tuple[np.ndarray, np.ndarray]:
    """Gradient (rows x 3) and Hessian (rows x 3 x 3) of log_likelihood by theta, in closed form."""
    k = np.arange(counts.shape[2])
    size = np.exp(np.clip(theta, -30, 40))
    la, lb, lx = size.T
    g, h = np.zeros((len(theta), 3)), np.zeros((len(theta), 3, 3))
    for kind, (lam, of) in enumerate((((la + lx), (0, 2)), (la, (0,)), ((lb + lx), (1, 2)), (lb, (1,)))):
        first, second = _slopes(lam, k, r, q)
        first, second = (counts[:, kind] * first).sum(1), (counts[:, kind] * second).sum(1)
        for i in of:
            g[:, i] += first
            for j in of:
                h[:, i, j] += second
    s = 1 / (r * np.exp2(np.minimum(k, q)))
    a, b, x = (l[:, None] * s for l in (la, lb, lx))
    bracket = np.maximum(-np.expm1(-x) + np.exp(-x) * np.expm1(-a) * np.expm1(-b), 1e-300)
    only_a, only_b, all_ = -np.exp(-a - x) * np.expm1(-b), -np.exp(-b - x) * np.expm1(-a), np.exp(-a - b - x)
    by = [only_a / bracket, only_b / bracket, (only_a + only_b + all_) / bracket]
    n = counts[:, 4] * (k > 0)
    plain = (counts[:, 4] * np.where(k <= q, s, 0.0)).sum(1)
    twice = {(0, 0): -by[0], (1, 1): -by[1], (2, 2): -by[2], (0, 1): all_ / bracket, (0, 2): -by[0], (1, 2): -by[1]}
    for i in range(3):
        g[:, i] += (n * s * by[i]).sum(1) - plain
        for j in range(i, 3):
            h[:, i, j] += (n * s * s * (twice[i, j] - by[i] * by[j])).sum(1)
            h[:, j, i] = h[:, i, j]
    grad = size * g
    return grad, h * size[:, :, None] * size[:, None, :] + np.eye(3) * grad[:, :, None]


LOW, HIGH = -9.0, 25.0  # logs of the smallest and largest size


def joint_ml(counts: np.ndarray, start: np.ndarray, spec: SketchSpec, rounds: int = 60, tol: float = 1e-7) -> tuple[np.ndarray, np.ndarray]:
    """Sizes (A only, B only, both) that make the statistics likeliest, and their standard errors.

    Damped Newton over log sizes for all rows at once, with a floor on the curvature and halved steps."""
    r, q = spec.r, spec.q
    theta = np.clip(np.log(np.maximum(start, 1.0)), LOW, HIGH)
    counts = counts[:, :, : max(2, int(np.flatnonzero(counts.sum((0, 1))).max(initial=0)) + 1)]
    todo = np.arange(len(theta))
    for _ in range(rounds):
        if not len(todo):
            break
        t, c = theta[todo], counts[todo]
        at = log_likelihood(t, c, r, q)
        grad, hess = derivatives(t, c, r, q)
        value, vector = np.linalg.eigh(-hess)
        value = np.maximum(np.abs(value), 1e-6)
        along = np.clip(np.einsum("nji,nj->ni", vector, grad) / value, -3, 3)  # a long step in a flat direction leaves the others
        move = np.einsum("nij,nj->ni", vector, along)
        best = t.copy()
        step, open_ = np.ones(len(t)), np.ones(len(t), bool)
        for _ in range(12):
            tried = np.clip(t[open_] + step[open_, None] * move[open_], LOW, HIGH)
            f = log_likelihood(tried, c[open_], r, q)
            where = np.flatnonzero(open_)
            # near the top a step of Newton is right even where rounding hides the gain
            ok = (f >= at[open_]) | (np.abs(move[open_]).max(1) < 1e-4)
            best[where[ok]] = tried[ok]
            open_[where[ok]] = False
            if not open_.any():
                break
            step[open_] /= 2
        theta[todo] = best
        todo = todo[np.abs(best - t).max(1) > tol]
    _, hess = derivatives(theta, counts, r, q)
    value, vector = np.linalg.eigh(-hess)
    spread = np.sqrt(np.einsum("nij,nj->ni", vector**2, 1 / np.maximum(value, 1e-6)))
    size = np.exp(theta)
    return size, np.minimum(size * spread, 1e18)


def estimate_pairs(a: np.ndarray, b: np.ndarray, spec: SketchSpec, how: str, sizes: tuple[np.ndarray, np.ndarray] | None = None) -> dict[str, np.ndarray]:
    """inter, a_only, b_only, n_union, se for rows of dense registers; sizes: known estimates of both sets."""
    n_a, n_b = sizes if sizes is not None else (estimate_array(a, "beta"), estimate_array(b, "beta"))
    rows = max(1, (1 << 17) // spec.r)
    n_u = np.concatenate([np.zeros(0), *(estimate_array(np.maximum(a[i : i + rows], b[i : i + rows]), "beta") for i in range(0, len(a), rows))])
    naive = n_a + n_b - n_u
    if how == "ie":
        inter = np.clip(naive, 0, np.minimum(n_a, n_b))
        return {"inter": inter, "a_only": n_a - inter, "b_only": n_b - inter, "n_union": n_u, "se": np.full(len(a), np.nan)}
    start = np.stack([n_a - naive, n_b - naive, naive], 1)
    size, se = joint_ml(count_arrays(a, b, spec.q + 1), start, spec)
    size = np.where(size < 1e-3, 0.0, size)
    return {"inter": size[:, 2], "a_only": size[:, 0], "b_only": size[:, 1], "n_union": size.sum(1), "se": se[:, 2]}


#: Edges of one vertex beyond which its sketch is sent to several tasks.
HUB = 20_000


def oriented(pairs: DataFrame, sizes: DataFrame, hub: int = HUB) -> DataFrame:
    """u, v, s, l, n_s, n_l, salt: the end with the smaller sketch first, and a part of the other end's pairs.

    sizes: x, n, nz (registers that are not zero).  Pairs of a vertex without a sketch are left out."""
    one, two = (sizes.select(F.col("x").alias(c), F.col("n").alias(f"n_{c}"), F.col("nz").alias(f"nz_{c}")) for c in "uv")
    both = pairs.select("u", "v").join(one, "u").join(two, "v")
    first = (F.col("nz_u") < F.col("nz_v")) | ((F.col("nz_u") == F.col("nz_v")) & (F.col("u") < F.col("v")))
    pick = lambda a, b: F.when(first, F.col(a)).otherwise(F.col(b))
    both = both.select("u", "v", pick("u", "v").alias("s"), pick("v", "u").alias("l"), pick("n_u", "n_v").alias("n_s"), pick("n_v", "n_u").alias("n_l"))
    return both.withColumn("salt", F.pmod(F.xxhash64("s"), _copies("n_l", hub)).cast("int"))


def _copies(n: str, hub: int) -> Column:
    return F.greatest(F.lit(1), F.ceil(F.col(n) / hub)).cast("int")


def intersect_packed(pairs: DataFrame, vst: Vst, how: str = "ml", rows: int = 1024, hub: int = HUB) -> DataFrame:
    """u, v, inter, a_only, b_only, n_union, se, n_u, n_v from packed sketches, a batch of pairs at a time.

    Only the smaller sketch of a pair travels, to where the larger one is; a hub's sketch is there in as many
    copies as its estimated pairs need.  Vertices without a sketch count as empty sets (the pair is left out)."""
    spec = vst.spec
    sums = vst.regs.groupBy("x").agg(F.sum(F.pow(F.lit(2.0), -F.col("rho"))).alias("t"), F.count("*").alias("nz"))
    sizes = sums.select("x", estimate(F.col("t"), F.col("nz").cast("double"), spec, "beta").alias("n"), "nz")
    packed = pack(vst.regs, spec).select("x", "mode", "regs")
    edges = oriented(pairs, sizes, hub)
    small = packed.select(F.col("x").alias("s"), F.col("mode").alias("mode_s"), F.col("regs").alias("regs_s"))
    copies = F.explode(F.sequence(F.lit(0), _copies("n", hub) - 1)).alias("salt")
    large = packed.join(sizes.select("x", "n"), "x").select(F.col("x").alias("l"), F.col("mode").alias("mode_l"), F.col("regs").alias("regs_l"), copies)
    both = edges.join(small, "s").join(large, ["l", "salt"]).select("u", "v", "s", "n_s", "n_l", "mode_s", "regs_s", "mode_l", "regs_l")
    names = ("inter", "a_only", "b_only", "n_union", "se", "n_u", "n_v")

    def run(batches):
        for batch in batches:
            for i in range(0, batch.num_rows, rows):
                part = batch.slice(i, rows)
                u, s, n_s, n_l = (np.asarray(part.column(k)) for k in (0, 2, 3, 4))
                a, b = (to_dense(part.column(k), part.column(k + 1), spec) for k in (5, 7))
                got = estimate_pairs(a, b, spec, how, (n_s, n_l))
                same = s == u
                got["a_only"], got["b_only"] = np.where(same, got["a_only"], got["b_only"]), np.where(same, got["b_only"], got["a_only"])
                got["n_u"], got["n_v"] = np.where(same, n_s, n_l), np.where(same, n_l, n_s)
                yield pa.RecordBatch.from_arrays([part.column(0), part.column(1), *(pa.array(got[c]) for c in names)], names=["u", "v", *names])

    return both.mapInArrow(run, "u long, v long, " + ", ".join(f"{c} double" for c in names))


def intersect_theta(edges: DataFrame, pairs: DataFrame, lg: int = 12) -> DataFrame:
    """u, v, inter, n_union from built-in theta sketches, whose intersection is closed."""
    from .vst import accumulate_builtin

    sk = accumulate_builtin(edges, "theta", lg)
    both = pairs.select("u", "v").join(sk.select(F.col("x").alias("u"), F.col("sk").alias("a")), "u").join(sk.select(F.col("x").alias("v"), F.col("sk").alias("b")), "v")
    return both.select("u", "v", F.theta_sketch_estimate(F.theta_intersection("a", "b")).cast("double").alias("inter"), F.theta_sketch_estimate(F.theta_union("a", "b")).cast("double").alias("n_union"))


def intersect(pairs: DataFrame, vst: Vst, how: str = "ml", edges: DataFrame | None = None) -> DataFrame:
    """u, v, inter, n_union, n_u, n_v (estimated sizes of both sets) by ``ie`` (packed), ``ie_rows`` (relational: a row a
    register, for a check or few registers), ``ml``, ``theta`` or ``exact`` (both need edges, and have no sizes)."""
    if how == "ie_rows":
        return inclusion_exclusion(pairs, vst).select("u", "v", "inter", "n_union", (F.col("a_only") + F.col("inter")).alias("n_u"), (F.col("b_only") + F.col("inter")).alias("n_v"))
    if how in ("ml", "ie", "ie_packed"):
        return intersect_packed(pairs, vst, how[:2]).select("u", "v", "inter", "n_union", "n_u", "n_v")
    if how == "theta":
        return intersect_theta(edges, pairs)
    if how == "exact":
        from .exact import intersections

        return intersections(edges, pairs)
    raise ValueError(f"unknown intersection {how}")
