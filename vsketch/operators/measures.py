"""Accuracy and cost: relative errors, bias, precision and recall, rank and tie profiles, space and traffic."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..sources.build import arcs as both_ways
from .joint import inclusion_exclusion
from .vst import Vst


def relative_errors(est: DataFrame, truth: DataFrame, keys: list[str], value: str, true: str) -> DataFrame:
    """keys.., est, truth, error; rows whose truth is 0 have a null error (undefined)."""
    rows = truth.join(est, keys, "left").select(*keys, F.coalesce(F.col(value), F.lit(0.0)).alias("est"), F.col(true).cast("double").alias("truth"))
    return rows.withColumn("error", F.when(F.col("truth") != 0, F.abs(F.col("est") - F.col("truth")) / F.abs("truth")))


def mre(errors: DataFrame, by: list[str] | None = None) -> DataFrame:
    """by.., mre, n, undefined: the mean over rows with a truth, and how many have none."""
    return errors.groupBy(*(by or [])).agg(F.avg("error").alias("mre"), F.count("error").alias("n"), F.sum(F.col("error").isNull().cast("long")).alias("undefined"))


def bias_sd(trials: DataFrame, truth: DataFrame, keys: list[str], value: str, true: str) -> DataFrame:
    """keys.., bias, sd: mean and spread over trials of the estimate against the truth, as shares of it."""
    share = F.col(value) / F.col(true)
    return trials.join(truth.filter(F.col(true) > 0), keys).groupBy(*keys).agg((F.avg(share) - 1).alias("bias"), F.stddev_samp(share).alias("sd"))


def _ranked(rows: DataFrame, keys: list[str], value: str, most: int) -> DataFrame:
    """The ``most`` heaviest rows and their rank (a bounded number of rows is numbered)."""
    top = rows.orderBy(F.desc(value), *keys).limit(most)
    return top.withColumn("rank", F.row_number().over(Window.partitionBy(F.lit(0)).orderBy(F.desc(value), *keys)))


def pr_curve(est: DataFrame, truth: DataFrame, keys: list[str], k: int, shares: list[float] | None = None, value: str = "t_est", true: str = "t", tie_aware: bool = False) -> DataFrame:
    """k, kprime, tp, fp, fn, tn, precision, recall of the estimated top k' against the true top k.

    tie_aware: every row whose truth reaches the k-th value counts as heavy."""
    shares = shares or [i / 5 for i in range(1, 11)]
    sizes = sorted({max(1, round(k * s)) for s in shares})
    m = truth.count()
    heavy = _ranked(truth.select(*keys, true), keys, true, k)
    if tie_aware:
        least = heavy.agg(F.min(true).alias("least"))
        heavy = truth.select(*keys, true).join(F.broadcast(least), F.col(true) >= F.col("least"))
    heavy = heavy.select(*keys, F.lit(1).alias("heavy"))
    found = _ranked(est.select(*keys, value), keys, value, max(sizes)).join(heavy, keys, "left")
    grid = est.sparkSession.createDataFrame([(s,) for s in sizes], "kprime int")
    hits = found.join(F.broadcast(grid), F.col("rank") <= F.col("kprime")).groupBy("kprime").agg(F.sum(F.coalesce("heavy", F.lit(0))).alias("tp"), F.count("*").alias("got"))
    n = heavy.agg(F.count("*").alias("n"))
    rows = hits.crossJoin(F.broadcast(n))
    tp = F.col("tp")
    return rows.select(F.lit(k).alias("k"), "kprime", "tp", (F.col("got") - tp).alias("fp"), (F.col("n") - tp).alias("fn"), (F.lit(m) - F.col("got") - F.col("n") + tp).alias("tn"), (tp / F.col("got")).alias("precision"), (tp / F.col("n")).alias("recall"))


def rank_profile(triangles: DataFrame, most: int = 10_000) -> DataFrame:
    """rank, u, v, t, density of the heaviest edges."""
    return _ranked(triangles, ["u", "v"], "t", most).select("rank", "u", "v", "t", "density")


def tie_profile(triangles: DataFrame, k: int) -> DataFrame:
    """kth, ties, modal, modal_share: value of the k-th edge, how many tie with it, the commonest value's share."""
    counts = triangles.groupBy("t").agg(F.count("*").alias("n"))
    kth = triangles.orderBy(F.desc("t")).limit(k).agg(F.min("t").alias("kth"))
    got = counts.crossJoin(F.broadcast(kth)).agg(F.max("kth").alias("kth"), F.max(F.when(F.col("t") == F.col("kth"), F.col("n"))).alias("ties"), F.max_by("t", F.struct("n", "t")).alias("modal"), (F.max("n") / F.sum("n")).alias("modal_share"))
    return got


def vst_bytes(vst: Vst, edges: DataFrame) -> DataFrame:
    """vertices, dense_share, sparse_bytes (4 a register), dense_bytes, mixed_bytes, edge_bytes (16 an edge)."""
    spec = vst.spec
    nz = vst.regs.groupBy("x").agg(F.count("*").alias("nz"))
    dense = F.col("nz") > spec.dense_at * spec.r
    got = nz.agg(F.count("*").alias("vertices"), F.avg(dense.cast("double")).alias("dense_share"), F.sum(F.col("nz") * 4).alias("sparse_bytes"), F.sum(F.lit(spec.r)).alias("dense_bytes"), F.sum(F.when(dense, F.lit(spec.r)).otherwise(F.col("nz") * 4)).alias("mixed_bytes"))
    return got.crossJoin(edges.agg((F.count("*") * 16).alias("edge_bytes")))


def traffic(edges: DataFrame, vst: Vst) -> DataFrame:
    """messages, register_rows that a ball pass and an edge pass ship, and what shipping the smaller sketch would."""
    nz = vst.regs.groupBy("x").agg(F.count("*").alias("nz"))
    ball = both_ways(edges).join(nz, "x").agg(F.count("*").alias("ball_messages"), F.sum("nz").alias("ball_rows"))
    one, two = (nz.select(F.col("x").alias(c), F.col("nz").alias(f"n{c}")) for c in "uv")
    edge = edges.join(one, "u").join(two, "v").agg(F.count("*").alias("edge_messages"), F.sum("nu").alias("edge_rows"), F.sum(F.least("nu", "nv")).alias("smaller_rows"))
    return ball.crossJoin(edge)


def reliability_flags(edges: DataFrame, vst: Vst, ratio: float = 10.0, density: float = 0.1) -> DataFrame:
    """u, v, size_ratio, density, shaky: where one set dwarfs the other or the intersection is a sliver of the union."""
    got = inclusion_exclusion(edges, vst)
    a, b = F.col("inter") + F.col("a_only"), F.col("inter") + F.col("b_only")
    rows = got.select("u", "v", (F.greatest(a, b) / F.greatest(F.least(a, b), F.lit(1.0))).alias("size_ratio"), (F.col("inter") / F.greatest("n_union", F.lit(1.0))).alias("density"))
    return rows.withColumn("shaky", (F.col("size_ratio") > ratio) | (F.col("density") < density))
