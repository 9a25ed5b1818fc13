"""Triangle estimates from the sketch table: per edge, per vertex, in total; heavy hitters; densities."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .balls import shared_table
from .exact import degrees
from .joint import intersect
from .vst import Vst

DIGITS = 6
ML_DIGITS = 2  # the likelihood's top is found to far more, but another engine's logarithms move the last digits
#: Sums of estimates are taken in decimals, so that they don't depend on the order of rows.
EXACT = "decimal(28,6)"


def edge_triangles(edges: DataFrame, vst: Vst, how: str = "ml", clamp: bool = True) -> DataFrame:
    """u, v, t_est, density for all edges (simple, u < v: a repeated edge would count twice in sums).

    An edge's triangles are the common neighbours of its ends.  clamp: into [0, smaller degree - 1], since
    each end is the other's neighbour and never a common one."""
    digits = ML_DIGITS if how == "ml" else DIGITS
    got = intersect(edges, vst, how, edges)
    t = F.col("inter")
    if clamp:
        if "n_u" not in got.columns:
            d = vst.degree()
            du, dv = (d.select(F.col("x").alias(c), F.col("d_est").alias(f"n_{c}")) for c in "uv")
            got = got.join(du, "u").join(dv, "v")
        t = F.greatest(F.lit(0.0), F.least(t, F.col("n_u") - 1, F.col("n_v") - 1))
    t = F.round(t, digits)
    return got.select("u", "v", t.alias("t_est"), F.round(F.when(F.col("n_union") > 0, t / F.col("n_union")).otherwise(0.0), digits).alias("density"))


def top_edges(per_edge: DataFrame, k: int, ties: str = "cut", value: str = "t_est") -> DataFrame:
    """The k heaviest edges; ties ``cut`` by (u, v), or ``keep``: all that tie with the k-th."""
    if k <= 0:
        raise ValueError("k must be positive")
    order = [F.desc(value), "u", "v"]
    first = per_edge.orderBy(*order).limit(k)
    if ties == "cut":
        return first
    least = first.agg(F.min(value).alias("least"))
    return per_edge.join(F.broadcast(least), F.col(value) >= F.col("least")).drop("least")


def vertex_triangles(per_edge: DataFrame) -> DataFrame:
    """x, t_est: half the sum over a vertex's edges (each triangle has two of them)."""
    return per_edge.select(F.explode(F.array("u", "v")).alias("x"), "t_est").groupBy("x").agg(F.round(F.sum(F.col("t_est").cast(EXACT)).cast("double") / 2, DIGITS + 1).alias("t_est"))


def top_vertices(per_vertex: DataFrame, k: int) -> DataFrame:
    if k <= 0:
        raise ValueError("k must be positive")
    return per_vertex.orderBy(F.desc("t_est"), "x").limit(k)


def total(per_edge: DataFrame) -> DataFrame:
    """t_est: a third of the sum over edges."""
    return per_edge.agg(F.round(F.coalesce(F.sum(F.col("t_est").cast(EXACT)).cast("double"), F.lit(0.0)) / 3, 4).alias("t_est"))


def heavy_hitters(edges: DataFrame, vst: Vst, k: int, how: str = "ml") -> tuple[DataFrame, DataFrame, DataFrame]:
    """Top edges, top vertices and the total from one pass, written once and read three times."""
    per_edge = shared_table(edge_triangles(edges, vst, how), "edge-triangles")
    return top_edges(per_edge, k), top_vertices(vertex_triangles(per_edge), k), total(per_edge)


def top_edges_pruned(edges: DataFrame, vst: Vst, k: int, how: str = "ml", first: int = 10) -> DataFrame:
    """The same top edges for less: an edge can't have more triangles than its smaller degree less one.

    The ``first`` * k edges with the highest bound are estimated; their k-th value prunes the others."""
    d = vst.degree()
    du, dv = (d.select(F.col("x").alias(c), F.col("d_est").alias(f"d{c}")) for c in "uv")
    bound = shared_table(edges.join(du, "u").join(dv, "v").select("u", "v", (F.least("du", "dv") - 1).alias("bound")), "bounds")
    lead = bound.orderBy(F.desc("bound"), "u", "v").limit(first * k)
    kth = top_edges(edge_triangles(lead.select("u", "v"), vst, how), k).agg(F.min("t_est"), F.count("*")).first()
    rest = bound if kth[1] < k else bound.filter(F.round("bound", DIGITS) >= kth[0])
    return top_edges(edge_triangles(rest.select("u", "v"), vst, how), k)


def clustering(per_vertex: DataFrame, edges: DataFrame) -> DataFrame:
    """x, cc: share of a vertex's neighbour pairs that are linked (degrees exact; 0 under two neighbours)."""
    d = F.col("d").cast("double")
    cc = F.when(d > 1, 2 * F.col("t_est") / (d * (d - 1))).otherwise(0.0)
    return degrees(edges).join(per_vertex, "x", "left").select("x", F.round(F.coalesce(cc, F.lit(0.0)), DIGITS).alias("cc"))


def transitivity(per_edge: DataFrame, edges: DataFrame) -> DataFrame:
    wedges = degrees(edges).agg(F.sum(F.col("d") * (F.col("d") - 1) / 2).alias("w"))
    return total(per_edge).crossJoin(wedges).select(F.round(3 * F.col("t_est") / F.col("w"), DIGITS).alias("transitivity"))


def support_filter(per_edge: DataFrame, least: float, value: str = "t_est") -> DataFrame:
    return per_edge.filter(F.col(value) >= least).select("u", "v")


def top_edges_by_vertex(per_edge: DataFrame, k: int) -> DataFrame:
    """x, u, v, t_est, nth: each vertex's k heaviest edges."""
    rows = per_edge.select(F.explode(F.array("u", "v")).alias("x"), "u", "v", "t_est")
    nth = F.row_number().over(Window.partitionBy("x").orderBy(F.desc("t_est"), "u", "v"))
    return rows.withColumn("nth", nth).filter(F.col("nth") <= k)
