"""Exact answers: degrees, balls, intersections and triangles."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..sources.build import arcs as both_ways
from .balls import shared_table


def degrees(edges: DataFrame) -> DataFrame:
    return both_ways(edges).groupBy("x").agg(F.count("*").alias("d"))


def balls(edges: DataFrame, k: int) -> DataFrame:
    """x, t, n: vertices within t hops, x included, by widening frontiers that leave out what was met before.

    Frontiers run over the core only.  A leaf (one neighbour, and of a lone edge the end of higher id) lies on no path
    between others: it is counted one hop after its hub, and its own ball is that of its hub one hop earlier."""
    arcs = shared_table(both_ways(edges).distinct(), "arcs")
    d = arcs.groupBy("x").agg(F.count("*").alias("d"), F.min("y").alias("hub"))
    ends = d.filter("d = 1").select("x", "hub").join(d.select(F.col("x").alias("hub"), F.col("d").alias("dh")), "hub")
    leaves = shared_table(ends.filter("dh > 1 or hub < x").select("x", "hub"), "leaves")
    gone = leaves.select("x")
    core = arcs.join(gone, "x", "left_anti").select(F.col("x").alias("z"), F.col("y").alias("next"))
    core = shared_table(core.join(gone.withColumnRenamed("x", "next"), "next", "left_anti").select("z", "next"), "core")
    held = leaves.groupBy(F.col("hub").alias("z")).agg(F.count("*").alias("w"))
    met = d.select("x").join(gone, "x", "left_anti").select("x", F.col("x").alias("z"))
    front, grown = met, met.withColumn("hop", F.lit(0))
    for t in range(1, k + 1):
        front = front.join(core, "z").select("x", F.col("next").alias("z")).distinct().join(met, ["x", "z"], "left_anti")
        if t < k:
            front = shared_table(front, "front")
        met = met.unionByName(front)
        grown = grown.unionByName(front.withColumn("hop", F.lit(t)))
    sums = grown.join(held, "z", "left").groupBy("x", "hop").agg(F.count("*").alias("c"), F.coalesce(F.sum("w"), F.lit(0)).alias("w"))
    times = sums.withColumn("t", F.explode(F.sequence("hop", F.lit(k))))
    sizes = shared_table(times.groupBy("x", "t").agg((F.sum("c") + F.sum(F.when(F.col("hop") < F.col("t"), F.col("w")).otherwise(0))).alias("n")), "sizes")
    behind = sizes.filter(F.col("t") < k).select(F.col("x").alias("hub"), (F.col("t") + 1).alias("t"), F.when(F.col("t") == 0, F.lit(2)).otherwise(F.col("n")).cast("long").alias("n"))
    return sizes.filter("t > 0").select("x", "t", "n").unionByName(leaves.join(behind, "hub").select("x", "t", "n"))


def intersections(edges: DataFrame, pairs: DataFrame) -> DataFrame:
    """u, v, inter, n_union of neighbour sets."""
    arcs, d = both_ways(edges), degrees(edges)
    one, two = (arcs.select(F.col("x").alias(c), F.col("y").alias("z")) for c in "uv")
    met = pairs.select("u", "v").join(one, "u").join(two, ["v", "z"]).groupBy("u", "v").agg(F.count("*").alias("n"))
    du, dv = (d.select(F.col("x").alias(c), F.col("d").alias(f"d{c}")) for c in "uv")
    inter = F.coalesce("n", F.lit(0)).cast("double")
    return pairs.select("u", "v").join(met, ["u", "v"], "left").join(du, "u").join(dv, "v").select("u", "v", inter.alias("inter"), (F.col("du") + F.col("dv") - inter).alias("n_union"))


def oriented(edges: DataFrame) -> DataFrame:
    """s, t: each edge from its end of lower (degree, id) to the other; out-degrees stay under sqrt(2m)."""
    d = degrees(edges)
    du, dv = (d.select(F.col("x").alias(c), F.col("d").alias(f"d{c}")) for c in "uv")
    rows = edges.join(du, "u").join(dv, "v")
    first = (F.col("du") < F.col("dv")) | ((F.col("du") == F.col("dv")) & (F.col("u") < F.col("v")))
    return rows.select(F.when(first, F.col("u")).otherwise(F.col("v")).alias("s"), F.when(first, F.col("v")).otherwise(F.col("u")).alias("t"))


def triangles(edges: DataFrame) -> DataFrame:
    """a, b, c with a < b < c, each triangle once: wedges of the orientation that an edge closes."""
    o = oriented(edges)
    one, two = o.select("s", F.col("t").alias("p")), o.select("s", F.col("t").alias("r"))
    wedges = one.join(two, "s").filter("p < r")
    closed = wedges.join(edges.select(F.col("u").alias("p"), F.col("v").alias("r")), ["p", "r"], "left_semi")
    three = F.sort_array(F.array("s", "p", "r"))
    return closed.select(three[0].alias("a"), three[1].alias("b"), three[2].alias("c"))


def edge_triangles(edges: DataFrame, how: str = "oriented") -> DataFrame:
    """u, v, t for every edge."""
    if how == "adjacency":
        return intersections(edges, edges).select("u", "v", F.col("inter").cast("long").alias("t"))
    if how == "arrays":  # adjacency lists side by side; for graphs whose hubs fit a row
        lists = both_ways(edges).groupBy("x").agg(F.collect_set("y").alias("n"))
        one, two = (lists.select(F.col("x").alias(c), F.col("n").alias(f"n{c}")) for c in "uv")
        return edges.join(one, "u").join(two, "v").select("u", "v", F.size(F.array_intersect("nu", "nv")).cast("long").alias("t"))
    sides = F.array(F.struct(F.col("a").alias("u"), F.col("b").alias("v")), F.struct(F.col("a").alias("u"), F.col("c").alias("v")), F.struct(F.col("b").alias("u"), F.col("c").alias("v")))
    counts = triangles(edges).select(F.inline(sides)).groupBy("u", "v").agg(F.count("*").alias("t"))
    return edges.join(counts, ["u", "v"], "left").select("u", "v", F.coalesce("t", F.lit(0)).cast("long").alias("t"))


def vertex_triangles(edges: DataFrame) -> DataFrame:
    """x, t for every vertex."""
    per_edge = edge_triangles(edges)
    return per_edge.select(F.explode(F.array("u", "v")).alias("x"), "t").groupBy("x").agg((F.sum("t") / 2).cast("long").alias("t"))


def global_triangles(edges: DataFrame) -> DataFrame:
    return triangles(edges).agg(F.count("*").alias("t"))
