"""Graphs that link ids seen under ``seconds`` apart, by twins: ids that were seen at just the same times.

Twins are linked and have the same neighbours but for each other, so one of them stands for all: edges are made between
those that stand for others and expanded where they are read.  Where no two ids are twins this is the graph itself."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..sources.build import arcs as both_ways
from ..sources.build import proximity
from .balls import shared_table
from .exact import triangles
from .mixed import Mixed


def twins(rows: DataFrame, ts: str, who: str, seconds: int) -> tuple[DataFrame, DataFrame]:
    """c, w, part, xs (in parts of up to 256, ascending) of twins that have neighbours; and u, v: edges of the graph of
    those that stand for them (the lowest id)."""
    seen = rows.select(F.col(ts).cast("timestamp").alias("t"), F.col(who).cast("long").alias("x")).filter("t is not null and x is not null")
    times = seen.groupBy("x").agg(F.sort_array(F.collect_set(F.unix_micros("t"))).alias("ts"))
    held = times.groupBy("ts").agg(F.sort_array(F.collect_list("x")).alias("xs"))
    held = shared_table(held.select(F.col("xs")[0].alias("c"), "ts", "xs"), "twins")
    edges = shared_table(proximity(held.select("c", F.explode("ts").alias("at")).select("c", F.timestamp_micros("at").alias("t")), "t", "c", seconds), "twin-edges")
    linked = both_ways(edges).select(F.col("x").alias("c")).distinct().withColumn("near", F.lit(True))
    table = held.join(linked, "c", "left").filter("near or size(xs) > 1").select("c", F.size("xs").cast("long").alias("w"), "xs")
    part = F.explode(F.sequence(F.lit(0), F.floor((F.size("xs") - 1) / 256).cast("int")))
    return shared_table(table.withColumn("part", part).select("c", "w", "part", F.slice("xs", F.col("part") * 256 + 1, 256).alias("xs")), "twin-parts"), edges


def members(table: DataFrame) -> DataFrame:
    return table.select("c", F.explode("xs").alias("x"))


def weights(table: DataFrame) -> DataFrame:
    return table.filter("part = 0").select("c", "w")


def _small(frame: DataFrame, most: int = 2_000_000) -> DataFrame:
    """For a join: broadcast where it has few rows."""
    return F.broadcast(frame) if frame.count() <= most else frame


def balls(table: DataFrame, edges: DataFrame, k: int) -> DataFrame:
    """c, t, z: those standing for others that a ball holds, c included, for t = 1..k."""
    arcs = shared_table(both_ways(edges).withColumnRenamed("x", "z"), "twin-arcs")
    met = table.filter("part = 0").select("c", F.col("c").alias("z"))
    out = None
    for t in range(1, k + 1):
        met = shared_table(met.unionByName(met.join(arcs, "z").select("c", F.col("y").alias("z"))).distinct(), "twin-balls")
        one = met.select("c", F.lit(t).alias("t"), "z")
        out = one if out is None else out.unionByName(one)
    return out


def exact_sizes(table: DataFrame, edges: DataFrame, k: int) -> DataFrame:
    """x, t, n: ids within t hops, x included."""
    w = weights(table).select(F.col("c").alias("z"), "w")
    sizes = balls(table, edges, k).join(_small(w), "z").groupBy("c", "t").agg(F.sum("w").alias("n"))
    return members(table).join(sizes, "c").select("x", "t", "n")


def builtin_sizes(table: DataFrame, edges: DataFrame, k: int, lg: int = 12) -> DataFrame:
    """x, t, n_est by built-in sketches, a hop at a time, as balls.ball_sizes_builtin."""
    from .balls import _merged_in_tasks

    arcs, spark, out = shared_table(both_ways(edges), "twin-arcs"), edges.sparkSession, None
    with _merged_in_tasks(spark):
        layer = shared_table(members(table).groupBy(F.col("c").alias("x")).agg(F.hll_sketch_agg("x", lg).alias("sk")), "layer")
        for t in range(1, k + 1):
            sent = layer.unionByName(arcs.join(layer, "x").select(F.col("y").alias("x"), "sk"))
            layer = shared_table(sent.groupBy("x").agg(F.hll_union_agg("sk").alias("sk")), "layer")
            sized = layer.select(F.col("x").alias("c"), F.lit(t).alias("t"), F.hll_sketch_estimate("sk").cast("double").alias("n_est"))
            out = sized if out is None else out.unionByName(sized)
    return members(table).join(out, "c").select("x", "t", "n_est")


def edge_triangles(table: DataFrame, edges: DataFrame, most: int = 4096) -> DataFrame:
    """u, v, t for every edge, as exact.edge_triangles.

    Common neighbours come from a matrix on the driver where at most ``most`` stand for others, else from triangles."""
    w, spark = weights(table), edges.sparkSession
    if w.count() <= most:
        held = Mixed(table, edges.select(F.col("u").alias("c"), F.col("v").alias("c2")), edges.limit(0))
        ids, size, linked = held.types
        a, b = np.nonzero(np.triu(linked))
        pairs = spark.createDataFrame(pa.table({"u": ids[a], "v": ids[b], "t": held.common[a, b] + size[a] + size[b] - 2}))
        own = size > 1
        same = spark.createDataFrame(pa.table({"c": ids[own], "t": (linked @ size + size - 2)[own]}))
        return expand(table, pairs, same, "t")
    sides = F.array(*(F.struct(F.col(p).alias("u"), F.col(q).alias("v"), F.col(z).alias("c")) for p, q, z in ("abc", "acb", "bca")))
    met = triangles(edges).select(F.inline(sides)).join(_small(w), "c").groupBy("u", "v").agg(F.sum("w").alias("n"))
    sized = lambda c: _small(w.select(F.col("c").alias(c), F.col("w").alias(f"w{c}")))
    pairs = edges.join(met, ["u", "v"], "left").join(sized("u"), "u").join(sized("v"), "v").select("u", "v", (F.coalesce("n", F.lit(0)) + F.col("wu") + F.col("wv") - 2).alias("t"))
    near = both_ways(edges).join(sized("y"), "y").groupBy(F.col("x").alias("c")).agg(F.sum("wy").alias("n"))
    same = w.filter("w > 1").join(near, "c", "left").select("c", (F.coalesce("n", F.lit(0)) + F.col("w") - 2).alias("t"))
    return expand(table, pairs, same, "t")


def expand(table: DataFrame, pairs: DataFrame, same: DataFrame, value: str) -> DataFrame:
    """u, v, value: every edge once, u < v.  pairs: u, v, value of edges between different ones; same: c, value for twins."""
    tasks = max(12, int(weights(table).agg(F.sum("w")).first()[0] or 0) // 600)
    lists = table.select("c", "part", "xs")
    if lists.agg(F.coalesce(F.sum(F.size("xs")), F.lit(0))).first()[0] <= 2_000_000:  # else lists are shuffled
        lists = F.broadcast(lists)
    side = lambda c, n: table.select(F.col("c").alias(c), F.col("part").alias(n))
    across = pairs.join(side("u", "i"), "u").join(side("v", "j"), "v").select("u", "i", "v", "j", value)
    inside = same.select(F.col("c").alias("u"), F.col("c").alias("v"), value).join(side("u", "i"), "u").join(side("v", "j"), "v").filter("i <= j")
    work = across.unionByName(inside.select("u", "i", "v", "j", value)).repartition(tasks)
    both = work.join(lists.select(F.col("c").alias("u"), F.col("part").alias("i"), F.col("xs").alias("a")), ["u", "i"])
    both = both.join(lists.select(F.col("c").alias("v"), F.col("part").alias("j"), F.col("xs").alias("b")), ["v", "j"])
    both = both.select("a", "b", value, ((F.col("u") == F.col("v")) & (F.col("i") == F.col("j"))).alias("same"))
    both = both.select(F.explode("a").alias("p"), "b", value, "same").select("p", F.explode("b").alias("q"), value, "same")
    return both.filter("not same or p < q").select(F.least("p", "q").alias("u"), F.greatest("p", "q").alias("v"), value)
