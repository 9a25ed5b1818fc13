"""Ball sizes: how many vertices lie within t hops, per vertex and in sum, by merging neighbours' sketches."""

from __future__ import annotations

import uuid
from collections.abc import Iterator
from contextlib import contextmanager
from dataclasses import dataclass

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions.spec import SketchSpec
from ..sources.build import arcs as both_ways
from .packed import ball_step_packed, measure_packed, pack, unpack
from .vst import Vst, measure, merge, registers

PACK_AT = 24  # registers, about where rows outweigh a binary several times


def shared_table(frame: DataFrame, tag: str) -> DataFrame:
    """Write to the folder that driver and executors share and read back: no lineage over hops."""
    spark = frame.sparkSession
    root = spark.conf.get("spark.checkpoint.dir", None) or spark.conf.get("spark.sql.warehouse.dir")
    path = f"{root.rstrip('/')}/vsketch/{tag}-{uuid.uuid4().hex}"
    frame.write.parquet(path)
    return spark.read.schema(frame.schema).parquet(path)


@dataclass
class Balls:
    """local: x, t, n_est.  layers: t -> registers (x, j, rho)."""

    local: DataFrame
    layers: dict[int, DataFrame]
    spec: SketchSpec
    hops: int

    @property
    def total(self) -> DataFrame:
        return self.local.groupBy("t").agg(F.sum("n_est").alias("n_est"))

    def save(self, path: str) -> None:
        """A folder a hop; saving again replaces the hops that are saved."""
        for t, regs in self.layers.items():
            regs.write.mode("overwrite").parquet(f"{path}/hop={t}")


def load_layers(spark: SparkSession, path: str, hop: int | None = None) -> DataFrame:
    """x, j, rho, hop of kept layers; a hop reads only its folder."""
    rows = spark.read.parquet(path)
    return rows if hop is None else rows.filter(F.col("hop") == hop)


def step(layer: DataFrame, arcs: DataFrame, source: DataFrame | None = None, exclusive: bool = False) -> DataFrame:
    """The next layer: every vertex merges its neighbours' sketches (of ``source``, by default the layer) into its own."""
    sent = arcs.join(layer if source is None else source, "x").select(F.col("y").alias("x"), "j", "rho")
    return merge(sent if exclusive else layer.unionByName(sent), ["x"])


def _sent(layer: DataFrame, d: DataFrame) -> float:
    """Registers that an arc carries on average.  d: x and its arcs."""
    nz = layer.groupBy("x").agg(F.count("*").alias("nz"))
    return nz.join(d, "x").agg(F.sum(F.col("nz").cast("double") * F.col("d")) / F.sum("d")).first()[0] or 0.0


def _packed_hops(layer: DataFrame, arcs: DataFrame, spec: SketchSpec, first: int, k: int, how: str, until_stable: bool) -> dict[int, tuple[DataFrame, DataFrame]]:
    """t -> (x, n_est; registers) of hops first..k, one binary a vertex; every layer is written."""
    now, out = shared_table(pack(layer, spec), "packed"), {}
    for t in range(first, k + 1):
        fresh = shared_table(ball_step_packed(now, arcs, spec, dense_only=False), "packed")
        if until_stable and fresh.join(now, ["x", "regs"], "left_anti").isEmpty():
            break
        out[t] = measure_packed(fresh, spec, how), unpack(fresh, spec)
        now = fresh
    return out


def ball_sizes(edges: DataFrame, vst: Vst, k: int, ball: str = "closed", how: str = "beta", active: str = "all", until_stable: bool = False, keep_layers: bool = True, cut_every: int = 1, form: str = "auto", simple: bool = True) -> Balls:
    """Sizes for t = 1..k.

    form: ``rows`` keeps a row a register throughout; ``packed`` goes over to a binary a vertex after the first
    hop; ``auto`` does so once an arc carries PACK_AT registers or more on average.  Registers are the same.
    ball: ``closed`` counts a vertex in its own ball from t = 1; ``as_printed`` starts from open sketches.
    active: ``changed`` lets only registers that grew in the last hop travel (the result is the same).
    simple: edges are distinct; without, repeats are dropped first, since each would send its sketch again (the
    result is the same).
    until_stable: stop when no register grows.  cut_every: hops between written layers (lineage is cut there)."""
    if k < 1:
        raise ValueError("k must be 1 or more")
    spec, arcs = vst.spec, both_ways(edges) if simple else both_ways(edges).distinct()
    layer = vst.regs
    if ball == "closed":
        own = registers(arcs.select("x").distinct().withColumn("me", F.col("x")), "x", F.col("me"), spec)
        layer = merge(layer.unionByName(own), ["x"])
    elif ball != "as_printed":
        raise ValueError(f"unknown ball {ball}")
    if k > 1:
        layer, arcs = shared_table(layer, "layer"), shared_table(arcs, "arcs")
    if form not in ("rows", "packed", "auto") or form == "packed" and (active == "changed" or how == "geo"):
        raise ValueError(f"form {form} is unknown, or has no {active}, {how}")
    local, layers, delta = measure(layer, ["x"], spec, how).withColumn("t", F.lit(1)), {1: layer}, layer
    hops, may_pack = 1, form == "auto" and active == "all" and how != "geo" and k > 1
    d = shared_table(arcs.groupBy("x").agg(F.count("*").alias("d")), "arcs-of") if may_pack else None
    for t in range(2, k + 1):
        if form == "packed" or may_pack and _sent(layer, d) >= PACK_AT:
            found = _packed_hops(layer, arcs, spec, t, k, how, until_stable)
            for at, (sizes, regs) in found.items():
                local = local.unionByName(sizes.withColumn("t", F.lit(at)))
                layers, hops = {**layers, at: regs} if keep_layers else {at: regs}, at
            break
        fresh = step(layer, arcs, delta if active == "changed" else None)
        if t < k and t % cut_every == 0 or until_stable or active == "changed":
            fresh = shared_table(fresh, "layer")
        if active == "changed" or until_stable:
            delta = fresh.join(layer, ["x", "j", "rho"], "left_anti")
            if until_stable and delta.isEmpty():
                break
            if active == "changed":
                delta = shared_table(delta, "delta")
        local = local.unionByName(measure(fresh, ["x"], spec, how).withColumn("t", F.lit(t)))
        layer, hops = fresh, t
        layers = {**layers, t: fresh} if keep_layers else {t: fresh}
    return Balls(local.select("x", "t", "n_est"), layers, spec, hops)


def two_hop(edges: DataFrame, vst: Vst, how: str = "beta") -> DataFrame:
    """x, n2: union of the neighbours' sketches only (misses neighbours that lie in no triangle)."""
    return measure(step(vst.regs, both_ways(edges).distinct(), exclusive=True), ["x"], vst.spec, how, "n2")


def coloured_ball_sizes(edges: DataFrame, colours: DataFrame, k: int, spec: SketchSpec, all_of: list[str] = (), none_of: list[str] = (), how: str = "beta") -> DataFrame:
    """x, t, n_est: vertices within t hops that have all of some colours and none of others.

    colours: x, colour (several rows a vertex).  A predicate gets its own layer 0, which holds matching vertices
    only, so complements are exact by filter, not by subtraction.  Vertices that reach none have no row."""
    arcs = both_ways(edges).distinct()
    marks = colours.groupBy("x").agg(F.collect_set("colour").alias("c"))
    vertices = arcs.select("x").distinct().join(marks, "x", "left").withColumn("c", F.coalesce("c", F.array().cast("array<string>")))
    for c in all_of:
        vertices = vertices.filter(F.array_contains("c", c))
    for c in none_of:
        vertices = vertices.filter(~F.array_contains("c", c))
    layer = registers(vertices.select("x", F.col("x").alias("me")), "x", F.col("me"), spec)
    out = None
    arcs = shared_table(arcs, "arcs") if k > 1 else arcs
    for t in range(1, k + 1):
        layer = step(layer, arcs)
        if t < k:
            layer = shared_table(layer, "layer")
        sized = measure(layer, ["x"], spec, how).withColumn("t", F.lit(t))
        out = sized if out is None else out.unionByName(sized)
    return out.select("x", "t", "n_est")


@contextmanager
def _merged_in_tasks(spark: SparkSession, most: int = 16_384) -> Iterator[None]:
    """While it lasts, a task merges the sketches of up to ``most`` vertices in memory (64 MB of 4 kB) before it sorts
    what comes: by default it sorts, and spills, the unmerged sketches of all arcs once it has met 128 vertices."""
    name = "spark.sql.objectHashAggregate.sortBased.fallbackThreshold"
    before = spark.conf.get(name)
    spark.conf.set(name, most)
    try:
        yield
    finally:
        spark.conf.set(name, before)


def ball_sizes_builtin(edges: DataFrame, k: int, lg: int = 12) -> DataFrame:
    """x, t, n_est from built-in sketches: each hop is a JVM partial union, and is written."""
    arcs = both_ways(edges).distinct()
    arcs = shared_table(arcs, "arcs")
    own = arcs.select("x", F.explode(F.array("x", "y")).alias("y"))
    layer, out = own.groupBy("x").agg(F.hll_sketch_agg("y", lg).alias("sk")), None
    with _merged_in_tasks(edges.sparkSession):
        for t in range(1, k + 1):
            if t > 1:
                sent = layer.unionByName(arcs.join(layer, "x").select(F.col("y").alias("x"), "sk"))
                layer = sent.groupBy("x").agg(F.hll_union_agg("sk").alias("sk"))
            layer = shared_table(layer, "layer")
            sized = layer.select("x", F.lit(t).alias("t"), F.hll_sketch_estimate("sk").cast("double").alias("n_est"))
            out = sized if out is None else out.unionByName(sized)
    return out


def effective_diameter(total: DataFrame, share: float = 0.9) -> DataFrame:
    """d_eff, mean_distance from t, n_est (one row a hop): the hop at which a share of reachable pairs is met, interpolated."""
    from pyspark.sql import Window

    w = Window.partitionBy(F.lit(0)).orderBy("t")  # a row a hop
    rows = total.select("t", "n_est", F.lag("n_est", 1, 0.0).over(w).alias("before"), F.max("n_est").over(Window.partitionBy(F.lit(0))).alias("most"))
    goal = F.lit(share) * F.col("most")
    at = F.col("t") - 1 + F.when(F.col("n_est") > F.col("before"), (goal - F.col("before")) / (F.col("n_est") - F.col("before"))).otherwise(0.0)
    rows = rows.withColumn("at", F.when((F.col("n_est") >= goal) & (F.col("before") < goal), at)).withColumn("grown", F.when(F.col("t") > 1, F.greatest(F.col("n_est") - F.col("before"), F.lit(0.0)) * F.col("t")).otherwise(0.0)).withColumn("pairs", F.when(F.col("t") > 1, F.greatest(F.col("n_est") - F.col("before"), F.lit(0.0))).otherwise(0.0))
    return rows.agg(F.min("at").alias("d_eff"), (F.sum("grown") / F.sum("pairs")).alias("mean_far_distance"))
