"""The vertex sketch table: for each vertex the registers of a cardinality sketch of its neighbours.

Relational form: rows (x, j, rho), only registers that are not zero.  Merging is a grouped maximum, so Spark
reduces before the shuffle, spills, and salts nothing away: maximum is the same in any order or repetition."""

from __future__ import annotations

import json
from dataclasses import dataclass

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions.estimate import estimate, estimate_geo
from ..functions.hashing import hash_word, index_of, rank_of
from ..functions.spec import SketchSpec, assert_compatible
from ..sources.build import arcs


def registers(rows: DataFrame, key: str | list[str], element: Column, spec: SketchSpec) -> DataFrame:
    """key.., j, rho: the nonzero registers of a sketch of each key's elements."""
    keys = [key] if isinstance(key, str) else key
    word = hash_word(element, spec)
    hashed = rows.select(*keys, index_of(word, spec).alias("j"), rank_of(word, spec).alias("rho"))
    return merge(hashed, keys)


def merge(rows: DataFrame, keys: list[str]) -> DataFrame:
    return rows.groupBy(*keys, "j").agg(F.max("rho").alias("rho"))


def measure(regs: DataFrame, keys: list[str], spec: SketchSpec, how: str = "beta", name: str = "n_est") -> DataFrame:
    """keys.., estimate of each sketch.  A sum of dyadic numbers: the same in any order."""
    sums = regs.groupBy(*keys).agg(F.sum(F.pow(F.lit(2.0), -F.col("rho"))).alias("_total"), F.count("*").cast("double").alias("_filled"), F.sum("rho").cast("double").alias("_ranks"))
    value = estimate_geo(F.col("_ranks"), spec) if how == "geo" else estimate(F.col("_total"), F.col("_filled"), spec, how)
    return sums.select(*keys, value.alias(name))


@dataclass(frozen=True)
class Vst:
    """A table of open sketches (a vertex is not in its own) and the spec that made it."""

    regs: DataFrame
    spec: SketchSpec

    def degree(self, how: str = "beta", ids: DataFrame | None = None) -> DataFrame:
        """x, d_est; with ids (a column x) also for vertices without neighbours (0)."""
        if ids is None:
            return measure(self.regs, ["x"], self.spec, how, "d_est")
        found = measure(self.regs.join(ids.select("x").distinct(), "x", "left_semi"), ["x"], self.spec, how, "d_est")
        return ids.select("x").distinct().join(found, "x", "left").select("x", F.coalesce("d_est", F.lit(0.0)).alias("d_est"))

    def union_size(self, groups: DataFrame, how: str = "beta") -> DataFrame:
        """gid, n_est: size of the union of neighbour sets of each group's vertices.  groups: gid, x."""
        merged = merge(groups.select("gid", "x").join(self.regs, "x").select("gid", "j", "rho"), ["gid"])
        return measure(merged, ["gid"], self.spec, how)

    def absorb(self, edges: DataFrame) -> Vst:
        """The table of the old and the new edges together."""
        fresh = registers(arcs(edges), "x", F.col("y"), self.spec)
        return Vst(merge(self.regs.unionByName(fresh), ["x"]), self.spec)

    def merged(self, other: Vst) -> Vst:
        assert_compatible(self.spec, other.spec)
        return Vst(merge(self.regs.unionByName(other.regs), ["x"]), self.spec)

    def save(self, path: str, buckets: int = 16) -> None:
        """Parquet, dealt by x and sorted, with the spec beside it."""
        self.regs.repartition(buckets, "x").sortWithinPartitions("x", "j").write.mode("overwrite").parquet(f"{path}/registers")
        spark = self.regs.sparkSession
        spark.createDataFrame([(json.dumps(self.spec.as_dict()),)], "spec string").coalesce(1).write.mode("overwrite").text(f"{path}/spec")


def load(spark: SparkSession, path: str) -> Vst:
    spec = SketchSpec(**json.loads(spark.read.text(f"{path}/spec").first()[0]))
    return Vst(spark.read.parquet(f"{path}/registers"), spec)


def accumulate(edges: DataFrame, spec: SketchSpec = SketchSpec()) -> Vst:
    """One pass over the edges; repeats, both directions and loops do no harm and need no cleaning."""
    return Vst(registers(arcs(edges), "x", F.col("y"), spec), spec)


def accumulate_builtin(edges: DataFrame, form: str = "hll", size: int = 12) -> DataFrame:
    """x, sk: built-in sketches with JVM partial merges (form ``hll`` or ``theta``); no register access."""
    agg = {"hll": F.hll_sketch_agg, "theta": F.theta_sketch_agg}[form]
    return arcs(edges).groupBy("x").agg(agg("y", size).alias("sk"))
