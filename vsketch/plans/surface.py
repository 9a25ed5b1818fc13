"""SQL surface: views of a graph and its sketch table, and functions over sketches."""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from ..functions.estimate import estimate_array
from ..functions.hashing import hash_word, index_of, rank_of
from ..functions.spec import SketchSpec
from ..operators.joint import estimate_pairs
from ..operators.packed import pack, to_dense
from ..operators.vst import Vst


def register(spark: SparkSession, edges: DataFrame, vst: Vst, balls: DataFrame | None = None) -> None:
    """Views edges, vst, vst_packed (and balls); functions vs_estimate(mode, regs), vs_merge(mode, regs, mode, regs),
    vs_joint(mode, regs, mode, regs); view vertex_words with the register index and rank of each vertex."""
    spec = vst.spec
    edges.createOrReplaceTempView("edges")
    vst.regs.createOrReplaceTempView("vst")
    pack(vst.regs, spec).createOrReplaceTempView("vst_packed")
    if balls is not None:
        balls.createOrReplaceTempView("balls")

    def vs_estimate(mode: pd.Series, regs: pd.Series) -> pd.Series:
        return pd.Series(estimate_array(to_dense(mode, regs, spec)))

    def vs_merge(m1: pd.Series, r1: pd.Series, m2: pd.Series, r2: pd.Series) -> pd.Series:
        return pd.Series([x.tobytes() for x in np.maximum(to_dense(m1, r1, spec), to_dense(m2, r2, spec))])

    def vs_joint(m1: pd.Series, r1: pd.Series, m2: pd.Series, r2: pd.Series) -> pd.DataFrame:
        got = estimate_pairs(to_dense(m1, r1, spec), to_dense(m2, r2, spec), spec, "ml")
        return pd.DataFrame({k: got[k] for k in ("a_only", "b_only", "inter")})

    for name, f, kind in (("vs_estimate", vs_estimate, "double"), ("vs_merge", vs_merge, "binary"), ("vs_joint", vs_joint, "a_only double, b_only double, inter double")):
        spark.udf.register(name, F.pandas_udf(f, kind))

    vertices = edges.select(F.explode(F.array("u", "v")).alias("x")).distinct()
    word = hash_word(F.col("x"), spec)
    vertices.select("x", index_of(word, spec).alias("vs_index"), rank_of(word, spec).alias("vs_rank")).createOrReplaceTempView("vertex_words")


def neighbourhood(edges: DataFrame, x: int, hops: int = 1) -> DataFrame:
    """z, t: vertices within ``hops`` of one vertex and the first hop that meets them (a point query: small frontiers)."""
    spark = edges.sparkSession
    met = spark.createDataFrame([(x, 0)], T.StructType([T.StructField("z", T.LongType()), T.StructField("t", T.IntegerType())]))
    front = met
    for t in range(1, hops + 1):
        ends = front.select(F.col("z").alias("s"))
        step = edges.join(F.broadcast(ends), F.col("u") == F.col("s")).select(F.col("v").alias("z"))
        step = step.unionByName(edges.join(F.broadcast(ends), F.col("v") == F.col("s")).select(F.col("u").alias("z"))).distinct()
        front = step.join(met, "z", "left_anti").withColumn("t", F.lit(t))
        met = met.unionByName(front)
    return met
