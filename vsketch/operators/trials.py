"""Many hash seeds side by side: repeats of ball and triangle estimates on graphs that fit a worker.

A seed is a task (or several), which holds the whole graph as two index arrays; these are collected only after a
check of their size (LOCAL arcs).  Larger graphs take the distributed operators, one seed after another, with
the same results.  Registers come from the same JVM hash expressions as those of the sketch table."""

from __future__ import annotations

from dataclasses import dataclass, replace

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.estimate import estimate_array
from ..functions.hashing import hash_word, index_of, rank_of
from ..functions.spec import SketchSpec
from ..sources.build import arcs
from . import balls, exact, triangles, vst
from .joint import estimate_pairs

LOCAL = 4_000_000
_CELLS = 1 << 26  # bytes of registers or bits that a step gathers at once


@dataclass
class LocalGraph:
    """ids ascending; the neighbours of vertex i are to[start[i] : start[i + 1]], as places in ids; edges u, v as places."""

    ids: np.ndarray
    start: np.ndarray
    to: np.ndarray
    u: np.ndarray
    v: np.ndarray

    def gathered(self, rows: np.ndarray, how=np.maximum) -> np.ndarray:
        """``how`` over the rows of each vertex's neighbours."""
        out = np.empty((len(self.ids), rows.shape[1]), rows.dtype)
        ends = self.start.tolist()
        for i in range(len(self.ids)):
            how.reduce(rows[self.to[ends[i] : ends[i + 1]]], axis=0, out=out[i])
        return out


def local_graph(edges: DataFrame, most: int = LOCAL) -> LocalGraph | None:
    """The graph as arrays, or None where it has more than ``most`` arcs."""
    if 2 * edges.count() > most:
        return None
    got = edges.select("u", "v").toArrow()
    u, v = (np.asarray(got.column(c)).astype(np.int64) for c in "uv")
    ids = np.unique(np.concatenate([u, v]))
    pu, pv = np.searchsorted(ids, u), np.searchsorted(ids, v)
    one, two = np.concatenate([pu, pv]), np.concatenate([pv, pu])
    order = np.argsort(one, kind="stable")
    return LocalGraph(ids, np.searchsorted(one[order], np.arange(len(ids) + 1)), two[order], pu, pv)


def _hashed(edges: DataFrame, spec: SketchSpec, seeds: int) -> DataFrame:
    """seed, x, j, rho of every vertex's own hash."""
    rows = arcs(edges).select("x").distinct().withColumn("seed", F.explode(F.sequence(F.lit(spec.seed), F.lit(spec.seed + seeds - 1))))
    word = hash_word(F.col("x"), spec, F.col("seed"))
    return rows.select((F.col("seed") - spec.seed).alias("seed"), "x", index_of(word, spec).alias("j"), rank_of(word, spec).alias("rho"))


def _own(graph: LocalGraph, pdf: pd.DataFrame, spec: SketchSpec) -> np.ndarray:
    regs = np.zeros((len(graph.ids), spec.r), np.uint8)
    regs[np.searchsorted(graph.ids, pdf.x.to_numpy()), pdf.j.to_numpy()] = pdf.rho.to_numpy()
    return regs


def ball_trials(edges: DataFrame, k: int, spec: SketchSpec, seeds: int, how: str = "beta") -> DataFrame:
    """seed, x, t, n_est: closed ball sizes of every vertex for t = 1..k and ``seeds`` seeds."""
    graph = local_graph(edges)
    if graph is None:
        out = None
        for seed in range(seeds):
            own = replace(spec, seed=spec.seed + seed)
            got = balls.ball_sizes(edges, vst.accumulate(edges, own), k, how=how, form="auto", keep_layers=False).local.select(F.lit(seed).alias("seed"), "x", "t", "n_est")
            out = got if out is None else out.unionByName(got)
        return out
    shared = edges.sparkSession.sparkContext.broadcast(graph)

    def run(pdf: pd.DataFrame) -> pd.DataFrame:
        own = shared.value
        regs, found = _own(own, pdf, spec), []
        for t in range(1, k + 1):
            regs = np.maximum(regs, own.gathered(regs))
            found.append(pd.DataFrame({"seed": pdf.seed.iloc[0], "x": own.ids, "t": t, "n_est": estimate_array(regs, how)}))
        return pd.concat(found)

    return _hashed(edges, spec, seeds).groupBy("seed").applyInPandas(run, "seed int, x long, t int, n_est double")


def exact_balls(edges: DataFrame, k: int, block: int = 1024) -> DataFrame:
    """x, t, n: exact closed ball sizes, by bit sets of ``block`` sources at a time; larger graphs as exact.balls."""
    graph = local_graph(edges)
    if graph is None:
        return exact.balls(edges, k)
    spark = edges.sparkSession
    shared, n = spark.sparkContext.broadcast(graph), len(graph.ids)

    def run(parts):
        own = shared.value
        for pdf in parts:
            for lo in pdf.id.tolist():
                width = min(block, n - lo)
                bits = np.zeros((n, -(-width // 64)), np.uint64)
                at = np.arange(width)
                bits[lo + at, at // 64] = np.uint64(1) << (at % 64).astype(np.uint64)
                for t in range(1, k + 1):
                    bits = bits | own.gathered(bits, np.bitwise_or)
                    met = sum(np.unpackbits(bits[i : i + 4096].view(np.uint8), axis=1, bitorder="little").sum(0, dtype=np.int64) for i in range(0, n, 4096))
                    yield pd.DataFrame({"x": own.ids[lo : lo + width], "t": t, "n": met[:width]})

    starts = spark.range(0, max(n, 0), block, -(-n // block) or 1)
    return starts.mapInPandas(run, "x long, t int, n long")


def edge_trials(edges: DataFrame, spec: SketchSpec, seeds: int, how: str = "ml", part: int = 20_000) -> DataFrame:
    """seed, u, v, t_est: triangles of every edge for ``seeds`` seeds, clamped as in triangles.edge_triangles."""
    digits = triangles.ML_DIGITS if how == "ml" else triangles.DIGITS
    graph = local_graph(edges)
    if graph is None:
        out = None
        for seed in range(seeds):
            got = triangles.edge_triangles(edges, vst.accumulate(edges, replace(spec, seed=spec.seed + seed)), how).select(F.lit(seed).alias("seed"), "u", "v", "t_est")
            out = got if out is None else out.unionByName(got)
        return out
    context = edges.sparkSession.sparkContext
    # each task makes all registers of its seed, so there are only as many tasks as keep the cores busy
    parts = max(1, min(-(-len(graph.u) // part), -(-2 * context.defaultParallelism // seeds)))
    shared, part = context.broadcast(graph), -(-len(graph.u) // parts)

    def run(pdf: pd.DataFrame) -> pd.DataFrame:
        own, at = shared.value, int(pdf.part.iloc[0])
        regs = own.gathered(_own(own, pdf, spec))
        size = estimate_array(regs, "beta")
        u, v = (x[at * part : (at + 1) * part] for x in (own.u, own.v))
        found = []
        for i in range(0, len(u), 1024):
            a, b = u[i : i + 1024], v[i : i + 1024]
            inter = estimate_pairs(regs[a], regs[b], spec, how, (size[a], size[b]))["inter"]
            found.append(np.round(np.maximum(0, np.minimum(inter, np.minimum(size[a], size[b]) - 1)), digits))
        return pd.DataFrame({"seed": pdf.seed.iloc[0], "u": own.ids[u], "v": own.ids[v], "t_est": np.concatenate(found)})

    hashed = _hashed(edges, spec, seeds).withColumn("part", F.explode(F.sequence(F.lit(0), F.lit(parts - 1))))
    return hashed.groupBy("seed", "part").applyInPandas(run, "seed int, u long, v long, t_est double")


def exact_edge_triangles(edges: DataFrame, part: int = 50_000, most: int = 1 << 28) -> DataFrame:
    """u, v, t: common neighbours of the ends of every edge, by a bit set of neighbours for each vertex where these
    take up to ``most`` bytes; larger graphs as exact.edge_triangles."""
    graph = local_graph(edges)
    if graph is None or len(graph.ids) ** 2 // 8 > most:
        return exact.edge_triangles(edges)
    spark = edges.sparkSession
    shared, m = spark.sparkContext.broadcast(graph), len(graph.u)

    def run(parts):
        own, bits = shared.value, None
        for pdf in parts:
            for lo in pdf.id.tolist():
                if bits is None:
                    n = len(own.ids)
                    bits = np.zeros((n, -(-n // 64)), np.uint64)
                    x = np.repeat(np.arange(n), np.diff(own.start))
                    np.bitwise_or.at(bits, (x, own.to // 64), np.uint64(1) << (own.to % 64).astype(np.uint64))
                u, v = own.u[lo : lo + part], own.v[lo : lo + part]
                step = max(1, _CELLS // (8 * bits.shape[1]))
                t = [np.bitwise_count(bits[u[i : i + step]] & bits[v[i : i + step]]).sum(1, dtype=np.int64) for i in range(0, len(u), step)]
                yield pd.DataFrame({"u": own.ids[u], "v": own.ids[v], "t": np.concatenate(t)})

    starts = spark.range(0, m, part, -(-m // part) or 1)
    return starts.mapInPandas(run, "u long, v long, t long")


def precision_trials(est: DataFrame, truth: DataFrame, keys: list[str], ks: tuple[int, ...], shares: tuple[float, ...] = tuple(i / 5 for i in range(1, 11))) -> DataFrame:
    """seed, k, kprime, tp, fp, fn, precision, recall: tie-aware (every row that reaches the true k-th value is heavy).

    A seed's rows meet in one task: for experiments on graphs of bounded size.  A k over the number of rows has none."""

    def run(pdf: pd.DataFrame) -> pd.DataFrame:
        true = pdf.t.to_numpy()
        order = np.lexsort([*(pdf[c].to_numpy() for c in reversed(keys)), -pdf.t_est.to_numpy()])
        rows = []
        for k in ks:
            if k > len(true):
                continue
            heavy = true >= np.partition(true, len(true) - k)[len(true) - k]
            hit = np.cumsum(heavy[order])
            for share in shares:
                kp = min(max(1, round(k * share)), len(true))
                rows.append((int(pdf.seed.iloc[0]), k, kp, int(hit[kp - 1]), int(kp - hit[kp - 1]), int(heavy.sum() - hit[kp - 1]), hit[kp - 1] / kp, hit[kp - 1] / heavy.sum()))
        return pd.DataFrame(rows, columns=["seed", "k", "kprime", "tp", "fp", "fn", "precision", "recall"])

    rows = truth.select(*keys, "t").join(est.select("seed", *keys, "t_est"), keys)
    return rows.groupBy("seed").applyInPandas(run, "seed int, k int, kprime int, tp long, fp long, fn long, precision double, recall double")
