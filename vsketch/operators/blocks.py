"""Triangles of any simple graph by blocks of vertices: an edge travels in four bytes, to one task for each third block."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .classes import _closed

HELD = 1 << 21


def _packed(edges: DataFrame, ids: np.ndarray, k: int) -> DataFrame:
    """i, j, data: edges between blocks i <= j, as pairs of places inside them."""
    shared = edges.sparkSession.sparkContext.broadcast((ids, np.random.default_rng(0).permutation(len(ids))))

    def rows(held: list[tuple[np.ndarray, np.ndarray]]):
        a, b = (np.concatenate(x) for x in zip(*held, strict=True))
        i, j, p, q = a % k, b % k, a // k, b // k
        turned = (i > j) | ((i == j) & (p > q))
        i, j, p, q = np.where(turned, j, i), np.where(turned, i, j), np.where(turned, q, p), np.where(turned, p, q)
        pair = i * k + j
        order = np.argsort(pair, kind="stable")
        pair, data = pair[order], np.column_stack([p, q])[order].astype(np.uint16)
        at = np.flatnonzero(np.r_[True, pair[1:] != pair[:-1]])
        parts = [data[s:e].tobytes() for s, e in zip(at, [*at[1:], len(pair)], strict=True)]
        return pa.RecordBatch.from_arrays([pa.array((pair[at] // k).astype(np.int32)), pa.array((pair[at] % k).astype(np.int32)), pa.array(parts, pa.binary())], names=["i", "j", "data"])

    def run(batches):
        ids, place = shared.value
        held, n = [], 0
        for batch in batches:
            if batch.num_rows:
                held.append(tuple(place[np.searchsorted(ids, np.asarray(batch.column(c)))] for c in (0, 1)))
                n += batch.num_rows
            if n >= HELD:
                yield rows(held)
                held, n = [], 0
        if n:
            yield rows(held)

    return edges.select("u", "v").mapInArrow(run, "i int, j int, data binary")


def triangles(edges: DataFrame, vertices: DataFrame, block: int = 8192) -> DataFrame:
    """t: how many.  edges: u, v, every edge once; vertices: x, at least all ends (their ids are broadcast).

    Vertices are dealt evenly in blocks of up to ``block`` (65,536 at most); a task has the edges between three as bits."""
    ids = np.unique(np.asarray(vertices.select(F.col("x").cast("long")).distinct().toArrow().column(0)))
    k = max(1, -(-len(ids) // block))
    size = max(1, -(-len(ids) // k))
    thirds = F.transform(F.sequence(F.lit(0), F.lit(k - 1)), lambda z: F.array_sort(F.array("i", "j", z.cast("int"))))
    packed = _packed(edges, ids, k).withColumn("three", F.explode(F.array_distinct(thirds)))
    packed = packed.select(F.col("three")[0].alias("a"), F.col("three")[1].alias("b"), F.col("three")[2].alias("c"), "i", "j", "data")

    def count(key: tuple, group: pa.Table) -> pa.Table:
        three, held = [x.as_py() for x in key], {}
        for i, j, data in zip(*(group.column(c).to_pylist() for c in ("i", "j", "data")), strict=True):
            held.setdefault((i, j), []).append(np.frombuffer(data, np.uint16).reshape(-1, 2))
        sides = [held.get((three[p], three[q])) for p, q in ((0, 1), (0, 2), (1, 2))]
        t = _closed(*(np.concatenate(x).astype(np.int64) for x in sides), (np.ones(size, np.uint64),) * 3) if all(sides) else 0
        return pa.table({"t": pa.array([t], pa.int64())})

    return packed.groupBy("a", "b", "c").applyInArrow(count, "t long").agg(F.coalesce(F.sum("t"), F.lit(0)).cast("long").alias("t"))
