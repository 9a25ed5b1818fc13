"""Graphs that link all members of a group, by classes of members with equal groups.

Members of a class have the same neighbours (and each other), so pairs of classes stand for all edges: they are made
distinct as pairs of classes and expanded where they are read, and triangles are counted over classes with weights."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..sources.build import co_occurrence
from .balls import shared_table


def classes(members: DataFrame) -> tuple[DataFrame, DataFrame]:
    """c, w, xs (in parts of up to 256 members); and c, c2: linked classes, c < c2.  members: g, x."""
    sets = members.groupBy("x").agg(F.sort_array(F.collect_set("g")).alias("gs"))
    held = sets.groupBy("gs").agg(F.sort_array(F.collect_list("x")).alias("xs")).select("gs", "xs", F.array_min("xs").alias("c"))
    held = shared_table(held, "classes")
    pairs = co_occurrence(held.select("c", F.explode("gs").alias("g")), "g", "c", 200)
    part = F.sequence(F.lit(0), F.floor((F.size("xs") - 1) / 256).cast("int"))
    table = held.select("c", F.size("xs").cast("long").alias("w"), "xs", F.explode(part).alias("part"))
    return table.select("c", "w", "part", F.slice("xs", F.col("part") * 256 + 1, 256).alias("xs")), shared_table(pairs.select(F.col("u").alias("c"), F.col("v").alias("c2")), "class-pairs")


def edges(table: DataFrame, pairs: DataFrame) -> DataFrame:
    """u, v: every edge once, u < v, without a shuffle of edges."""
    one = table.select("c", F.col("part").alias("i"), F.col("xs").alias("a"))
    two = table.select(F.col("c").alias("c2"), F.col("part").alias("j"), F.col("xs").alias("b"))
    across = pairs.join(one, "c").join(two, "c2").select("a", "b", F.lit(False).alias("same"))
    inside = one.join(two, F.col("c") == F.col("c2")).filter("i <= j").select("a", "b", (F.col("i") == F.col("j")).alias("same"))
    both = across.unionByName(inside).select(F.explode("a").alias("p"), "b", "same").select("p", F.explode("b").alias("q"), "same")
    return both.filter("not same or p < q").select(F.least("p", "q").alias("u"), F.greatest("p", "q").alias("v"))


def _closed(one: np.ndarray, two: np.ndarray, far: np.ndarray, weights: tuple[np.ndarray, ...]) -> int:
    """Triangles of three blocks by weight.  one, two, far: edges (rows of two places) of blocks 1-2, 1-3 and 2-3."""
    w1, w2, w3 = (w.astype(np.uint64) for w in weights)
    order = np.argsort(w3, kind="stable")[::-1]  # heavy ones first, so that high bits of weights lie in front
    place = np.empty(len(order), np.int64)
    place[order] = np.arange(len(order))

    def bits(rows: np.ndarray, n: int) -> np.ndarray:
        out = np.zeros((n, -(-len(order) // 64) * 8), np.uint8)
        at = place[rows[:, 1]]
        np.bitwise_or.at(out, (rows[:, 0], at >> 3), (1 << (at & 7)).astype(np.uint8))
        return out.view(np.uint64)

    near, other, total = bits(two, len(w1)), bits(far, len(w2)), 0
    masks = []
    for b in range(int(w3.max()).bit_length()):
        on = (w3[order] >> np.uint64(b)) & np.uint64(1) == 1
        words = int(np.flatnonzero(on)[-1]) // 64 + 1 if on.any() else 0
        full = np.zeros(near.shape[1] * 64, np.uint8)
        full[: len(on)] = on
        masks.append(np.packbits(full, bitorder="little").view(np.uint64)[:words])
    one = one[np.argsort(one[:, 0], kind="stable")]
    at = np.flatnonzero(np.r_[True, one[1:, 0] != one[:-1, 0]]) if len(one) else []
    for a, z in zip(at, [*at[1:], len(one)], strict=True):
        x, ys = int(one[a, 0]), one[a:z, 1]
        for lo in range(0, len(ys), 4096):
            met = other[ys[lo : lo + 4096]] & near[x]
            here = np.zeros(len(met), np.uint64)
            for b, mask in enumerate(masks):
                if len(mask):
                    here += np.bitwise_count(met[:, : len(mask)] & mask).sum(axis=1, dtype=np.uint64) << np.uint64(b)
            total += int(w1[x]) * int((here * w2[ys[lo : lo + 4096]]).sum())
    return total


def weighted_triangles(pairs: DataFrame, weights: DataFrame, block: int = 4096) -> DataFrame:
    """t: sum over triangles of the product of their ends' weights.  pairs: c < c2, distinct; weights: c, w.

    Vertices are dealt by hash in blocks of about ``block``; a task has the edges between three of them as bits."""
    k = max(1, -(-weights.count() // block))
    side = lambda c: F.pmod(F.xxhash64(c), F.lit(k)).cast("int")
    w = lambda c, n: weights.select(F.col("c").alias(c), F.col("w").alias(n))
    rows = pairs.join(w("c", "w"), "c").join(w("c2", "w2"), "c2").withColumn("i", side("c")).withColumn("j", side("c2"))
    turned = (F.col("i") > F.col("j")) | ((F.col("i") == F.col("j")) & (F.col("c") > F.col("c2")))
    pick = lambda a, b, n: F.when(turned, F.col(b)).otherwise(F.col(a)).alias(n)
    rows = rows.select(pick("i", "j", "i"), pick("j", "i", "j"), pick("c", "c2", "a"), pick("c2", "c", "b"), pick("w", "w2", "wa"), pick("w2", "w", "wb"))
    thirds = F.transform(F.sequence(F.lit(0), F.lit(k - 1)), lambda z: F.array_sort(F.array("i", "j", z.cast("int"))))
    rows = rows.withColumn("blocks", F.explode(F.array_distinct(thirds))).withColumn("key", F.concat_ws("-", F.transform("blocks", lambda z: z.cast("string"))))

    def count(group: pa.Table) -> pa.Table:
        i, j, a, b, wa, wb = (group.column(c).to_numpy() for c in ("i", "j", "a", "b", "wa", "wb"))
        three = group.column("blocks")[0].as_py()
        ids, first = np.unique(np.r_[a, b], return_index=True)
        weight, where = np.r_[wa, wb][first], np.r_[i, j][first]
        number, sizes = np.zeros(len(ids), np.int64), []
        for n in three:
            here = where == n
            number[here] = np.arange(here.sum())
            sizes.append(weight[here])
        found = []
        for p, q in ((0, 1), (0, 2), (1, 2)):
            on = (i == three[p]) & (j == three[q])
            found.append(np.column_stack([number[np.searchsorted(ids, a[on])], number[np.searchsorted(ids, b[on])]]))
        some = all(len(s) for s in sizes) and all(len(f) for f in found)
        return pa.table({"t": pa.array([_closed(*found, tuple(sizes)) if some else 0], pa.int64())})

    got = rows.select("key", "blocks", "i", "j", "a", "b", "wa", "wb").groupBy("key").applyInArrow(count, "t long")
    return got.agg(F.coalesce(F.sum("t"), F.lit(0)).cast("long").alias("t"))


def global_triangles(table: DataFrame, pairs: DataFrame) -> DataFrame:
    """t: triangles of the graph: over three classes, two and one."""
    weights = shared_table(table.select("c", "w").distinct(), "class-weights")
    other = weights.select(F.col("c").alias("c2"), F.col("w").alias("w2"))
    two = pairs.join(weights, "c").join(other, "c2").agg(F.coalesce(F.sum(F.expr("(w * w2 * (w + w2 - 2)) div 2")), F.lit(0)).alias("t"))
    one = weights.agg(F.coalesce(F.sum(F.expr("(w * (w - 1) * (w - 2)) div 6")), F.lit(0)).alias("t"))
    return weighted_triangles(pairs, weights).unionByName(two).unionByName(one).agg(F.sum("t").alias("t"))
