"""Minimax contiguous partition of ordered atomic groups into shards.

Groups are equal texts, ordered by the smallest doc_id that holds them.  The smallest feasible
capacity is found by binary search with a greedy check.  The driver never sees all groups: it works on
cells of a histogram over the order key and asks Spark to refine only cells in which a cut can fall, until
all those are single groups, so the answer is exact with a few thousand numbers on the driver."""

from __future__ import annotations

from bisect import bisect_right
from itertools import accumulate

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .common import arrow_map, column, table

LOWEST = -(2**63)
CELLS = 4096


class Cells:
    """Ordered (first key, last key, bytes); a cell with equal keys is one group and can't be split."""

    def __init__(self, rows: list[tuple[int, int, int]]):
        self.rows = sorted(rows)
        self.ends = list(accumulate((r[2] for r in self.rows), initial=0))
        self.total = self.ends[-1]

    def whole(self, i: int) -> bool:
        return self.rows[i][0] == self.rows[i][1]

    def forward(self, start: float, cap: int, loose: bool) -> float:
        """How far a shard from ``start`` reaches; loose: cells that can be split give any part."""
        goal = start + cap
        if goal >= self.total:
            return self.total
        i = bisect_right(self.ends, goal) - 1
        return goal if loose and not self.whole(i) else max(self.ends[i], start)

    def backward(self, end: float, cap: int, loose: bool) -> float:
        goal = end - cap
        if goal <= 0:
            return 0
        i = bisect_right(self.ends, goal - 1)
        return goal if loose and not self.whole(i - 1) else min(self.ends[i], end)

    def reach(self, cap: int, parts: int, loose: bool) -> list[float]:
        out = [0.0]
        for _ in range(parts):
            out.append(self.forward(out[-1], cap, loose))
        return out

    def back(self, cap: int, parts: int, loose: bool) -> list[float]:
        out = [float(self.total)]
        for _ in range(parts):
            out.append(self.backward(out[-1], cap, loose))
        return out[::-1]

    def capacity(self, parts: int, loose: bool) -> int:
        low = max([-(-self.total // parts), *(r[2] for i, r in enumerate(self.rows) if not loose or self.whole(i))])
        high = max(low, self.total)
        while low < high:
            mid = (low + high) // 2
            if self.reach(mid, parts, loose)[-1] >= self.total:
                high = mid
            else:
                low = mid + 1
        return low

    def cuts(self, cap: int, parts: int) -> list[int]:
        """Prefix sums of cuts: each as near an equal share of what is left as the capacity allows."""
        least, out = self.back(cap, parts, False), [0]
        for j in range(1, parts):
            most = self.forward(out[-1], cap, False)
            goal = out[-1] + (self.total - out[-1]) / (parts - j + 1)
            i = bisect_right(self.ends, goal) - 1
            near = self.ends[i]
            if i + 1 < len(self.ends) and self.ends[i + 1] - goal < goal - near:
                near = self.ends[i + 1]
            out.append(int(min(max(near, least[j], out[-1]), most)))
        return out[1:]

    def unsure(self, parts: int) -> list[int]:
        """Cells that can be split and in which a cut can fall."""
        low, high = self.capacity(parts, True), self.capacity(parts, False)
        spans = list(zip(self.reach(low, parts, False), self.reach(high, parts, True), strict=True))
        spans += list(zip(self.back(high, parts, True), self.back(low, parts, False), strict=True))
        spans += [(c - 1, c + 1) for c in self.cuts(high, parts)]
        found: set[int] = set()
        for a, b in spans:
            i = max(0, bisect_right(self.ends, min(a, b)) - 2)
            while i < len(self.rows) and self.ends[i] <= max(a, b):
                found.add(i)
                i += 1
        return sorted(i for i in found if not self.whole(i))


def _histogram(units: DataFrame, spans: list[tuple[int, int]]) -> list[tuple[int, int, int]]:
    """Bytes by cell; ``spans`` are key ranges, each cut into equal steps."""
    each = max(2, CELLS // len(spans))
    starts: list[int] = []
    for a, b in spans:
        step = max(1, -(-(b - a + 1) // each))
        starts += range(a, b + 1, step)
    edges = np.array(starts, np.int64)
    lows, highs = np.array([s[0] for s in spans], np.int64), np.array([s[1] for s in spans], np.int64)

    def make():
        def step(batch):
            key, size = (np.asarray(column(batch, c)) for c in ("first_id", "size"))
            at = np.searchsorted(lows, key, "right") - 1
            ok = (at >= 0) & (key <= highs[np.maximum(at, 0)])
            key, size = key[ok], size[ok]
            cell = np.searchsorted(edges, key, "right") - 1
            order = np.lexsort((key, cell))
            cell, key, size = cell[order], key[order], size[order]
            if not len(cell):
                return None
            at = np.flatnonzero(np.r_[True, np.diff(cell) != 0])
            last = np.r_[at[1:], len(cell)] - 1
            return {"cell": pa.array(cell[at], pa.int64()), "a": pa.array(key[at]), "b": pa.array(key[last]), "size": pa.array(np.add.reduceat(size, at))}

        return step

    got = arrow_map(units, make, "cell long, a long, b long, size long").groupBy("cell").agg(F.min("a"), F.max("b"), F.sum("size"))
    return [tuple(r)[1:] for r in got.collect()]  # at most CELLS rows, or two for each span


def minimax_cuts(units: DataFrame, shards: int) -> tuple[list[int], int]:
    """First keys of shards 1.., and the capacity.  units: first_id, size (one row for each group, or more)."""
    ends = units.agg(F.min("first_id"), F.max("first_id")).first()
    if ends[0] is None:
        return [], 0
    cells = Cells(_histogram(units, [(ends[0], ends[1])]))
    while todo := cells.unsure(shards):
        spans = [cells.rows[i][:2] for i in todo]
        fresh = _histogram(units, spans)
        gone = set(todo)
        cells = Cells([r for i, r in enumerate(cells.rows) if i not in gone] + fresh)
    cap = cells.capacity(shards, False)
    keys = []
    for cut in cells.cuts(cap, shards):
        i = bisect_right(cells.ends, cut) - 1
        keys.append(cells.rows[i][0] if i < len(cells.rows) else None)
    return keys, cap


def shard(docs: DataFrame, shards: int = 16, rows_a_block: int = 50_000) -> DataFrame:
    """doc_id, size, text_crc32, law, shard, slot, grown_shard for every row.

    Size is UTF-8 bytes plus 1 (null: 1, crc32 0, and nulls form a group with empty texts).  Equal texts
    stay together.  Groups with the same smallest doc_id (only where doc_id repeats) count as one.  A null
    doc_id orders first.  Slots are dealt by blocks of hashed doc_id with counted offsets, so no task
    numbers a whole shard.  An empty table gives no rows; other columns are ignored."""
    text = F.coalesce(F.col("text"), F.lit(""))
    seen = table(docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.unhex(F.sha2(text, 256)).alias("digest"), (F.octet_length(text) + 1).cast("long").alias("size"), F.crc32(text).alias("text_crc32")), "shard-rows")
    groups = table(seen.groupBy("digest").agg(F.min(F.coalesce("doc_id", F.lit(LOWEST))).alias("first_id"), F.sum("size").alias("size"), F.count("*").alias("copies")), "shard-groups")
    keys, _ = minimax_cuts(groups.select("first_id", "size"), shards)
    placed = F.lit(0)
    for k in keys:
        if k is not None:
            placed = placed + (F.col("first_id") >= F.lit(k)).cast("int")
    home = groups.select("digest", placed.cast("int").alias("shard"))
    total = groups.agg(F.sum("copies")).first()[0] or 0
    blocks = max(1, -(-total // (rows_a_block * shards)))
    rows = seen.join(home, "digest").select("doc_id", "size", "text_crc32", "shard", F.pmod(F.xxhash64("doc_id", "text_crc32"), F.lit(blocks)).alias("block"))
    rows = table(rows, "shard-placed")
    sums = rows.groupBy("shard", "block").agg(F.count("*").alias("n"))
    before = Window.partitionBy("shard").orderBy("block").rowsBetween(Window.unboundedPreceding, -1)
    offsets = sums.select("shard", "block", F.coalesce(F.sum("n").over(before), F.lit(0)).alias("before"))
    own = Window.partitionBy("shard", "block").orderBy("doc_id", "text_crc32", "size")
    return (
        rows.withColumn("nth", F.row_number().over(own)).join(offsets, ["shard", "block"])
        .select("doc_id", "size", "text_crc32", F.lit("bytes").alias("law"), "shard", (F.col("before") + F.col("nth") - 1).cast("long").alias("slot"), F.lit(None).cast("int").alias("grown_shard"))
    )
