"""Balls of a graph that links ids seen under ``seconds`` apart, from the sightings alone.

The neighbours that a sighting brings lie in one window of time, so a hop merges what lies in windows and no edge is
made: the edges grow with the square of a window's sightings, the work here grows with the sightings.  Time is cut in
cells of ``seconds``; a window is its own cell, an end of the cell before and a start of the next one, whose running
merges are made once a cell.  Cells are dealt in ranges of about ``many`` sightings with a cell of overlap."""

from __future__ import annotations

from collections.abc import Callable

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.hashing import hash_word, rank_of
from ..functions.spec import SketchSpec
from .balls import Balls, shared_table
from .packed import SCHEMA, _pack_rows, measure_packed, merge_packed, pack, to_dense, unpack
from .vst import registers


def sightings(rows: DataFrame, ts: str, who: str, seconds: int, many: int = 400_000) -> DataFrame:
    """r, t, x, core: who was seen when, in ranges of time; rows that are not core only show a range its borders."""
    width = seconds * 1_000_000
    at = F.unix_micros(F.col(ts).cast("timestamp"))
    rows = rows.select(at.alias("t"), F.col(who).cast("long").alias("x")).filter("t is not null and x is not null").distinct()
    cell = F.floor(F.col("t") / F.lit(width)).cast("long")
    k = max(1, -(-rows.count() // many))
    cuts = rows.agg(F.percentile_approx(cell, [i / k for i in range(1, k)], 10_000)).first()[0] or [] if k > 1 else []
    bounds = F.array(*(F.lit(c).cast("long") for c in sorted(set(cuts)))) if cuts else F.array().cast("array<long>")
    place = lambda c: F.size(F.filter(bounds, lambda b: b <= c))
    rows = rows.select("t", "x", place(cell).alias("own"), F.explode(F.array_distinct(F.array(place(cell - 1), place(cell), place(cell + 1)))).alias("r"))
    return shared_table(rows.select("r", "t", "x", (F.col("r") == F.col("own")).alias("core")), "sightings")


def _spans(t: np.ndarray, u: np.ndarray, core: np.ndarray, width: int) -> tuple[np.ndarray, ...]:
    """start of cells; and cell, id, first and last place (of the window) of each id in each core cell, where the
    window holds another id.  t ascends."""
    cell = t // width
    starts = np.flatnonzero(np.r_[True, cell[1:] != cell[:-1]])
    number = np.cumsum(np.r_[False, cell[1:] != cell[:-1]])
    here = np.flatnonzero(core)
    order = here[np.lexsort((here, u[here], number[here]))]
    first = np.r_[True, (u[order][1:] != u[order][:-1]) | (number[order][1:] != number[order][:-1])]
    at = np.flatnonzero(first)
    one, last = order[at], order[np.r_[at[1:], len(order)] - 1]
    lo, hi = np.searchsorted(t, t[one] - width, "right"), np.searchsorted(t, t[last] + width, "left")
    change = np.r_[np.flatnonzero(u[1:] != u[:-1]) + 1, len(u)]
    other = change[np.searchsorted(change, lo, "right")] < hi
    return starts, number[one][other], u[one][other], lo[other], hi[other]


def _merged(values: np.ndarray, u: np.ndarray, spans: tuple[np.ndarray, ...], join: np.ufunc, own: tuple | None, out: np.ndarray) -> np.ndarray:
    """Which ids got something; ``out`` gets for each id the merged values of all its windows.

    own: place and value of what an id itself brings, which then is left out (values hold no more than that)."""
    starts, number, who, lo, hi = spans
    ends = np.r_[starts[1:], len(u)]
    got = np.zeros(len(out), bool)
    cells = np.flatnonzero(np.r_[True, number[1:] != number[:-1]]) if len(number) else np.array([], int)
    if own is not None:
        best = _others(u, who, lo, hi, *own)
    made: dict[int, np.ndarray] = {}

    def ahead(c: int) -> np.ndarray:
        if c not in made:
            made[c] = join.accumulate(values[u[starts[c] : ends[c]]], axis=0)
        return made[c]

    for a, b in zip(cells.tolist(), [*cells[1:].tolist(), len(number)], strict=True):
        c = int(number[a])
        for old in [k for k in made if k < c]:
            del made[old]
        ids = who[a:b]
        rows = np.repeat(ahead(c)[-1:], b - a, axis=0)
        before, after = lo[a:b] < starts[c], hi[a:b] > ends[c]
        if before.any():
            s, e = starts[c - 1], ends[c - 1]
            back = join.accumulate(values[u[s:e][::-1]], axis=0)
            rows[before] = join(rows[before], back[e - 1 - lo[a:b][before]])
        if after.any():
            rows[after] = join(rows[after], ahead(c + 1)[hi[a:b][after] - 1 - starts[c + 1]])
        if own is not None:
            rows[np.arange(b - a), own[0][ids]] = best[a:b]
        out[ids] = join(out[ids], rows)
        got[ids] = True
    return got


def _others(u: np.ndarray, who: np.ndarray, lo: np.ndarray, hi: np.ndarray, j: np.ndarray, rho: np.ndarray, step: int = 1 << 20) -> np.ndarray:
    """For each window of an id, the largest rank that others bring to the register that the id itself falls in."""
    n = len(u) + 1
    key = np.sort(j[u].astype(np.int64) * n + np.arange(len(u)))
    a, b = (np.searchsorted(key, j[who].astype(np.int64) * n + x) for x in (lo, hi))
    best, sums = np.zeros(len(who), np.uint8), np.cumsum(b - a)
    at = 0
    while at < len(who):
        to = max(at + 1, int(np.searchsorted(sums, (sums[at - 1] if at else 0) + step, "right")))
        size = (b - a)[at:to]
        row = np.repeat(np.arange(at, to), size)
        seen = u[key[np.repeat(a[at:to] - (np.cumsum(size) - size), size) + np.arange(size.sum())] % n]
        strange = seen != who[row]
        np.maximum.at(best, row[strange], rho[seen[strange]].astype(np.uint8))
        at = to
    return best


def _hop(seen: DataFrame, layer: DataFrame, seconds: int, join: np.ufunc, read: Callable, write: Callable, schema: str, open_: bool = False) -> DataFrame:
    """A row for each range and id: merged values of its windows there."""
    width = seconds * 1_000_000

    def run(events: pa.Table, held: pa.Table) -> pa.Table:
        ids, values = read(held)
        order = np.argsort(ids)
        ids, values = ids[order], values[order]
        t, x, core = (events.column(c).to_numpy() for c in ("t", "who", "core"))
        known = np.isin(x, ids)
        t, x, core = t[known], x[known], core[known]
        order = np.lexsort((x, t))
        t, x, core = t[order], x[order], core[order]
        if not len(t):
            return write(ids[:0], values[:0])
        u, out = np.searchsorted(ids, x), np.zeros_like(values)
        own = (values.argmax(axis=1), values.max(axis=1)) if open_ else None
        got = _merged(values, u, _spans(t, u, core, width), join, own, out)
        return write(ids[got], out[got])

    held = seen.select(F.col("r").alias("range"), "x").distinct().join(layer, "x").drop("r")
    return seen.select(F.col("r").alias("of"), "t", F.col("x").alias("who"), "core").groupBy("of").cogroup(held.groupBy("range")).applyInArrow(run, schema)


def _sketch_hop(seen: DataFrame, layer: DataFrame, seconds: int, spec: SketchSpec, open_: bool = False) -> DataFrame:
    def read(held):
        regs = held.column("regs").combine_chunks()
        return held.column("x").to_numpy(), np.array(to_dense(held.column("mode").to_numpy(), regs, spec))

    def write(ids, values):
        return pa.Table.from_batches([_pack_rows(ids, values, spec, False)])

    hop = _hop(seen, layer.select("x", "mode", "regs"), seconds, np.maximum, read, write, SCHEMA, open_)
    return shared_table(merge_packed(hop, spec), "layer")


def ball_sizes(seen: DataFrame, seconds: int, spec: SketchSpec, k: int, how: str = "beta", ball: str = "closed", until_stable: bool = False) -> Balls:
    """Sizes for t = 1..k, as balls.ball_sizes over the edges.  seen: as sightings() gives it.

    Every sketch is a binary, sparse or dense as it is filled."""
    if k < 1:
        raise ValueError("k must be 1 or more")
    if ball not in ("closed", "as_printed"):
        raise ValueError(f"unknown ball {ball}")
    ids = seen.select("x").distinct()
    layer = shared_table(pack(registers(ids.withColumn("me", F.col("x")), "x", F.col("me"), spec), spec), "layer")
    local, layers, hops = None, {}, 0
    for t in range(1, k + 1):
        fresh = _sketch_hop(seen, layer, seconds, spec, ball == "as_printed" and t == 1)
        if until_stable and t > 1 and fresh.join(layer, ["x", "regs"], "left_anti").isEmpty():
            break
        sized = measure_packed(fresh, spec, how).select("x", F.lit(t).alias("t"), "n_est")
        local = sized if local is None else local.unionByName(sized)
        layer, layers[t], hops = fresh, unpack(fresh, spec), t
    return Balls(local, layers, spec, hops)


def balls_bitmap(seen: DataFrame, seconds: int, k: int, maps: int = 16, seed: int = 0) -> DataFrame:
    """x, t, n_est: as baselines.balls_bitmap over the edges."""
    from .baselines import PHI, lowest_unset

    spec, names = SketchSpec(p=4, hash="portable", seed=seed), [f"b{i}" for i in range(maps)]
    ids = seen.select("x").distinct()
    ranks = ids.select("x", *(rank_of(hash_word(F.concat(F.lit(f"{i}/"), F.col("x").cast("string")), spec), spec).alias(n) for i, n in enumerate(names)))
    layer = shared_table(ranks.select("x", *(F.expr(f"shiftleft(1L, {n} - 1)").alias(n) for n in names)), "bitmaps")

    def read(held):
        return held.column("x").to_numpy(), np.column_stack([held.column(n).to_numpy() for n in names])

    def write(found, values):
        return pa.table([pa.array(found, pa.int64()), *(pa.array(values[:, i]) for i in range(maps))], names=["x", *names])

    out = None
    for t in range(1, k + 1):
        hop = _hop(seen, layer, seconds, np.bitwise_or, read, write, "x long, " + ", ".join(f"{n} long" for n in names))
        layer = shared_table(hop.groupBy("x").agg(*(F.bit_or(n).alias(n) for n in names)), "bitmaps")
        mean = sum((lowest_unset(F.col(n)).cast("double") for n in names[1:]), lowest_unset(F.col("b0")).cast("double")) / float(maps)
        sized = layer.select("x", F.lit(t).alias("t"), (F.pow(F.lit(2.0), mean) / PHI).alias("n_est"))
        out = sized if out is None else out.unionByName(sized)
    return out
