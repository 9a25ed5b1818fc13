"""Sequential reservoirs over a stream of edges, without a shuffle of edges.

An edge has a place in the stream and, for each reservoir, a priority, both by hash.  A reservoir holds the ``size`` edges
of lowest priority among those that came: a new one enters with chance size / t and drives out one that is equally likely
any of those held, which is what drawing does.  Edges that ever enter are few (size times a logarithm), and their wedges
are closed by a join with all edges.  Every edge is read, counted and compared; the numbers are those of the pass in order."""

from __future__ import annotations

import heapq
from collections.abc import Callable

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .balls import shared_table

WEDGE = "trial int, worker string, u long, v long, since double, until double"


def _even(*parts) -> F.Column:
    """Evenly spread over 0 to 1, by 53 bits of a hash."""
    return F.shiftrightunsigned(F.xxhash64(*parts), 11).cast("double") * 2.0**-53


def streams(edges: DataFrame, seed: int = 0, groups: int | None = None) -> DataFrame:
    """stream, u, v, gu, gv, pos.  groups: a stream for each multiset of three groups of vertices, of the edges inside
    them; else one stream of all edges."""
    side = lambda c: F.pmod(F.xxhash64(F.lit(seed), c), F.lit(groups or 1))
    rows = edges.select("u", "v", side("u").alias("gu"), side("v").alias("gv"), _even(F.lit(seed + 1000), "u", "v").alias("pos"))
    if not groups:
        return rows.select(F.lit("").alias("stream"), "u", "v", "gu", "gv", "pos")
    three = F.transform(F.sequence(F.lit(0), F.lit(groups - 1)), lambda z: F.array_join(F.sort_array(F.array("gu", "gv", z.cast("long"))), "-"))
    return rows.select(F.explode(F.array_distinct(three)).alias("stream"), "u", "v", "gu", "gv", "pos")


def reservoirs(rows: DataFrame, trials: int, seed: int = 0, workers: int = 1, groups: int | None = None) -> DataFrame:
    """The streams with trial, worker and prio: a row for each reservoir that an edge comes to."""
    worker = F.col("stream") if groups else F.explode(F.array(*(F.lit(str(w)) for w in range(workers))))
    rows = rows.withColumn("worker", worker).withColumn("trial", F.explode(F.sequence(F.lit(0), F.lit(trials - 1))))
    return rows.withColumn("prio", _even(F.lit(seed), "trial", "worker", "u", "v"))


def _wedges(come: pd.DataFrame, size: int, m: int, slack: float, three: tuple | None) -> list[tuple]:
    """u, v, since, until of wedges that the reservoir held; [(-1, -1, 0, -1)] where an edge outside ``come`` could have entered."""
    come = come.sort_values(["pos", "u", "v"])
    ends, pos, prio = list(zip(come.u.tolist(), come.v.tolist(), strict=True)), come.pos.tolist(), come.prio.tolist()
    code = dict(zip(come.u.tolist(), come.gu.tolist(), strict=True)) | dict(zip(come.v.tolist(), come.gv.tolist(), strict=True))
    heap, near, of, out = [], {}, {}, []
    for i, ((u, v), p, r) in enumerate(zip(ends, pos, prio, strict=True)):
        if len(heap) < size or r < -heap[0][0]:
            if len(heap) == size:
                old = heapq.heappop(heap)[1]
                a, b = ends[old]
                del near[a][b], near[b][a]
                for k in of.pop(old):
                    out[k][3] = min(out[k][3], p)
            of[i] = []
            for x, y in ((u, v), (v, u)):
                for z, other in near.get(x, {}).items():
                    if three is None or tuple(sorted((code[x], code[y], code[z]))) == three:
                        of[i].append(len(out))
                        of[other].append(len(out))
                        out.append([min(y, z), max(y, z), p, 2.0])
            near.setdefault(u, {})[v] = i
            near.setdefault(v, {})[u] = i
            heapq.heappush(heap, (-r, i))
        after = pos[i + 1] if i + 1 < len(pos) else 1.0
        if slack * size / (m * max(after, 1e-300)) < (-heap[0][0] if len(heap) == size else 1.0):
            return [(-1, -1, 0.0, -1.0)]
    return [tuple(x) for x in out]


def _places(rows: DataFrame, at: dict[str, np.ndarray], streams: dict[int, list[str]]) -> dict[str, np.ndarray]:
    """How many edges of each stream come up to each position of ``at`` (ascending, by stream).  rows: kind, pos;
    streams: those that a kind of edge is in."""
    marks = {k: np.unique(np.concatenate([at[n] for n in names if n in at] or [np.zeros(0)])) for k, names in streams.items()}
    shared = rows.sparkSession.sparkContext.broadcast(marks)

    def run(batches):
        marks = shared.value
        held = {k: np.zeros(len(x) + 1, np.int64) for k, x in marks.items()}
        for batch in batches:
            kinds, pos = np.asarray(batch.column(0)), np.asarray(batch.column(1))
            for k, x in marks.items():
                if len(x):
                    held[k] += np.bincount(np.searchsorted(x, pos[kinds == k] if len(marks) > 1 else pos), minlength=len(held[k]))
        for k, n in held.items():
            some = np.flatnonzero(n)
            yield pa.RecordBatch.from_arrays([pa.array([k] * len(some), pa.int32()), pa.array(some), pa.array(n[some])], names=["kind", "bin", "n"])

    got = rows.select("kind", "pos").mapInArrow(run, "kind int, bin long, n long").groupBy("kind", "bin").agg(F.sum("n").alias("n")).toPandas()
    out = {n: np.zeros(len(x), np.int64) for n, x in at.items()}
    for k, x in marks.items():
        n, mine = np.zeros(len(x) + 1, np.int64), got[got.kind == k]
        n[mine.bin.to_numpy()] = mine.n.to_numpy()
        for name in streams[k]:
            if name in at:
                out[name] += np.cumsum(n)[np.searchsorted(x, at[name])]
    return out


def _kinds(groups: int | None) -> dict[int, list[str]]:
    """By the groups of an edge's ends (gu * groups + gv): the streams that it is in, as streams() has them."""
    if not groups:
        return {0: [""]}
    name = lambda *three: "-".join(map(str, sorted(three)))
    return {a * groups + b: sorted({name(a, b, z) for z in range(groups)}) for a in range(groups) for b in range(groups)}


def triangles(edges: DataFrame, size: int, trials: int = 4, seed: int = 0, workers: int = 1, groups: int | None = None, slack: float = 1.5, among: Callable[[DataFrame], DataFrame] | None = None, count: int | None = None) -> DataFrame:
    """trial, t_est, as baselines.reservoir_triangles (improved): a triangle weighs by the place of its last edge.

    Edges go on as candidates where their place times their priority is low enough; whether that left one out is
    checked reservoir by reservoir, and then ``slack`` doubles.  among: keeps the rows whose u, v are an edge, where that
    needs no pass over edges; count: of edges, where known."""
    spark, rows, kinds = edges.sparkSession, streams(edges, seed), _kinds(groups)
    side = lambda c: F.pmod(F.xxhash64(F.lit(seed), c), F.lit(groups))
    rows = rows.withColumn("kind", (side("u") * groups + side("v")).cast("int") if groups else F.lit(0))
    of = {0: count} if count is not None and not groups else {r[0]: r[1] for r in rows.groupBy("kind").count().collect()}
    m: dict[str, int] = {}
    for k, n in of.items():
        for name in kinds[k] if n else []:
            m[name] = m.get(name, 0) + n
    result = "trial int, t_est double"
    if not m:
        return spark.createDataFrame([(t, 0.0) for t in range(trials)], result)

    def low(slack: float) -> DataFrame:
        """The edges that may enter a reservoir of theirs, found before a row is made for each reservoir."""
        if groups:  # an edge is in as many streams as there are groups
            names = [F.coalesce(*(F.when(F.col("kind") == k, F.lit(x[i])) for k, x in kinds.items())) for i in range(groups)]
        else:
            names = [F.lit(str(w)) for w in range(workers)]
        first = [_even(F.lit(seed), F.lit(t), x, "u", "v") * (_per(x, m) if groups else F.lit(float(m[""]))) for t in range(trials) for x in names]
        few = rows.filter(F.col("pos") * (F.least(*first) if len(first) > 1 else first[0]) <= slack * size * (1 + 1e-9))
        if groups:
            few = streams(few.select("u", "v"), seed, groups)
        many = _per(F.col("stream"), m)
        return reservoirs(few, trials, seed, workers, groups).filter(F.col("pos") * F.col("prio") * many <= slack * size)

    def held(slack: float):
        def run(come: pd.DataFrame) -> pd.DataFrame:
            trial, worker, stream = come.trial.iloc[0], come.worker.iloc[0], come.stream.iloc[0]
            found = _wedges(come, size, m[stream], slack, tuple(map(int, worker.split("-"))) if groups else None)
            return pd.DataFrame([(trial, worker, *x) for x in found], columns=["trial", "worker", "u", "v", "since", "until"])

        return run

    while True:
        wedges = shared_table(low(slack).groupBy("trial", "worker").applyInPandas(held(slack), WEDGE), "reservoir-wedges")
        if wedges.filter("until < 0").isEmpty():
            break
        slack *= 2
    wedges = wedges.withColumn("stream", F.col("worker") if groups else F.lit(""))
    if among is not None:  # wedges whose ends are of these groups have the edge that closes them in the same stream
        closed = streams(among(wedges.select("u", "v").distinct()), seed).select("u", "v", "pos").join(wedges, ["u", "v"])
    else:
        if wedges.count() <= 2_000_000:  # else edges are shuffled
            wedges = F.broadcast(wedges)
        closed = rows.select("u", "v", "pos").join(wedges, ["u", "v"])
    closed = closed.filter("pos > since and pos <= until").groupBy("trial", "worker", "stream", "pos").count().toPandas()
    at = {k: np.unique(x.pos.to_numpy()) for k, x in closed.groupby("stream")}
    place = _places(rows, at, kinds) if at else {}
    total = {(t, w): 0.0 for t in range(trials) for w in (m if groups else map(str, range(workers)))}
    for (trial, worker, stream), x in closed.groupby(["trial", "worker", "stream"]):
        t = place[stream][np.searchsorted(at[stream], x.pos.to_numpy())].astype(float)
        total[int(trial), worker] += float((np.maximum(1.0, (t - 1) * (t - 2) / (size * (size - 1))) * x["count"].to_numpy()).sum())
    by = {t: [x for (trial, _), x in sorted(total.items()) if trial == t] for t in range(trials)}
    return spark.createDataFrame([(t, sum(x) / (1 if groups else len(x))) for t, x in by.items()], result)


def _per(stream: F.Column, m: dict[str, int]) -> F.Column:
    return F.coalesce(*(F.when(stream == name, F.lit(float(n))) for name, n in m.items()), F.lit(1.0))


def _sample_triangles(ends: list[tuple[int, int]]) -> int:
    near: dict[int, set[int]] = {}
    total = 0
    for u, v in ends:
        total += len(near.get(u, set()) & near.get(v, set()))
        near.setdefault(u, set()).add(v)
        near.setdefault(v, set()).add(u)
    return total


def dynamic_triangles(edges: DataFrame, size: int, trials: int = 4, seed: int = 0, slack: float = 2.0) -> DataFrame:
    """trial, t_est, as baselines.reservoir_triangles (dynamic): edges with ``deleted`` go after all have come.

    Then a deletion only leaves a gap, since no insertion follows to fill it: what is left of the ``size`` edges of
    lowest priority is the sample.  Edges above ``slack`` times the expected bound are left out only where enough are below."""
    m, live = edges.agg(F.count("*"), F.coalesce(F.sum((~F.col("deleted")).cast("long")), F.lit(0))).first()
    rows = edges.withColumn("trial", F.explode(F.sequence(F.lit(0), F.lit(trials - 1))))
    rows = rows.withColumn("prio", _even(F.lit(seed), "trial", "u", "v")).select("trial", "u", "v", "deleted", "prio")
    while True:
        low = shared_table(rows.filter(F.col("prio") <= slack * size / max(1, m)), "reservoir-low")
        held = [r[1] for r in low.groupBy("trial").count().collect()]
        if len(held) == trials and min(held) >= min(size, m) or slack * size >= m:
            break
        slack *= 2

    def run(come: pd.DataFrame) -> pd.DataFrame:
        left = come.sort_values(["prio", "u", "v"]).head(size)
        left = left[~left.deleted]
        s, t = len(left), float(_sample_triangles(list(zip(left.u.tolist(), left.v.tolist(), strict=True))))
        weight = live * (live - 1) * (live - 2) / (s * (s - 1) * (s - 2)) if live > s >= 3 else 1.0
        return pd.DataFrame({"trial": come.trial.iloc[:1], "t_est": [t * weight]})

    got = low.groupBy("trial").applyInPandas(run, "trial int, t_est double")
    return edges.sparkSession.range(trials).select(F.col("id").cast("int").alias("trial")).join(got, "trial", "left").select("trial", F.coalesce("t_est", F.lit(0.0)).alias("t_est"))
