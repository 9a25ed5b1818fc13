"""Earlier methods to compare with: neighbourhood functions, sampling estimators, other cardinality sketches."""

from __future__ import annotations

import pandas as pd
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..functions.hashing import hash_word, index_of, rank_of, uniform
from ..functions.spec import SketchSpec
from ..sources.build import arcs as both_ways
from .balls import shared_table
from .exact import degrees, triangles
from .vst import Vst

PHI = 0.77351


def lowest_unset(bits) -> F.Column:
    """How many low bits are set before the first that is not."""
    return F.bit_count(bits.bitwiseAND(F.bitwise_not(bits + 1)))


# neighbourhood functions

def balls_bitmap(edges: DataFrame, k: int, maps: int = 16, seed: int = 0) -> DataFrame:
    """x, t, n_est with ``maps`` bitmaps a vertex, OR-ed along edges; every vertex sets one bit in each map."""
    arcs, spec = shared_table(both_ways(edges).distinct(), "arcs"), SketchSpec(p=4, hash="portable", seed=seed)
    own = arcs.select("x").distinct().select("x", F.explode(F.sequence(F.lit(0), F.lit(maps - 1))).alias("i"))
    word = hash_word(F.concat(F.col("i").cast("string"), F.lit("/"), F.col("x").cast("string")), spec)
    layer, out = own.select("x", "i", F.lit(1).cast("long").alias("one"), rank_of(word, spec).alias("rho")).select("x", "i", F.expr("shiftleft(one, rho - 1)").alias("bits")), None
    for t in range(1, k + 1):
        sent = layer.unionByName(arcs.join(layer, "x").select(F.col("y").alias("x"), "i", "bits"))
        layer = sent.groupBy("x", "i").agg(F.bit_or("bits").alias("bits"))
        if t < k:
            layer = shared_table(layer, "bitmaps")
        sized = layer.groupBy("x").agg((F.pow(F.lit(2.0), F.avg(lowest_unset(F.col("bits")).cast("double"))) / PHI).alias("n_est")).withColumn("t", F.lit(t))
        out = sized if out is None else out.unionByName(sized)
    return out.select("x", "t", "n_est")


def balls_global_only(edges: DataFrame, vst: Vst, k: int) -> DataFrame:
    """t, n_est: the sum over vertices, two layers at a time and none kept."""
    from .balls import ball_sizes

    return ball_sizes(edges, vst, k, keep_layers=False).total


# triangles by min-wise agreement

def minwise_triangles(edges: DataFrame, seeds: int = 16) -> DataFrame:
    """u, v, t_est: share of equal minima over ``seeds`` orders of the neighbours gives a Jaccard coefficient."""
    arcs, d = both_ways(edges), degrees(edges)
    mins = arcs.groupBy("x").agg(*(F.min(hash_word(F.col("y"), SketchSpec(p=4, hash="portable", seed=s))).alias(f"m{s}") for s in range(seeds)))
    mins = mins.select("x", F.array(*(f"m{s}" for s in range(seeds))).alias("m")).join(d, "x")
    one, two = (mins.select(F.col("x").alias(c), F.col("m").alias(f"m{c}"), F.col("d").alias(f"d{c}")) for c in "uv")
    same = F.aggregate(F.zip_with("mu", "mv", lambda a, b: (a == b).cast("int")), F.lit(0), lambda s, x: s + x)
    j = same / F.lit(float(seeds))
    return edges.join(one, "u").join(two, "v").select("u", "v", (j / (1 + j) * (F.col("du") + F.col("dv"))).alias("t_est"))


# triangles by edge sampling

def edge_key() -> F.Column:
    return F.concat(F.col("u").cast("string"), F.lit("-"), F.col("v").cast("string"))


def sampled_triangles(edges: DataFrame, prob: float, seed: int = 1, mode: str = "final") -> DataFrame:
    """t_est from edges kept with a fixed probability by their hash.

    final: triangles whose edges are all kept.  arrival: edges come in the order of another hash, and the
    last edge of a triangle need not be kept."""
    kept = edges.filter(uniform(edge_key(), seed) < prob)
    if mode == "final":
        return triangles(kept).agg((F.count("*") / prob**3).alias("t_est"))
    rows = edges.select("u", "v", uniform(edge_key(), seed + 1000).alias("pos"), (uniform(edge_key(), seed) < prob).alias("kept"))
    early = both_ways(rows.filter("kept").select("u", "v")).join(_positions(rows), ["x", "y"])
    one, two = (early.select(F.col("x").alias(c), F.col("y").alias("z"), F.col("pos").alias(f"p{c}")) for c in "uv")
    closed = rows.join(one, "u").join(two, ["v", "z"]).filter((F.col("pu") < F.col("pos")) & (F.col("pv") < F.col("pos")))
    return closed.agg((F.count("*") / prob**2).alias("t_est"))


def _positions(rows: DataFrame) -> DataFrame:
    both = F.array(F.struct(F.col("u").alias("x"), F.col("v").alias("y")), F.struct(F.col("v").alias("x"), F.col("u").alias("y")))
    return rows.select(F.inline(both), "pos")


def reservoir_base(edges: DataFrame, size: int, seed: int = 2) -> DataFrame:
    """t_est from the ``size`` edges of lowest hash, a uniform sample without replacement."""
    m = edges.count()
    sample = shared_table(edges.withColumn("p", uniform(edge_key(), seed)).orderBy("p", "u", "v").limit(size).select("u", "v"), "sample")
    weight = max(1.0, m * (m - 1) * (m - 2) / (size * (size - 1) * (size - 2))) if m > size else 1.0
    return triangles(sample).agg((F.count("*") * weight).alias("t_est"))


def _run_reservoir(edges: list[tuple[int, int, bool]], size: int, seed: int, variant: str, owner: tuple | None = None) -> float:
    """One pass over (u, v, insert?) in order.  improved: weighs a triangle when its last edge comes.
    dynamic: random pairing; a deletion leaves a gap that a later insertion may fill, and the count is over the sample.
    owner: groups of vertices, and the three groups whose triangles this reservoir counts."""
    import random

    rng, sample, near, total = random.Random(seed), [], {}, 0.0
    place: dict[tuple[int, int], int] = {}
    t = live = inside = outside = 0

    def put(u, v):
        place[u, v] = len(sample)
        sample.append((u, v))
        near.setdefault(u, set()).add(v)
        near.setdefault(v, set()).add(u)

    def drop(u, v):
        i, last = place.pop((u, v)), sample.pop()
        if last != (u, v):
            sample[i] = last
            place[last] = i
        near[u].discard(v)
        near[v].discard(u)

    def common(u, v):
        both = near.get(u, set()) & near.get(v, set())
        if owner is None:
            return len(both)
        code, three = owner
        return sum(tuple(sorted((code[u], code[v], code[z]))) == three for z in both)

    for u, v, insert in edges:
        if variant == "improved":
            t += 1
            total += max(1.0, (t - 1) * (t - 2) / (size * (size - 1))) * common(u, v)
            if t <= size:
                put(u, v)
            elif rng.random() < size / t:
                drop(*rng.choice(sample))
                put(u, v)
        elif insert:
            live += 1
            if inside + outside == 0:
                if len(sample) < size:
                    total += common(u, v)
                    put(u, v)
                elif rng.random() < size / live:
                    old = rng.choice(sample)
                    drop(*old)
                    total -= common(*old)
                    total += common(u, v)
                    put(u, v)
            elif rng.random() < inside / (inside + outside):
                inside -= 1
                total += common(u, v)
                put(u, v)
            else:
                outside -= 1
        else:
            live -= 1
            if (u, v) in place:
                drop(u, v)
                total -= common(u, v)
                inside += 1
            else:
                outside += 1
    if variant == "dynamic":
        s, m = len(sample), live
        return total * (m * (m - 1) * (m - 2) / (s * (s - 1) * (s - 2)) if m > s >= 3 else 1.0)
    return total


def reservoir_triangles(edges: DataFrame, size: int, trials: int = 4, seed: int = 0, variant: str = "improved", workers: int = 1, groups: int | None = None) -> DataFrame:
    """trial, t_est by sequential reservoirs, one group a trial (and worker): kept as comparison, not for scale.

    workers: independent reservoirs over the whole stream, averaged.  groups: a worker for each three groups of
    vertices gets the edges inside them and counts the triangles over exactly these, so each triangle has one.
    The stream's order is a hash of the edge.  dynamic: a column ``deleted`` marks edges removed at the end."""
    rows = edges.withColumn("pos", uniform(edge_key(), seed + 1000))
    if "deleted" not in edges.columns:
        rows = rows.withColumn("deleted", F.lit(False))
    side = lambda c: F.pmod(F.xxhash64(F.lit(seed), c), F.lit(groups or 1))
    rows = rows.withColumn("gu", side("u")).withColumn("gv", side("v"))
    if groups:
        a, b = F.col("gu"), F.col("gv")
        # a worker for each multiset of three groups, the only one to count triangles over just these groups
        rows = rows.withColumn("a", F.least(a, b)).withColumn("b", F.greatest(a, b)).withColumn("third", F.explode(F.sequence(F.lit(0), F.lit(groups - 1))))
        three = F.sort_array(F.array(F.col("a"), F.col("b"), F.col("third").cast("long")))
        rows = rows.withColumn("worker", F.array_join(three, "-")).drop("third", "a", "b").distinct()
    else:
        rows = rows.withColumn("worker", F.explode(F.sequence(F.lit(0), F.lit(workers - 1)))).withColumn("worker", F.col("worker").cast("string"))
    rows = rows.withColumn("trial", F.explode(F.sequence(F.lit(0), F.lit(trials - 1))))

    def run(pdf: pd.DataFrame) -> pd.DataFrame:
        pdf = pdf.sort_values(["pos", "u", "v"])
        stream = [(int(u), int(v), True) for u, v in zip(pdf.u, pdf.v, strict=True)]
        gone = pdf[pdf.deleted]
        stream += [(int(u), int(v), False) for u, v in zip(gone.u, gone.v, strict=True)]
        trial, worker = int(pdf.trial.iloc[0]), str(pdf.worker.iloc[0])
        import zlib

        owner = None
        if groups:
            code = {int(x): int(g) for c, gc in (("u", "gu"), ("v", "gv")) for x, g in zip(pdf[c], pdf[gc], strict=True)}
            owner = (code, tuple(sorted(map(int, worker.split("-")))))
        t = _run_reservoir(stream, size, seed * 7919 + trial * 104729 + zlib.crc32(worker.encode()), variant, owner)
        return pd.DataFrame({"trial": [trial], "worker": [worker], "t_est": [t]})

    rows = rows.select("trial", "worker", "u", "v", "pos", "deleted", "gu", "gv")
    got = rows.groupBy("trial", "worker").applyInPandas(run, "trial int, worker string, t_est double")
    if not groups:
        return got.groupBy("trial").agg(F.avg("t_est").alias("t_est"))
    return got.groupBy("trial").agg(F.sum("t_est").alias("t_est"))


def weighted_sample_triangles(edges: DataFrame, low: float, high: float, trials: int = 4, seed: int = 0) -> DataFrame:
    """trial, t_est: an edge that touches the sample is kept with probability ``high``, another with ``low``;
    a triangle counts, when its last edge comes, as the inverse of its other edges' probabilities."""
    rows = edges.withColumn("pos", uniform(edge_key(), seed + 1000)).withColumn("trial", F.explode(F.sequence(F.lit(0), F.lit(trials - 1))))

    def run(pdf: pd.DataFrame) -> pd.DataFrame:
        import random

        pdf = pdf.sort_values(["pos", "u", "v"])
        trial = int(pdf.trial.iloc[0])
        rng, near, total = random.Random(seed * 7919 + trial), {}, 0.0
        for u, v in zip(pdf.u, pdf.v, strict=True):
            a, b = near.get(u, {}), near.get(v, {})
            total += sum(1 / (a[z] * b[z]) for z in a.keys() & b.keys())
            p = high if a or b else low
            if rng.random() < p:
                near.setdefault(u, {})[v] = p
                near.setdefault(v, {})[u] = p
        return pd.DataFrame({"trial": [trial], "t_est": [total]})

    return rows.select("trial", "u", "v", "pos").groupBy("trial").applyInPandas(run, "trial int, t_est double")


def drawn_wedges(degree: DataFrame, samples: int, seed: int = 3, blocks: int = 64) -> DataFrame:
    """s, all, x, i, j: wedges drawn evenly (a centre by its number of wedges), by the places i < j of their ends among
    the neighbours of x.  degree: x, d.

    Centres are laid out along a line by running sums, in ``blocks`` blocks so no task orders all of them."""
    d = degree.filter("d > 1").select("x", "d", (F.col("d") * (F.col("d") - 1) / 2).cast("long").alias("w"), F.pmod("x", F.lit(blocks)).alias("block"))
    d = shared_table(d, "degrees")
    sums = d.groupBy("block").agg(F.sum("w").alias("bw"))
    line = sums.select("block", "bw", F.coalesce(F.sum("bw").over(Window.partitionBy(F.lit(0)).orderBy("block").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0)).alias("b0"))
    inside = F.sum("w").over(Window.partitionBy("block").orderBy("x").rowsBetween(Window.unboundedPreceding, -1))
    spans = d.withColumn("inner", F.coalesce(inside, F.lit(0))).join(F.broadcast(line), "block").select("x", "d", "block", "inner", "w")
    every = sums.agg(F.sum("bw").alias("all"))
    draws = degree.sparkSession.range(samples).crossJoin(F.broadcast(every)).select(F.col("id").alias("s"), F.floor(uniform(F.col("id"), seed) * F.col("all")).cast("long").alias("at"), "all")
    draws = draws.join(F.broadcast(line), (F.col("at") >= F.col("b0")) & (F.col("at") < F.col("b0") + F.col("bw"))).select("s", "all", "block", (F.col("at") - F.col("b0")).alias("rest"))
    picked = draws.join(spans, "block").filter((F.col("rest") >= F.col("inner")) & (F.col("rest") < F.col("inner") + F.col("w"))).select("s", "all", "x", "d", (F.col("rest") - F.col("inner")).alias("n"))
    # the n-th pair i < j of neighbours in id order: j is the largest with j (j - 1) / 2 <= n
    j = F.floor((1 + F.sqrt(1.0 + 8.0 * F.col("n"))) / 2).cast("long")
    return shared_table(picked.withColumn("j", j).withColumn("i", F.col("n") - (F.col("j") * (F.col("j") - 1) / 2).cast("long")), "picked")


def wedge_triangles(edges: DataFrame, samples: int, seed: int = 3, blocks: int = 64) -> DataFrame:
    """t_est: wedges drawn evenly, the closed share times all wedges over 3."""
    picked = drawn_wedges(degrees(edges), samples, seed, blocks)
    # no more rows than samples are broadcast
    place = both_ways(edges).join(F.broadcast(picked.select("x").distinct()), "x", "left_semi").withColumn("r", (F.row_number().over(Window.partitionBy("x").orderBy("y")) - 1).cast("long"))
    a, b = place.select("x", F.col("r").alias("i"), F.col("y").alias("a")), place.select("x", F.col("r").alias("j"), F.col("y").alias("b"))
    wedges = picked.join(a, ["x", "i"]).join(b, ["x", "j"]).select("s", "all", F.least("a", "b").alias("u"), F.greatest("a", "b").alias("v"))
    wedges = shared_table(wedges, "wedges")
    closed = edges.join(F.broadcast(wedges.select("u", "v").distinct()), ["u", "v"], "left_semi").select("u", "v", F.lit(1).alias("hit"))
    hit = wedges.join(closed, ["u", "v"], "left")
    return hit.agg((F.sum(F.coalesce("hit", F.lit(0))) / F.count("*") * F.max("all") / 3).alias("t_est"))


# other sketches of a set

def pcsa(rows: DataFrame, key: str, element: F.Column, spec: SketchSpec) -> DataFrame:
    """key, n_est: a bitmap of ranks for each of 2**p buckets, mean position of the first gap."""
    w = hash_word(element, spec)
    bits = rows.select(key, index_of(w, spec).alias("j"), rank_of(w, spec).alias("rho")).groupBy(key, "j").agg(F.bit_or(F.expr("shiftleft(1L, rho - 1)")).alias("bits"))
    return bits.groupBy(key).agg((F.lit(spec.r / PHI) * F.pow(F.lit(2.0), F.sum(lowest_unset(F.col("bits")).cast("double")) / float(spec.r))).alias("n_est"))


def kmv(rows: DataFrame, key: str, element: F.Column, k: int, seed: int = 0) -> DataFrame:
    """key, n_est from the k smallest hash values (fewer elements are counted)."""
    h = rows.select(key, uniform(element, seed).alias("h")).distinct()
    nth = F.row_number().over(Window.partitionBy(key).orderBy("h"))
    low = h.withColumn("nth", nth).filter(F.col("nth") <= k)
    return low.groupBy(key).agg(F.when(F.count("*") < k, F.count("*").cast("double")).otherwise(F.lit(k - 1.0) / F.max("h")).alias("n_est"))


def multires_bitmap(rows: DataFrame, key: str, element: F.Column, levels: int = 8, bits: int = 64, spec: SketchSpec = SketchSpec(p=6, hash="portable"), most: float = 0.9) -> DataFrame:
    """key, n_est: an element goes to level min(rank, levels) and one of ``bits`` places; linear counts of the
    first level that is not too full and those above it, scaled by its sampling rate."""
    w = hash_word(element, spec)
    cells = rows.select(key, F.least(rank_of(w, spec), F.lit(levels)).alias("level"), F.pmod(index_of(w, spec), F.lit(bits)).alias("bit")).distinct()
    fill = cells.groupBy(key, "level").agg(F.count("*").alias("n"))
    linear = F.lit(-float(bits)) * F.log((bits - F.least(F.col("n"), F.lit(bits - 1)).cast("double")) / float(bits))
    full = fill.filter(F.col("n") > most * bits).groupBy(key).agg(F.least(F.max("level") + 1, F.lit(levels)).alias("base"))
    rows = fill.join(full, key, "left").withColumn("base", F.coalesce("base", F.lit(1))).filter(F.col("level") >= F.col("base"))
    return rows.groupBy(key).agg((F.sum(linear) * F.pow(F.lit(2.0), F.max("base") - 1)).alias("n_est"))
