"""Balls of a graph that links all members of a group, from the memberships alone.

A vertex's neighbours are the members of its groups, so a hop merges sketches into groups and those back into members.
Registers are those of the edges; the work grows with the memberships and not with the square of a group."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.spec import SketchSpec
from .balls import Balls, shared_table
from .packed import measure_packed, merge_packed, pack, unpack
from .vst import measure, merge, registers


def memberships(rows: DataFrame, group: str, member: str) -> DataFrame:
    """g, x: distinct members of groups that have two or more, groups numbered.

    Names may be long and mostly of one member: only those whose hash two members have are written and compared, and
    text of 32 bytes or more by its SHA-256."""
    text = dict(rows.dtypes)[group] == "string"
    rows = rows.select(F.col(group).alias("name"), F.col(member).cast("long").alias("x")).filter("name is not null and x is not null")
    rows = rows.withColumn("h", F.xxhash64("name"))
    ends = rows.groupBy("h").agg(F.min("x").alias("first"), F.max("x").alias("last"))
    met = shared_table(ends.filter("first < last").select("h"), "several")
    if met.count() <= 2_000_000:  # else rows are shuffled
        met = F.broadcast(met)
    rows = rows.join(met, "h").select("name", "x")
    if text:
        rows = rows.withColumn("name", F.when(F.octet_length("name") < 32, F.col("name").cast("binary")).otherwise(F.unhex(F.sha2("name", 256))))
    rows = shared_table(rows.distinct(), "members")
    several = rows.groupBy("name").agg(F.count("*").alias("n")).filter("n > 1")
    ids = shared_table(several.select("name", F.monotonically_increasing_id().alias("g")), "groups")
    return shared_table(rows.join(ids, "name").select("g", "x"), "memberships")


def _own(members: DataFrame, spec: SketchSpec) -> DataFrame:
    return registers(members.select("x").distinct().withColumn("me", F.col("x")), "x", F.col("me"), spec)


def _sent(members: DataFrame, rows: DataFrame) -> DataFrame:
    """x, j, rho: what members get from the registers (x, j, rho) of all members of their groups."""
    of_group = merge(members.join(rows, "x").select("g", "j", "rho"), ["g"])
    return merge(members.join(of_group, "g").select("x", "j", "rho"), ["x"])


def _sent_packed(members: DataFrame, layer: DataFrame, spec: SketchSpec) -> DataFrame:
    of_group = merge_packed(members.join(layer, "x").select(F.col("g").alias("x"), "mode", "regs"), spec)
    got = members.join(of_group.select(F.col("x").alias("g"), "mode", "regs"), "g").select("x", "mode", "regs")
    return merge_packed(got, spec)


def ball_sizes(members: DataFrame, spec: SketchSpec, k: int, how: str = "beta", active: str = "all") -> Balls:
    """Sizes of closed balls for t = 1..k.  members: g, x as memberships() gives them.

    active: ``all`` keeps one binary a vertex; ``changed`` keeps a row a register and lets only registers that grew
    in the last hop travel.  The result is the same."""
    if k < 1:
        raise ValueError("k must be 1 or more")
    layer, local, layers = _own(members, spec), None, {}
    layer = delta = shared_table(layer if active == "changed" else pack(layer, spec), "layer")
    for t in range(1, k + 1):
        if active == "changed":
            fresh = shared_table(merge(layer.unionByName(_sent(members, delta)), ["x"]), "layer")
            delta = shared_table(fresh.join(layer, ["x", "j", "rho"], "left_anti"), "delta") if t < k else delta
            sized, layers[t] = measure(fresh, ["x"], spec, how), fresh
        else:
            fresh = shared_table(_sent_packed(members, layer, spec), "layer")
            sized, layers[t] = measure_packed(fresh, spec, how), unpack(fresh, spec)
        layer = fresh
        sized = sized.select("x", F.lit(t).alias("t"), "n_est")
        local = sized if local is None else local.unionByName(sized)
    return Balls(local, layers, spec, k)


def _from_others(members: DataFrame, rows: DataFrame) -> DataFrame:
    """x, j, rho: as _sent, but nothing that only x itself brought.  The two highest of a group's members suffice."""
    rows = members.join(rows, "x").select("g", "x", "j", "rho")
    first = rows.groupBy("g", "j").agg(F.max(F.struct("rho", "x")).alias("top"))
    first = shared_table(first.select("g", "j", F.col("top.rho").alias("most"), F.col("top.x").alias("holder")), "top")
    second = rows.join(first, ["g", "j"]).filter("x <> holder").groupBy("g", "j").agg(F.max("rho").alias("next"))
    top = shared_table(first.join(second, ["g", "j"], "left"), "top-two")
    got = members.join(top, "g").select("x", "j", F.when(F.col("x") == F.col("holder"), F.col("next")).otherwise(F.col("most")).alias("rho"))
    return merge(got.filter("rho is not null"), ["x"])


def two_hop(members: DataFrame, spec: SketchSpec, how: str = "beta") -> DataFrame:
    """x, n2: union of the neighbours' open sketches only, as balls.two_hop."""
    table = shared_table(_from_others(members, _own(members, spec)), "open")
    return measure(_from_others(members, table), ["x"], spec, how, "n2")
