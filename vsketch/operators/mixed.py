"""Graphs that link all members of a group: large groups by types of members, small ones by plain edges.

A type is a set of large groups that some members have in common (all the large groups they are in); types that share a
group are linked, and so are all their members.  What only small groups link stays as edges.  Groups count as large from
``least`` members on; that doubles until there are at most ``most`` types, whose table the driver holds.  Every edge is
in one of the two parts, and triangles are counted by how many of their edges are plain."""

from __future__ import annotations

from dataclasses import dataclass
from functools import cached_property

import numpy as np
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..sources.build import arcs as both_ways
from ..sources.build import co_occurrence
from . import classes, exact
from .balls import shared_table
from .baselines import drawn_wedges


@dataclass
class Mixed:
    """table: c, w, part, xs as classes() gives it, for large groups; pairs: c, c2, linked types, c < c2; light: u, v,
    cu, cv, edges that no large group has, with their ends' types (null where in no large group)."""

    table: DataFrame
    pairs: DataFrame
    light: DataFrame

    @cached_property
    def types(self) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """Ids ascending, members, and which types are linked."""
        got = self.table.filter("part = 0").select("c", "w").orderBy("c").toArrow()
        ids, w = (np.asarray(got.column(n)).astype(np.int64) for n in ("c", "w"))
        two = self.pairs.toArrow()
        a, b = (np.searchsorted(ids, np.asarray(two.column(n)).astype(np.int64)) for n in ("c", "c2"))
        linked = np.zeros((len(ids), len(ids)), bool)
        linked[a, b] = linked[b, a] = True
        return ids, w, linked

    @cached_property
    def common(self) -> np.ndarray:
        """Members of types that are linked to both of two."""
        _, w, linked = self.types
        out, scaled = np.empty(linked.shape, np.int64), linked * w.astype(float)[:, None]
        for a in range(0, len(w), 512):
            out[a : a + 512] = np.rint(linked[a : a + 512].astype(float) @ scaled)
        return out

    @cached_property
    def size(self) -> int:
        """How many edges."""
        _, w, linked = self.types
        return int((w * (linked @ w)).sum() + (w * (w - 1)).sum()) // 2 + self.light.count()

    def edges(self) -> DataFrame:
        """u, v: every edge once, u < v.  What is dealt to tasks are pairs of parts of up to 256 members."""
        side = lambda c, n: self.table.select(F.col("c").alias(c), F.col("part").alias(n))
        one, two = side("c", "i"), side("c2", "j")
        across = self.pairs.join(one, "c").join(two, "c2").select("c", "i", "c2", "j")
        work = across.unionByName(one.join(two, F.col("c") == F.col("c2")).filter("i <= j").select("c", "i", "c2", "j"))
        tasks = int(min(1000, max(12, self.size // 8_000_000)))
        work = work.repartition(tasks)
        lists = self.table.select("c", "part", "xs")
        if lists.agg(F.coalesce(F.sum(F.size("xs")), F.lit(0))).first()[0] <= 2_000_000:  # else lists are shuffled
            lists = F.broadcast(lists)
        both = work.join(lists.select("c", F.col("part").alias("i"), F.col("xs").alias("a")), ["c", "i"])
        both = both.join(lists.select(F.col("c").alias("c2"), F.col("part").alias("j"), F.col("xs").alias("b")), ["c2", "j"])
        both = both.select("a", "b", ((F.col("c") == F.col("c2")) & (F.col("i") == F.col("j"))).alias("same"))
        both = both.select(F.explode("a").alias("p"), "b", "same").select("p", F.explode("b").alias("q"), "same")
        return both.filter("not same or p < q").select(F.least("p", "q").alias("u"), F.greatest("p", "q").alias("v")).unionByName(self.light.select("u", "v"))

    def of(self) -> DataFrame:
        """x, c: the types of members."""
        return self.table.select(F.explode("xs").alias("x"), "c")

    def among(self, rows: DataFrame) -> DataFrame:
        """The rows (u < v and others) that are edges."""
        names = rows.columns
        for n in "uv":
            rows = rows.join(self.of().select(F.col("x").alias(n), F.col("c").alias(f"c{n}")), n, "left")
        rows = shared_table(rows, "pairs-asked")
        linked = rows.withColumn("c", F.least("cu", "cv")).withColumn("c2", F.greatest("cu", "cv")).filter("cu <> cv").join(self.pairs, ["c", "c2"])
        plain = rows.join(self.light.select("u", "v"), ["u", "v"])
        return rows.filter("cu = cv").select(names).unionByName(linked.select(names)).unionByName(plain.select(names))

    def _sum(self, rows: DataFrame, cells: np.ndarray) -> int:
        """Sum of n times the cell of two types.  rows: a, b, n, a row for each two types."""
        got, (ids, _, _) = rows.toArrow(), self.types
        a, b, n = (np.asarray(got.column(c)).astype(np.int64) for c in ("a", "b", "n"))
        return sum((cells[np.searchsorted(ids, a), np.searchsorted(ids, b)] * n).tolist())

    def triangles(self) -> int:
        _, w, linked = self.types
        three = [int(x) for x in w]
        total = sum(x * (x - 1) * (x - 2) // 6 for x in three)  # in one type
        total += sum(x * int((w[on] * (x + w[on] - 2)).sum()) for x, on in zip(three, np.triu(linked), strict=True)) // 2  # in two
        total += sum(x * int((w[on] * row[on]).sum()) for x, on, row in zip(three, np.triu(linked), self.common, strict=True)) // 3
        typed = self.light.filter("cu is not null and cv is not null").groupBy(F.col("cu").alias("a"), F.col("cv").alias("b")).agg(F.count("*").alias("n"))
        total += self._sum(typed, self.common)
        both = F.array(F.struct(F.col("u").alias("z"), F.col("v").alias("x"), F.col("cv").alias("c")), F.struct(F.col("v").alias("z"), F.col("u").alias("x"), F.col("cu").alias("c")))
        ends = self.light.select(F.inline(both)).filter("c is not null")
        one, two = ends.select("z", F.col("x").alias("p"), F.col("c").alias("a")), ends.select("z", F.col("x").alias("q"), F.col("c").alias("b"))
        wedges = one.join(two, "z").filter("p < q").groupBy("a", "b").agg(F.count("*").alias("n"))
        total += self._sum(wedges, linked | np.eye(len(w), dtype=bool))
        return total + exact.triangles(self.light.select("u", "v")).count()

    def global_triangles(self) -> DataFrame:
        return self.light.sparkSession.createDataFrame([(self.triangles(),)], "t long")

    def degrees(self) -> DataFrame:
        """x, d, c (or null) and h: neighbours, and those by large groups."""
        ids, w, linked = self.types
        spark = self.light.sparkSession
        reach = spark.createDataFrame([(int(c), int(n)) for c, n in zip(ids, linked @ w + w - 1, strict=True)], "c long, h long")
        plain = both_ways(self.light).groupBy("x").agg(F.count("*").alias("p"))
        rows = self.of().join(F.broadcast(reach), "c").join(plain, "x", "full")
        rows = rows.select("x", "c", F.coalesce("h", F.lit(0)).alias("h"), F.coalesce("p", F.lit(0)).alias("p"))
        return rows.select("x", (F.col("h") + F.col("p")).alias("d"), "c", "h").filter("d > 0")

    def neighbours(self, rows: DataFrame) -> DataFrame:
        """rows with y, the k-th neighbour of x (from 0).  rows: x, k, others; few.

        The order of neighbours: members of linked types, type by type, of the own type, then those by plain edges."""
        names, (ids, w, linked) = rows.columns, self.types
        spark = rows.sparkSession
        places = self.table.select("c", "part", F.posexplode("xs").alias("at", "x")).select("x", "c", (F.col("part") * 256 + F.col("at")).cast("long").alias("place"))
        asked = rows.withColumn("n", F.monotonically_increasing_id()).join(F.broadcast(rows.select("x").distinct()).join(places, "x").withColumnRenamed("c", "own"), "x", "left")
        asked = shared_table(asked.join(self.degrees().select("x", "h"), "x"), "asked")
        got = asked.filter("k < h").select("n", "own", "place", "k").toArrow()
        n, own, place, k = (np.asarray(got.column(c)).astype(np.int64) for c in ("n", "own", "place", "k"))
        found = []
        for row, c, p, at in zip(n.tolist(), np.searchsorted(ids, own).tolist(), place.tolist(), k.tolist(), strict=True):
            to = np.r_[np.flatnonzero(linked[c]), c]
            ends = np.cumsum(np.r_[w[to[:-1]], w[c] - 1])
            which = int(np.searchsorted(ends, at, "right"))
            inner = at - (int(ends[which - 1]) if which else 0)
            found.append((row, int(ids[to[which]]), inner + int(to[which] == c and inner >= p)))
        seats = spark.createDataFrame(found, "n long, c long, seat long").withColumn("part", F.floor(F.col("seat") / 256).cast("int"))
        typed = self.table.select("c", "part", "xs").join(F.broadcast(seats), ["c", "part"]).select("n", F.col("xs")[(F.col("seat") % 256).cast("int")].alias("y"))
        arcs = both_ways(self.light).join(F.broadcast(asked.filter("k >= h").select("x").distinct()), "x")
        arcs = arcs.withColumn("rest", (F.row_number().over(Window.partitionBy("x").orderBy("y")) - 1).cast("long"))
        plain = asked.filter("k >= h").withColumn("rest", F.col("k") - F.col("h")).join(arcs, ["x", "rest"]).select("n", "y")
        return asked.join(typed.unionByName(plain), "n").select(*names, "y")

    def wedge_triangles(self, samples: int, seed: int = 3) -> DataFrame:
        """t_est as baselines.wedge_triangles, without edges: ends are found by their places among the neighbours."""
        picked = drawn_wedges(self.degrees().select("x", "d"), samples, seed)
        ends = self.neighbours(picked.select("s", "all", "x", F.explode(F.array("i", "j")).alias("k")))
        wedges = shared_table(ends.groupBy("s", "all").agg(F.min("y").alias("u"), F.max("y").alias("v")), "wedges")
        closed = self.among(wedges).agg(F.count("*").alias("hit"))
        return wedges.agg(F.count("*").alias("n"), F.max("all").alias("all")).crossJoin(closed).select((F.col("hit") / F.col("n") * F.col("all") / 3).alias("t_est"))


def mixed(members: DataFrame, least: int = 64, most: int = 4096) -> Mixed:
    """members: g, x, as groups.memberships() gives them."""
    sizes = shared_table(members.groupBy("g").agg(F.count("*").alias("n")), "sizes")
    while True:
        large = members.join(sizes.filter(F.col("n") >= least).select("g"), "g")
        if large.groupBy("x").agg(F.sort_array(F.collect_set("g")).alias("gs")).select("gs").distinct().count() <= most:
            break
        least *= 2
    table, pairs = classes.classes(large)
    table = shared_table(table, "types")
    small = members.join(sizes.filter(F.col("n") < least).select("g"), "g")
    light = co_occurrence(small, "g", "x")
    of = table.select(F.explode("xs").alias("x"), "c")
    for n in "uv":
        light = light.join(of.select(F.col("x").alias(n), F.col("c").alias(f"c{n}")), n, "left")
    light = light.filter("cu is null or cv is null or cu <> cv").withColumn("c", F.least("cu", "cv")).withColumn("c2", F.greatest("cu", "cv"))
    light = light.join(F.broadcast(pairs) if pairs.count() <= 500_000 else pairs, ["c", "c2"], "left_anti")
    return Mixed(table, pairs, shared_table(light.select("u", "v", "cu", "cv"), "light"))
