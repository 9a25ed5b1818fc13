"""Edges (u < v, distinct) and arcs (both directions) from tables."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window


def canonical(edges: DataFrame) -> DataFrame:
    """Undirected simple edges: no loops, no repeats, u < v; rows with a null end go."""
    ends = edges.select(F.col("u").cast("long").alias("u"), F.col("v").cast("long").alias("v")).filter("u <> v")
    return ends.select(F.least("u", "v").alias("u"), F.greatest("u", "v").alias("v")).distinct()


def arcs(edges: DataFrame) -> DataFrame:
    """x, y for both directions, in one scan.  Loops and null ends go; repeats stay (sketches ignore them)."""
    both = F.array(F.struct(F.col("u").alias("x"), F.col("v").alias("y")), F.struct(F.col("v").alias("x"), F.col("u").alias("y")))
    return edges.filter("u <> v").select(F.inline(both))


def co_occurrence(rows: DataFrame, group: str, member: str, block: int | None = None) -> DataFrame:
    """Pairs of distinct members of a group.

    block: groups may be large; each is dealt into blocks of about so many members, and every pair of blocks is
    joined on its own, so that no task holds all pairs of a group.  The pairs are the same."""
    rows = rows.select(F.col(group).alias("g"), F.col(member).cast("long").alias("m")).filter("g is not null and m is not null").distinct()
    if block is None:
        a, b = rows.select("g", F.col("m").alias("u")), rows.select("g", F.col("m").alias("v"))
        return a.join(b, "g").filter("u < v").select("u", "v").distinct()
    sizes = rows.groupBy("g").agg(F.count("*").alias("n")).filter("n > 1").select("g", F.ceil(F.col("n") / block).cast("int").alias("k"))
    rows = rows.join(sizes, "g").select("g", "m", "k", F.pmod(F.xxhash64("m"), F.col("k")).cast("int").alias("s"))
    a = rows.select("g", F.col("m").alias("a"), F.col("s").alias("i"), F.explode(F.sequence("s", F.col("k") - 1)).alias("j"))
    b = rows.select("g", F.col("m").alias("b"), F.col("s").alias("j"), F.explode(F.sequence(F.lit(0), "s")).alias("i"))
    both = a.join(b, ["g", "i", "j"]).filter("i < j or a < b")
    return both.select(F.least("a", "b").alias("u"), F.greatest("a", "b").alias("v")).distinct()


def bipartite(rows: DataFrame, left: Column, right: Column, kinds: int = 2, kind: tuple[int, int] = (0, 1)) -> DataFrame:
    """Edges between two kinds of vertices that share one id space: key * kinds + kind."""
    pair = rows.select((left.cast("long") * kinds + kind[0]).alias("u"), (right.cast("long") * kinds + kind[1]).alias("v"))
    return canonical(pair)


def proximity(rows: DataFrame, ts: str, who: str, seconds: int) -> DataFrame:
    """Pairs of different ids with two rows under ``seconds`` apart: an equi-join of time cells, own and next."""
    at = F.unix_micros(F.col(ts).cast("timestamp"))
    cell = F.floor(at / F.lit(seconds * 1_000_000)).cast("long")
    rows = rows.select(at.alias("t"), F.col(who).cast("long").alias("m"), cell.alias("cell")).filter("t is not null and m is not null")
    a = rows.select("cell", F.col("t").alias("ta"), F.col("m").alias("u"))
    b = rows.select(F.explode(F.array("cell", F.col("cell") - 1)).alias("cell"), F.col("t").alias("tb"), F.col("m").alias("v"))
    near = a.join(b, "cell").filter((F.abs(F.col("ta") - F.col("tb")) < seconds * 1_000_000) & (F.col("u") != F.col("v")))
    return canonical(near.select("u", "v"))


def successive(rows: DataFrame, who: Column, order: list[str], by: list[str] | None = None) -> DataFrame:
    """An edge from each row's id to the next one's, within ``by``.  Without ``by`` the order is over all rows:
    then one task sorts them, so give a key at scale."""
    window = (Window.partitionBy(*by) if by else Window.partitionBy(F.lit(0))).orderBy(*order)
    return canonical(rows.select(who.alias("u"), F.lead(who).over(window).alias("v")))


def similarity(rows: DataFrame, key: str, vector: str, least: float, block: int = 500) -> DataFrame:
    """Pairs with a cosine of at least ``least``.  All pairs are compared: vectors are dealt into blocks of about
    ``block`` and every pair of blocks is joined on its own."""
    unit = F.transform(vector, lambda x: x.cast("double"))
    rows = rows.select(F.col(key).cast("long").alias("id"), unit.alias("x"))
    norm = F.sqrt(F.aggregate("x", F.lit(0.0), lambda s, x: s + x * x))
    rows = rows.withColumn("norm", norm).filter("norm > 0")
    k = max(1, -(-rows.count() // block))
    rows = rows.withColumn("s", F.pmod(F.xxhash64("id"), F.lit(k)).cast("int"))
    side = lambda n, own: [*(F.col(c).alias(f"{c}_{n}") for c in ("id", "x", "norm")), F.col("s").alias(own)]
    a = rows.select(*side("a", "i"), F.explode(F.sequence("s", F.lit(k - 1))).alias("j"))
    b = rows.select(*side("b", "j"), F.explode(F.sequence(F.lit(0), "s")).alias("i"))
    both = a.join(b, ["i", "j"]).filter("(i < j and id_a != id_b) or id_a < id_b")
    dot = F.aggregate(F.zip_with("x_a", "x_b", lambda p, q: p * q), F.lit(0.0), lambda s, x: s + x)
    return both.filter(dot >= least * F.col("norm_a") * F.col("norm_b")).select(F.least("id_a", "id_b").alias("u"), F.greatest("id_a", "id_b").alias("v")).distinct()


def stable_id(text: Column) -> Column:
    """A 60-bit id of a string, the same in any SQL engine."""
    return F.conv(F.substring(F.md5(text), 1, 15), 16, 10).cast("long")


def links(pages: DataFrame) -> DataFrame:
    """page * 2 to hashed target * 2 + 1, for each href in a page."""
    found = pages.select("page_id", F.explode(F.regexp_extract_all("html", F.lit('href="([^"]+)"'), F.lit(1))).alias("target"))
    return bipartite(found.filter("target <> ''"), F.col("page_id"), stable_id(F.col("target")))


def document_lines(docs: DataFrame, least: int = 12) -> DataFrame:
    lines = docs.select("doc_id", F.explode(F.split("text", "\n")).alias("line"))
    return lines.select("doc_id", F.trim("line").alias("line")).filter(F.length("line") >= least)


def mentions(docs: DataFrame, items: DataFrame) -> DataFrame:
    """doc * 2 to item * 2 + 1 where a line holds the item's text.

    An item's second space-separated token stands whole in any line that holds it, so candidates come from
    an equi-join on tokens; items of under three tokens are few and are compared directly."""
    lines = document_lines(docs)
    tokens = F.split("text", " ")
    items = items.filter("length(text) > 0 and instr(text, '\n') = 0").select("item_id", F.col("text").alias("item"), F.when(F.size(tokens) >= 3, tokens[1]).alias("token"))
    words = lines.select("doc_id", "line", F.explode(F.array_distinct(F.split("line", " "))).alias("token"))
    long = words.join(items.filter("token is not null"), "token")
    short = lines.join(F.broadcast(items.filter("token is null").drop("token")), F.expr("instr(line, item) > 0"))
    found = long.filter("instr(line, item) > 0").select("doc_id", "item_id").unionByName(short.select("doc_id", "item_id"))
    return bipartite(found, F.col("doc_id"), F.col("item_id"))


def kronecker(a: DataFrame, b: DataFrame) -> DataFrame:
    """Product of two factor graphs over dense ids 0..n-1; id = a * n_B + b.  The only cross join in the library."""
    n = b.agg(F.max("v")).first()[0]
    size = (n or 0) + 1
    one, two = arcs(a).select(F.col("x").alias("xa"), F.col("y").alias("ya")), arcs(b).select(F.col("x").alias("xb"), F.col("y").alias("yb"))
    return one.crossJoin(two).select((F.col("xa") * size + F.col("xb")).alias("u"), (F.col("ya") * size + F.col("yb")).alias("v")).filter("u < v")


def dense_ids(edges: DataFrame) -> DataFrame:
    """The same graph over 0..n-1 by ascending id (for factor graphs: one task numbers all vertices)."""
    ids = arcs(edges).select("x").distinct()
    ids = ids.select("x", (F.row_number().over(Window.partitionBy(F.lit(0)).orderBy("x")) - 1).cast("long").alias("i"))
    one, two = (ids.select(F.col("x").alias(c), F.col("i").alias(f"i{c}")) for c in "uv")
    return edges.join(one, "u").join(two, "v").select(F.col("iu").alias("u"), F.col("iv").alias("v"))
