"""The named graphs of the experiments, from the given tables, and their SQL."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import build


def _t(spark: SparkSession, sf: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf}/{name}.parquet")


def _order_lines(s, d):
    o = _t(s, d, "orders").select("o_orderkey", "o_custkey")
    return _t(s, d, "lineitem").select("l_orderkey", "l_partkey", "l_suppkey").join(o, F.col("l_orderkey") == F.col("o_orderkey"))


def _geo(s, d):
    c, p, n = _t(s, d, "customer"), _t(s, d, "supplier"), _t(s, d, "nation")
    k = lambda col, kind: (F.col(col).cast("long") * 4 + kind)
    parts = [c.select(k("c_custkey", 0).alias("u"), k("c_nationkey", 2).alias("v")), p.select(k("s_suppkey", 1).alias("u"), k("s_nationkey", 2).alias("v")), n.select(k("n_nationkey", 2).alias("u"), k("n_regionkey", 3).alias("v"))]
    return build.canonical(parts[0].unionByName(parts[1]).unionByName(parts[2]))


def _turns(s, d):
    rows = _t(s, d, "conversations").select("conv_id", "turn")
    return build.successive(rows, F.col("conv_id").cast("long") * 4096 + F.col("turn").cast("long"), ["turn"], ["conv_id"])


GRAPHS: dict[str, Callable[[SparkSession, str], DataFrame]] = {
    "copart": lambda s, d: build.co_occurrence(_t(s, d, "lineitem"), "l_orderkey", "l_partkey"),
    "cosupp": lambda s, d: build.co_occurrence(_t(s, d, "lineitem"), "l_orderkey", "l_suppkey"),
    "docline": lambda s, d: build.co_occurrence(build.document_lines(_t(s, d, "documents")), "line", "doc_id", 200),
    "cust_part": lambda s, d: build.bipartite(_order_lines(s, d), F.col("o_custkey"), F.col("l_partkey")),
    "cust_supp": lambda s, d: build.bipartite(_order_lines(s, d), F.col("o_custkey"), F.col("l_suppkey")),
    "part_supp": lambda s, d: build.bipartite(_t(s, d, "lineitem"), F.col("l_partkey"), F.col("l_suppkey")),
    "order_part": lambda s, d: build.bipartite(_t(s, d, "lineitem"), F.col("l_orderkey"), F.col("l_partkey")),
    "event_prox60": lambda s, d: build.proximity(_t(s, d, "events"), "ts", "user_id", 60),
    "event_prox300": lambda s, d: build.proximity(_t(s, d, "events"), "ts", "user_id", 300),
    "user_next": lambda s, d: build.successive(_t(s, d, "events"), F.col("user_id"), ["ts", "event_id"]),
    "geo_tree": _geo,
    "emb_sim": lambda s, d: build.similarity(_t(s, d, "embeddings"), "vec_id", "embedding", 0.3),
    "page_link": lambda s, d: build.links(_t(s, d, "pages")),
    "conv_turn": _turns,
    "doc_bench": lambda s, d: build.mentions(_t(s, d, "documents"), _t(s, d, "benchmark")),
}


def graph(spark: SparkSession, sf: str, name: str) -> DataFrame:
    if name.startswith("kron:"):
        a, b = name[5:].split("*")
        return build.kronecker(build.dense_ids(graph(spark, sf, a)), build.dense_ids(graph(spark, sf, b)))
    return GRAPHS[name](spark, sf)


def _canon(sql: str) -> str:
    return f"SELECT DISTINCT least(u, v) AS u, greatest(u, v) AS v FROM ({sql}) WHERE u <> v"


def _pairs(table: str, group: str, member: str) -> str:
    return f"SELECT DISTINCT a.{member} AS u, b.{member} AS v FROM {table} a JOIN {table} b ON a.{group} = b.{group} AND a.{member} < b.{member}"


def _prox(w: int) -> str:
    micro = w * 1_000_000
    return _canon(f"SELECT a.user_id AS u, b.user_id AS v FROM (SELECT epoch_us(ts) AS t, user_id FROM events) a JOIN (SELECT epoch_us(ts) AS t, user_id FROM events) b ON b.t >= a.t AND b.t < a.t + {micro} AND a.user_id <> b.user_id")


_LINES = "SELECT DISTINCT doc_id, trim(line, ' ') AS line FROM (SELECT doc_id, unnest(string_split(text, chr(10))) AS line FROM documents) WHERE length(trim(line, ' ')) >= 12"
SQL: dict[str, str] = {
    "copart": _pairs("lineitem", "l_orderkey", "l_partkey"),
    "cosupp": _pairs("lineitem", "l_orderkey", "l_suppkey"),
    "docline": f"WITH l AS ({_LINES}), k AS (SELECT line FROM l GROUP BY line HAVING count(*) >= 2) SELECT DISTINCT a.doc_id AS u, b.doc_id AS v FROM l a JOIN k ON k.line = a.line JOIN l b ON b.line = a.line AND a.doc_id < b.doc_id",
    "cust_part": _canon("SELECT o_custkey * 2 AS u, l_partkey * 2 + 1 AS v FROM lineitem JOIN orders ON l_orderkey = o_orderkey"),
    "cust_supp": _canon("SELECT o_custkey * 2 AS u, l_suppkey * 2 + 1 AS v FROM lineitem JOIN orders ON l_orderkey = o_orderkey"),
    "part_supp": _canon("SELECT l_partkey * 2 AS u, l_suppkey * 2 + 1 AS v FROM lineitem"),
    "order_part": _canon("SELECT l_orderkey * 2 AS u, l_partkey * 2 + 1 AS v FROM lineitem"),
    "event_prox60": _prox(60),
    "event_prox300": _prox(300),
    "user_next": _canon("SELECT user_id AS u, lead(user_id) OVER (ORDER BY ts, event_id) AS v FROM events"),
    "geo_tree": _canon("SELECT c_custkey * 4 AS u, CAST(c_nationkey AS BIGINT) * 4 + 2 AS v FROM customer UNION ALL SELECT s_suppkey * 4 + 1, CAST(s_nationkey AS BIGINT) * 4 + 2 FROM supplier UNION ALL SELECT CAST(n_nationkey AS BIGINT) * 4 + 2, CAST(n_regionkey AS BIGINT) * 4 + 3 FROM nation"),
    "emb_sim": "WITH e AS (SELECT vec_id, list_transform(embedding, lambda x: x::DOUBLE) AS x FROM embeddings), n AS (SELECT vec_id, x, sqrt(list_inner_product(x, x)) AS norm FROM e) SELECT DISTINCT a.vec_id AS u, b.vec_id AS v FROM n a JOIN n b ON a.vec_id < b.vec_id WHERE a.norm > 0 AND b.norm > 0 AND list_inner_product(a.x, b.x) >= 0.3 * a.norm * b.norm",
    "page_link": _canon("""SELECT page_id * 2 AS u, ('0x' || substr(md5(t), 1, 15))::BIGINT * 2 + 1 AS v FROM (SELECT page_id, unnest(regexp_extract_all(html, 'href="([^"]+)"', 1)) AS t FROM pages) WHERE t <> ''"""),
    "conv_turn": _canon("SELECT conv_id * 4096 + turn AS u, lead(conv_id * 4096 + turn) OVER (PARTITION BY conv_id ORDER BY turn) AS v FROM conversations"),
    "doc_bench": _canon(f"SELECT doc_id * 2 AS u, item_id * 2 + 1 AS v FROM ({_LINES}) l JOIN benchmark b ON contains(l.line, b.text) AND length(b.text) > 0"),
}


def sql(name: str) -> str:
    if name.startswith("kron:"):
        a, b = name[5:].split("*")
        dense = lambda g: f"SELECT p.i AS u, q.i AS v FROM ({SQL[g]}) e JOIN (SELECT x, row_number() OVER (ORDER BY x) - 1 AS i FROM (SELECT u AS x FROM ({SQL[g]}) UNION SELECT v FROM ({SQL[g]}))) p ON p.x = e.u JOIN (SELECT x, row_number() OVER (ORDER BY x) - 1 AS i FROM (SELECT u AS x FROM ({SQL[g]}) UNION SELECT v FROM ({SQL[g]}))) q ON q.x = e.v"
        both = lambda t: f"SELECT u AS x, v AS y FROM {t} UNION ALL SELECT v, u FROM {t}"
        return f"WITH da AS MATERIALIZED ({dense(a)}), db AS MATERIALIZED ({dense(b)}), size AS (SELECT max(v) + 1 AS s FROM db) SELECT a.x * s + b.x AS u, a.y * s + b.y AS v FROM ({both('da')}) a, ({both('db')}) b, size WHERE a.x * s + b.x < a.y * s + b.y"
    return SQL[name]
