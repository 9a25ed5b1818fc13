import pytest
from pyspark.sql import functions as F

from tests import test_entry
from vsketch.operators import exact
from vsketch.sources.build import canonical


@pytest.mark.parametrize("name", ["agg_cube_colour_hop", "win_hop_growth"])
def test_queries_over_hubs(spark, name):
    test_entry.test_against_sql(spark, name)


def test_balls_with_leaves(spark):
    """Stars, chains, a lone edge, a triangle with leaves, against plain search."""
    pairs = [(1, 2), (1, 3), (1, 4), (10, 11), (20, 21), (21, 22), (22, 23), (30, 31), (31, 32), (30, 32), (30, 33), (30, 34), (32, 35), (35, 36)]
    near: dict = {}
    for a, b in pairs:
        near.setdefault(a, set()).add(b)
        near.setdefault(b, set()).add(a)
    want = set()
    for x in near:
        ball = {x}
        for k in (1, 2, 3, 4):
            ball = ball | {z for y in ball for z in near[y]}
            want.add((x, k, len(ball)))
    edges = canonical(spark.createDataFrame(pairs, "u long, v long"))
    assert {tuple(r) for r in exact.balls(edges, 4).select("x", "t", "n").collect()} == want
    front = exact.balls(edges.unionByName(canonical(spark.range(40_000).select(F.lit(1).alias("u"), (F.col("id") + 100).alias("v")))), 2)
    assert front.filter("x = 100").select("n").first()[0] == 40_004
