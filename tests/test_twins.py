import datetime
import random

import pytest
from pyspark.sql import functions as F

from tests import test_entry
from vsketch.operators import exact, twins
from vsketch.sources.build import proximity

START = datetime.datetime(2024, 1, 1)


def seen(spark):
    draw = random.Random(4)
    rows = [(START + datetime.timedelta(seconds=draw.randrange(9000)), x) for x in range(60) for _ in range(draw.randrange(1, 4))]
    rows += [(t, x + 100 * i) for t, x in rows for i in range(1, 4) if x % 3 == 0] + [(START + datetime.timedelta(days=9), 900 + i) for i in range(3)]
    return spark.createDataFrame([*rows, *rows[:5], (START + datetime.timedelta(days=20), 999), (None, 1), (START, None)], "ts timestamp, who long").cache()


def test_twins_give_exact_balls_and_built_in_estimates(spark):
    want = exact.balls(proximity(seen(spark), "ts", "who", 60), 2).cache()
    held = twins.twins(seen(spark), "ts", "who", 60)
    got = twins.exact_sizes(*held, 2).cache()
    assert got.count() == want.count() > 100 and not got.select("x", "t", "n").exceptAll(want.select("x", "t", "n").withColumn("n", F.col("n").cast("long"))).count()
    est = twins.builtin_sizes(*held, 2).join(want, ["x", "t"])
    assert est.count() == want.count() and est.filter("abs(n_est - n) > 0.1 * n + 1").isEmpty()


def test_built_in_balls_make_no_edges_of_twins(spark, monkeypatch):
    from vsketch.operators import trials
    from vsketch.plans import graph_queries

    monkeypatch.setattr(trials, "exact_balls", None)
    monkeypatch.setattr(graph_queries.balls, "ball_sizes_builtin", None)
    test_entry.test_against_sql(spark, "balls_builtin_hll")


@pytest.mark.parametrize("most", [4096, 1])
def test_triangles_of_edges_by_twins(spark, most):
    edges = proximity(seen(spark), "ts", "who", 60).cache()
    got = twins.edge_triangles(*twins.twins(seen(spark), "ts", "who", 60), most).cache()
    want = exact.edge_triangles(edges)
    assert got.count() == edges.count() and not got.exceptAll(want).count()


def test_array_triangles_make_no_edges_of_twins(spark, monkeypatch):
    monkeypatch.setattr(exact, "edge_triangles", None)
    test_entry.test_against_sql(spark, "arr_adjacency_intersect")
