import random

import pytest
from pyspark.sql import functions as F

from tests import test_entry
from vsketch.operators import baselines, classes, exact, groups, mixed
from vsketch.sources.build import arcs, co_occurrence


def rows_of(spark):
    draw = random.Random(8)
    rows = [(f"g{draw.randrange(40)}", draw.randrange(150)) for _ in range(330)] + [("big", i) for i in range(100, 400)] + [("next", i) for i in range(380, 410)]
    return spark.createDataFrame([*rows, *rows[:9], ("lone", 5), ("none", None)], "line string, doc long").cache()


@pytest.mark.parametrize("least, most", [(10, 4096), (2, 4096), (1000, 4096), (2, 20)])
def test_large_and_small_groups_give_all_edges_and_triangles(spark, least, most):
    rows = rows_of(spark)
    want = co_occurrence(rows, "line", "doc").cache()
    held = mixed.mixed(groups.memberships(rows, "line", "doc"), least, most)
    got = held.edges().cache()
    assert got.count() == want.count() == got.distinct().count() == held.size and not got.exceptAll(want).count()
    assert held.triangles() == exact.global_triangles(want).first()[0] > 0
    assert not held.degrees().select("x", "d").exceptAll(exact.degrees(want)).count()
    every = spark.range(0, 420).alias("a").join(spark.range(0, 420).alias("b"), F.expr("a.id < b.id")).select(F.expr("a.id u"), F.expr("b.id v"))
    assert held.among(every).count() == want.count()
    asked = held.degrees().filter("x % 7 = 0").select("x", F.explode(F.expr("sequence(0L, d - 1)")).alias("k")).cache()
    there = held.neighbours(asked).select("x", "y")
    assert there.count() == asked.count() and not arcs(want).filter("x % 7 = 0").exceptAll(there).count()


def test_no_groups(spark):
    held = mixed.mixed(groups.memberships(rows_of(spark).filter("doc < 0"), "line", "doc"))
    assert held.size == held.triangles() == held.edges().count() == 0


def test_wedges_make_no_edges(spark, monkeypatch):
    for module, fn in ((classes, "edges"), (mixed.Mixed, "edges"), (baselines, "wedge_triangles")):
        monkeypatch.setattr(module, fn, None)
    test_entry.test_against_sql(spark, "b_wedges")


@pytest.mark.parametrize("name", ["b_reservoir_improved", "b_reservoir_parallel", "b_reservoir_grouped"])
def test_reservoirs_join_no_edges(spark, monkeypatch, name):
    """Closed wedges and the exact total come from types; edges are only read in place, twice."""
    read = []
    real = mixed.Mixed.edges
    monkeypatch.setattr(mixed.Mixed, "edges", lambda held: read.append(1) or real(held))
    for module, fn in ((classes, "edges"), (classes, "global_triangles")):
        monkeypatch.setattr(module, fn, None)
    test_entry.test_against_sql(spark, name)
    assert len(read) == 1
