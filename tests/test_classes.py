import random

import pytest
from pyspark.sql import functions as F

from tests import test_entry
from vsketch.operators import classes, exact, groups
from vsketch.sources.build import co_occurrence


def test_classes_give_all_edges_and_triangles(spark):
    draw = random.Random(3)
    rows = [(f"g{draw.randrange(25)}", draw.randrange(120)) for _ in range(260)] + [("big", i) for i in range(400, 1000)] + [("next", i) for i in range(980, 1010)]
    rows = spark.createDataFrame([*rows, *rows[:9], ("lone", 5), ("none", None)], "line string, doc long").cache()
    want = co_occurrence(rows, "line", "doc").cache()
    table, pairs = classes.classes(groups.memberships(rows, "line", "doc"))
    got = classes.edges(table, pairs).cache()
    assert got.count() == want.count() == got.distinct().count() and not got.exceptAll(want).count()
    assert classes.global_triangles(table, pairs).first()[0] == exact.global_triangles(want).first()[0]
    weights = table.select("c", "w").distinct()
    assert len({classes.weighted_triangles(pairs, weights, block).first()[0] for block in (10, 4096)}) == 1


def test_a_large_class_needs_no_edges(spark):
    """A line of 200,000 documents: 20 billion edges, 1.3e15 triangles."""
    table, pairs = classes.classes(groups.memberships(spark.range(200_000).select(F.lit("line").alias("line"), "id"), "line", "id"))
    n = 200_000
    assert classes.global_triangles(table, pairs).first()[0] == n * (n - 1) * (n - 2) // 6


@pytest.mark.parametrize("name", ["b_reservoir_base", "b_wedges"])
def test_queries_against_sql(spark, name):
    test_entry.test_against_sql(spark, name)
