import random

import pytest

from tests import test_entry
from vsketch.operators import baselines, blocks, exact


@pytest.mark.parametrize("block", [7, 40, 8192])
def test_triangles_by_blocks_are_exact(spark, block):
    draw = random.Random(6)
    pairs = sorted({tuple(sorted(draw.sample(range(0, 9000, 90), 2))) for _ in range(1500)})
    edges = spark.createDataFrame(pairs, "u long, v long").repartition(4).cache()
    vertices = spark.createDataFrame([(x,) for x in range(0, 9000, 90)], "x long")
    want = exact.global_triangles(edges).first()[0]
    assert blocks.triangles(edges, vertices, block).first()[0] == want > 0
    assert blocks.triangles(edges.filter("u > v"), vertices, block).first()[0] == 0


def test_sample_final_lists_no_wedges(spark, monkeypatch):
    monkeypatch.setattr(baselines, "triangles", None)
    monkeypatch.setattr(exact, "triangles", None)
    test_entry.test_against_sql(spark, "b_sample_final")
