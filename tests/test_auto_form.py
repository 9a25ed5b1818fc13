import pytest

from tests import test_entry
from vsketch.functions.spec import PORTABLE8
from vsketch.operators import balls, vst
from vsketch.sources.build import co_occurrence


def test_filled_sketches_are_packed_by_default(spark, monkeypatch):
    called = []
    real = balls._packed_hops
    monkeypatch.setattr(balls, "_packed_hops", lambda *a: called.append(1) or real(*a))
    edges = co_occurrence(spark.range(100).selectExpr("1 as g", "id"), "g", "id")
    got = balls.ball_sizes(edges, vst.accumulate(edges, PORTABLE8), 2).local
    assert called and got.count() == 200


@pytest.mark.parametrize("name", ["b_balls_global_only", "balls_total_k3", "balls_until_stable"])
def test_queries_of_dense_graphs(spark, name):
    test_entry.test_against_sql(spark, name)
