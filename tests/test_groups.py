import pytest
from pyspark.sql import functions as F

from tests import test_entry
from vsketch.functions.spec import PORTABLE8
from vsketch.operators import balls, groups, vst
from vsketch.sources.build import co_occurrence


@pytest.fixture(scope="module")
def rows(spark):
    pairs = [("a", 1), ("a", 2), ("b", 2), ("b", 3), ("c", 3), ("c", 4), ("c", 5), ("c", 6), ("d", 6), ("d", 7), ("e", 8), ("f", 9), ("f", 9), ("g", 10), ("g", 11), ("h", None)]
    pairs += [("big", i) for i in range(100, 400)] + [("next", i) for i in range(390, 420)] + [("pair", 1), ("pair", 400)]
    return spark.createDataFrame(pairs, "line string, doc long").cache()


def key(frame):
    return sorted(tuple(round(v, 6) if isinstance(v, float) else v for v in r) for r in frame.collect())


def test_memberships_give_the_registers_of_edges(rows):
    edges, members = co_occurrence(rows, "line", "doc"), groups.memberships(rows, "line", "doc")
    table = vst.accumulate(edges, PORTABLE8)
    want = balls.ball_sizes(edges, table, 3, form="rows")
    for active in ("all", "changed"):
        got = groups.ball_sizes(members, PORTABLE8, 3, active=active)
        assert key(got.local) == key(want.local)
        assert all(key(got.layers[t].select("x", "j", "rho")) == key(want.layers[t].select("x", "j", "rho")) for t in (1, 2, 3))
    assert key(groups.two_hop(members, PORTABLE8)) == key(balls.two_hop(edges, table))


@pytest.mark.parametrize("name", ["balls_beta_k2", "balls_delta_k3", "balls_packed_k3", "balls_two_hop"])
def test_queries_against_sql(spark, name):
    test_entry.test_against_sql(spark, name)


def test_a_large_group_has_few_memberships(spark):
    """A line of 200,000 documents: 20 billion edges, which are never made."""
    got = groups.ball_sizes(groups.memberships(spark.range(200_000).select(F.lit("line").alias("line"), "id"), "line", "id"), PORTABLE8, 1)
    assert got.local.count() == 200_000 and got.local.agg(F.countDistinct("n_est")).first()[0] == 1
