import random

import pytest
from pyspark.sql import functions as F

from tests import test_entry
from vsketch.operators import reservoirs


def in_order(rows, size, three=None):
    """The pass over a stream in order, held edges by lowest priority."""
    held, total = [], 0.0
    for t, r in enumerate(sorted(rows, key=lambda r: (r["pos"], r["u"], r["v"])), 1):
        near = lambda x: {a if b == x else b: g for a, b, g in ((e["u"], e["v"], e["gu"] if e["v"] == x else e["gv"]) for e in held) if x in (a, b)}  # noqa: B023, E731
        one, two = near(r["u"]), near(r["v"])
        both = [z for z in one.keys() & two.keys() if three is None or tuple(sorted((r["gu"], r["gv"], one[z]))) == three]
        total += max(1.0, (t - 1) * (t - 2) / (size * (size - 1))) * len(both)
        held = sorted([*held, r], key=lambda e: e["prio"])[:size]
    return total


@pytest.mark.parametrize("workers, groups, slack", [(1, None, 1.5), (3, None, 0.01), (1, 3, 1.5)])
def test_reservoirs_are_those_of_a_pass_in_order(spark, workers, groups, slack):
    draw = random.Random(5)
    pairs = {tuple(sorted(draw.sample(range(40), 2))) for _ in range(420)}
    edges = spark.createDataFrame(sorted(pairs), "u long, v long").repartition(5).cache()
    got = {r["trial"]: r["t_est"] for r in reservoirs.triangles(edges, 60, 2, 3, workers, groups, slack).collect()}
    rows = reservoirs.reservoirs(reservoirs.streams(edges, 3, groups), 2, 3, workers, groups).collect()
    names = {r["worker"] for r in rows}
    assert len(names) == (10 if groups else workers)
    for trial in range(2):
        each = [in_order([r for r in rows if (r["trial"], r["worker"]) == (trial, w)], 60, tuple(map(int, w.split("-"))) if groups else None) for w in names]
        assert got[trial] == pytest.approx(sum(each) / (1 if groups else workers)) and got[trial] > 0


def test_a_reservoir_that_holds_all_counts_all(spark):
    edges = spark.range(12).alias("a").join(spark.range(12).alias("b"), F.expr("a.id < b.id")).select(F.expr("a.id u"), F.expr("b.id v"))
    assert [r["t_est"] for r in reservoirs.triangles(edges, 100, 2).collect()] == [220.0, 220.0]
    assert [r["t_est"] for r in reservoirs.triangles(edges.filter("u > v"), 100, 2).collect()] == [0.0, 0.0]


@pytest.mark.parametrize("name", ["b_reservoir_improved", "b_reservoir_parallel", "b_reservoir_grouped"])
def test_queries_make_no_rows_for_each_edge_and_trial(spark, monkeypatch, name):
    from vsketch.operators import baselines, exact

    for module, fn in ((baselines, "reservoir_triangles"), (exact, "global_triangles")):
        monkeypatch.setattr(module, fn, None)
    test_entry.test_against_sql(spark, name)


@pytest.mark.parametrize("size, slack", [(60, 2.0), (60, 0.01), (1000, 2.0)])
def test_deletions_at_the_end_leave_gaps(spark, size, slack):
    """The sample is what is left of the edges of lowest priority."""
    draw = random.Random(9)
    pairs = sorted({tuple(sorted(draw.sample(range(30), 2))) for _ in range(300)})
    edges = spark.createDataFrame(pairs, "u long, v long").withColumn("deleted", F.expr("u % 5 = 0")).repartition(4).cache()
    live = sum(u % 5 > 0 for u, _ in pairs)
    got = {r["trial"]: r["t_est"] for r in reservoirs.dynamic_triangles(edges, size, 3, 1, slack).collect()}
    rows = edges.withColumn("trial", F.explode(F.array(F.lit(0), F.lit(1), F.lit(2)))).withColumn("prio", reservoirs._even(F.lit(1), "trial", "u", "v")).collect()
    for trial in range(3):
        held = sorted((r for r in rows if r["trial"] == trial), key=lambda r: r["prio"])[:size]
        left = {(r["u"], r["v"]) for r in held if not r["deleted"]}
        t = sum((a, c) in left and (b, c) in left for a, b in left for c in range(b + 1, 30))
        s = len(left)
        assert t > 0 and got[trial] == pytest.approx(t * (live * (live - 1) * (live - 2) / (s * (s - 1) * (s - 2)) if live > s else 1.0))
    assert [r["t_est"] for r in reservoirs.dynamic_triangles(edges.filter("u > v"), 60, 2).collect()] == [0.0, 0.0]


def test_dynamic_lists_no_wedges_of_all_edges(spark, monkeypatch):
    from vsketch.operators import baselines, exact

    for module, fn in ((baselines, "reservoir_triangles"), (exact, "global_triangles")):
        monkeypatch.setattr(module, fn, None)
    test_entry.test_against_sql(spark, "b_reservoir_dynamic")
