import random

import pytest
from pyspark.sql import functions as F

from tests import test_entry
from vsketch.functions.spec import PORTABLE8
from vsketch.operators import balls, baselines, vst, windows
from vsketch.sources.build import proximity


@pytest.fixture(scope="module")
def rows(spark):
    """Bursts, lone ids, ids seen several times in a window, equal times, a null and gaps of exactly a minute."""
    draw = random.Random(5)
    seen = [(draw.choice([0, 40, 90, 200, 333, 1000]) + draw.random() * 70, draw.randrange(60)) for _ in range(300)]
    seen += [(5000.0, 70), (5060.0, 71), (5119.5, 72), (5119.5, 72), (9000.0, 73), (9000.0, 74), (9030.0, 73), (20000.0, 75), (20010.0, 75), (-61.0, 76), (-2.0, 77), (None, 78), (1.0, None)]
    return spark.createDataFrame(seen, "s double, who long").select(F.expr("timestamp_micros(cast(s * 1000000 as long))").alias("ts"), "who").cache()


def key(frame):
    return sorted(tuple(round(v, 6) if isinstance(v, float) else v for v in r) for r in frame.collect())


@pytest.mark.parametrize("many", [40, 400_000])
def test_windows_give_the_registers_of_edges(rows, many):
    edges, seen = proximity(rows, "ts", "who", 60), windows.sightings(rows, "ts", "who", 60, many)
    table = vst.accumulate(edges, PORTABLE8)
    for ball in ("closed", "as_printed"):
        want, got = balls.ball_sizes(edges, table, 3, ball=ball, form="rows"), windows.ball_sizes(seen, 60, PORTABLE8, 3, ball=ball)
        assert key(got.local) == key(want.local)
        assert all(key(got.layers[t].select("x", "j", "rho")) == key(want.layers[t].select("x", "j", "rho")) for t in (1, 2, 3))
    want, got = (f(60, until_stable=True) for f in (lambda k, **h: balls.ball_sizes(edges, table, k, **h), lambda k, **h: windows.ball_sizes(seen, 60, PORTABLE8, k, **h)))
    assert got.hops == want.hops and key(got.local) == key(want.local)
    assert key(windows.balls_bitmap(seen, 60, 3)) == key(baselines.balls_bitmap(edges, 3))


def test_a_crowded_minute_makes_no_edges(spark):
    """100,000 ids in a minute: 5 billion edges, which are never made."""
    rows = spark.range(100_000).select(F.expr("timestamp_micros(id * 100)").alias("ts"), "id")
    got = windows.ball_sizes(windows.sightings(rows, "ts", "id", 60), 60, PORTABLE8, 1)
    assert got.local.count() == 100_000 and got.local.agg(F.countDistinct("n_est")).first()[0] == 1


@pytest.mark.parametrize("name", ["balls_total_k3", "balls_until_stable", "balls_auto_k3", "balls_as_printed_k2", "b_balls_bitmap"])
def test_queries_against_sql(spark, name):
    test_entry.test_against_sql(spark, name)


def test_global_balls_make_no_edges(spark, monkeypatch):
    from tests import test_entry
    from vsketch.plans import measure_queries

    for fn in ("graph", "_vst"):
        monkeypatch.setattr(measure_queries, fn, None)
    test_entry.test_against_sql(spark, "b_balls_global_only")
