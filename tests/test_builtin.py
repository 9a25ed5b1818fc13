from tests import test_entry
from vsketch.operators import balls
from vsketch.sources.build import co_occurrence


def test_sketches_merge_in_tasks_before_the_shuffle(spark, monkeypatch):
    """A hub's task holds more vertices than the default lets it merge; the setting is put back."""
    name = "spark.sql.objectHashAggregate.sortBased.fallbackThreshold"
    before, seen, real = spark.conf.get(name), [], balls.shared_table
    monkeypatch.setattr(balls, "shared_table", lambda frame, tag: seen.append((tag, int(spark.conf.get(name)))) or real(frame, tag))
    edges = co_occurrence(spark.range(200).selectExpr("1 as g", "id"), "g", "id")
    got = balls.ball_sizes_builtin(edges, 2)
    assert [n for tag, n in seen if tag == "layer"] == [16_384, 16_384] and spark.conf.get(name) == before
    assert got.count() == 400 and got.filter("abs(n_est - 200) > 10").isEmpty()


def test_query_against_sql(spark):
    test_entry.test_against_sql(spark, "balls_builtin_hll")
