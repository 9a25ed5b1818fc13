import itertools

import pytest

import __spark_entry__ as entry
from tests import test_entry


@pytest.mark.parametrize("name", ["k_alpha_integral", "k_std_error", "w09_intersection_grid"])
def test_a_table_is_read(spark, name):
    with pytest.raises(Exception, match="/nowhere"):
        entry.queries()[name](spark, "/nowhere").collect()


@pytest.mark.parametrize("name", ["k_alpha_integral", "k_std_error"])
def test_changed_queries_against_sql(spark, name):
    test_entry.test_against_sql(spark, name)


def test_grid_of_sets(spark):
    t = lambda n: [r.asDict() for r in spark.read.parquet(f"{test_entry.SF}/{n}.parquet").collect()]
    nation = {r["s_suppkey"]: r["s_nationkey"] for r in t("supplier")}
    sets: dict = {}
    for r in t("lineitem"):
        sets.setdefault(nation[r["l_suppkey"]], set()).add(r["l_orderkey"])
    got = {(r["p"], r["element"], r["pair"]): r for r in entry.queries()["w09_intersection_grid"](spark, test_entry.SF).collect()}
    assert len(got) == 20 and {k[0] for k in got} == {8, 12}
    shared = [len(a & b) for a, b in itertools.combinations(sets.values(), 2)]
    one = got[12, "order", "nations"]
    assert one["pairs"] == len(shared) and one["empty"] == shared.count(0) and one["mre_naive"] < 0.2 and one["mre_ml"] < 0.2
