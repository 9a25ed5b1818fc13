import duckdb
import pytest

import __spark_entry__ as entry

SF = "/root/testdata/sf0.001"
SAMPLE = ["g_geo_tree", "vst_degree", "balls_local_k3", "balls_delta_k3", "i_joint_counts", "tri_edge_top100_ie", "x_edge_triangles_oriented", "b_minwise_triangles", "m_pr_curve_edges", "s_accumulate_available_now", "s_window_session", "join_asof_version"]


def test_names_agree():
    q, o = entry.queries(), entry.oracle_sql()
    assert set(o) <= set(q) and len(q) > 100


def test_entry(spark):
    assert entry.entry(spark).count() == 100


@pytest.mark.parametrize("name", SAMPLE)
def test_against_sql(spark, name):
    con = duckdb.connect()
    for t in "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split():
        con.execute(f"create view {t} as select * from '{SF}/{t}.parquet'")
    got = entry.queries()[name](spark, SF)
    want = con.execute(entry.oracle_sql()[name])
    names = [c[0] for c in want.description]
    assert sorted(names) == sorted(got.columns)
    key = lambda rows, cols: sorted(tuple(str(round(float(r[c]), 5)) if isinstance(r[c], float) else str(r[c]) for c in sorted(names)) for r in rows)
    assert key([r.asDict() for r in got.collect()], names) == key([dict(zip(names, r, strict=True)) for r in want.fetchall()], names)


def test_intersections_of_all_parts(spark):
    sf = SF.replace("0.001", "0.01")
    con = duckdb.connect()
    for t in ("part", "lineitem"):
        con.execute(f"create view {t} as select * from '{sf}/{t}.parquet'")
    got = entry.queries()["vst_intersect_all_parts"](spark, sf)
    want = con.execute(f"select {', '.join(got.columns)} from ({entry.oracle_sql()['vst_intersect_all_parts']})").fetchall()
    near = lambda rows: sorted(tuple(round(x, 5) for x in r) for r in rows)
    assert near(map(tuple, got.collect())) == near(want) and len(want) == spark.read.parquet(f"{sf}/part.parquet").count() > 200
