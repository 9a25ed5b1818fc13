import pytest
from pyspark.sql import functions as F

from vsketch.functions.spec import PORTABLE8, SketchSpec
from vsketch.operators import balls, baselines, exact, measures, triangles, vst
from vsketch.sources import build
from vsketch.sources.graphs import graph

GRAPHS = {
    "triangle": ([(1, 2), (2, 3), (1, 3)], (9, 9, 9), 1),
    "k4": ([(a, b) for a in range(4) for b in range(a + 1, 4)], (16, 16, 16), 4),
    "star": ([(0, i) for i in range(1, 6)], (16, 36, 36), 0),
    "path": ([(i, i + 1) for i in range(4)], (13, 19, 23), 0),
    "bridge": ([(0, 1), (1, 2), (0, 2), (3, 4), (4, 5), (3, 5), (2, 3)], (20, 28, 36), 2),
}


def frame(spark, rows):
    return spark.createDataFrame(rows, "u long, v long")


@pytest.mark.parametrize("name", list(GRAPHS))
def test_hand_made_graphs(spark, name):
    rows, sums, tri = GRAPHS[name]
    edges = frame(spark, rows)
    got = {r[0]: r[1] for r in exact.balls(edges, 3).groupBy("t").agg(F.sum("n")).collect()}
    assert tuple(got[t] for t in (1, 2, 3)) == sums
    assert exact.global_triangles(edges).first()[0] == tri
    counts = {(r[0], r[1]): r[2] for r in exact.edge_triangles(edges).collect()}
    for how in ("adjacency", "arrays"):
        assert {(r[0], r[1]): r[2] for r in exact.edge_triangles(edges, how).collect()} == counts
    assert sum(counts.values()) == 3 * tri and sum(r[1] for r in exact.vertex_triangles(edges).collect()) == 3 * tri
    table = vst.accumulate(edges, SketchSpec(p=12))
    est = {r["t"]: r["n_est"] for r in balls.ball_sizes(edges, table, 3).total.collect()}
    assert all(abs(est[t] - s) < 0.5 for t, s in zip((1, 2, 3), sums, strict=True))
    per = triangles.edge_triangles(edges, table, "ie")
    assert abs(triangles.total(per).first()[0] - tri) < 0.3


def test_ball_sketch_is_the_sketch_of_the_ball(spark):
    """Layer t equals, register for register, the sketch of the exact ball."""
    edges = frame(spark, [(i, (i * 7 + 3) % 40) for i in range(40)] + [(i, i + 1) for i in range(39)]).transform(build.canonical)
    table = vst.accumulate(edges, PORTABLE8)
    got = balls.ball_sizes(edges, table, 3)
    arcs = build.arcs(edges)
    ball = arcs.select("x", F.col("x").alias("z")).distinct()
    for t in (1, 2, 3):
        ball = ball.unionByName(ball.join(arcs.select(F.col("x").alias("z"), F.col("y").alias("w")), "z").select("x", F.col("w").alias("z"))).distinct()
        want = vst.registers(ball, "x", F.col("z"), PORTABLE8)
        assert sorted(map(tuple, want.collect())) == sorted(map(tuple, got.layers[t].collect()))
    same = balls.ball_sizes(edges, table, 3, active="changed")
    assert sorted(map(tuple, same.layers[3].collect())) == sorted(map(tuple, got.layers[3].collect()))
    for form in ("packed", "auto"):
        for until_stable in (False, True):
            other = balls.ball_sizes(edges, table, 3, form=form, until_stable=until_stable)
            assert sorted(map(tuple, other.layers[3].collect())) == sorted(map(tuple, got.layers[3].collect()))
            want = {(r["x"], r["t"]): r["n_est"] for r in got.local.collect()}
            assert {(r["x"], r["t"]): pytest.approx(r["n_est"]) for r in other.local.collect()} == want
    stop = balls.ball_sizes(frame(spark, GRAPHS["triangle"][0]), vst.accumulate(frame(spark, GRAPHS["triangle"][0]), PORTABLE8), 9, until_stable=True)
    assert stop.hops < 3


def test_dirty_stream_and_order(spark):
    dirty = frame(spark, [(1, 2), (2, 1), (1, 2), (2, 3), (3, 3), (1, 3), (4, None)])
    clean = build.canonical(dirty)
    assert sorted(map(tuple, clean.collect())) == [(1, 2), (1, 3), (2, 3)]
    a, b = (sorted(map(tuple, vst.accumulate(x, PORTABLE8).regs.collect())) for x in (dirty, clean.repartition(7).orderBy(F.desc("v"))))
    assert a == b


def test_empty_graph_and_bad_arguments(spark):
    none = frame(spark, [])
    table = vst.accumulate(none, PORTABLE8)
    assert table.degree().count() == 0 and balls.ball_sizes(none, table, 2).local.count() == 0
    per = triangles.edge_triangles(none, table, "ml")
    assert per.count() == 0 and triangles.total(per).first()[0] == 0
    for bad in (lambda: triangles.top_edges(per, 0), lambda: balls.ball_sizes(none, table, 0), lambda: balls.ball_sizes(none, table, 1, ball="no")):
        with pytest.raises(ValueError):
            bad()


def test_top_ties_and_pruning(spark):
    edges = frame(spark, GRAPHS["k4"][0])
    per = exact.edge_triangles(edges)
    assert triangles.top_edges(per, 1, "keep", "t").count() == 6 and triangles.top_edges(per, 1, value="t").count() == 1
    table = vst.accumulate(edges, SketchSpec(p=10))
    a = triangles.top_edges(triangles.edge_triangles(edges, table, "ml"), 3).collect()
    assert [tuple(r)[:2] for r in triangles.top_edges_pruned(edges, table, 3, "ml", first=1).collect()] == [tuple(r)[:2] for r in a]


def test_kronecker_truth(spark):
    a, b = (frame(spark, [(x, y) for x, y in GRAPHS[n][0]]) for n in ("k4", "bridge"))
    product = build.kronecker(a, b)
    assert product.count() == 2 * 6 * 7
    assert exact.global_triangles(product).first()[0] == 6 * 4 * 2


def test_samplers_on_a_known_graph(spark):
    edges = spark.range(0, 60).crossJoin(spark.range(0, 60).withColumnRenamed("id", "j")).filter("id < j and (id * 31 + j * 17) % 3 = 0").select(F.col("id").alias("u"), F.col("j").alias("v"))
    truth = exact.global_triangles(edges).first()[0]
    m = edges.count()
    whole = {
        "final": baselines.sampled_triangles(edges, 1.0), "arrival": baselines.sampled_triangles(edges, 1.0, mode="arrival"), "base": baselines.reservoir_base(edges, m),
        "improved": baselines.reservoir_triangles(edges, m, 1).select("t_est"), "dynamic": baselines.reservoir_triangles(edges, m, 1, variant="dynamic").select("t_est"),
        "grouped": baselines.reservoir_triangles(edges, m, 1, groups=3).select("t_est"), "parallel": baselines.reservoir_triangles(edges, m, 1, workers=3).select("t_est"), "weighted": baselines.weighted_sample_triangles(edges, 1.0, 1.0, 1).select("t_est"),
    }
    for name, got in whole.items():
        assert abs(got.first()[0] - truth) < 1e-6 * max(1, truth), name
    assert abs(baselines.wedge_triangles(edges, 3000).first()[0] / truth - 1) < 0.15
    for kind in ({"variant": "improved"}, {"variant": "dynamic"}, {"workers": 2}):
        got = baselines.reservoir_triangles(edges, m // 2, 24, **kind).agg(F.avg("t_est")).first()[0]
        assert abs(got / truth - 1) < 0.25, kind


def test_plans(spark):
    edges = frame(spark, GRAPHS["bridge"][0])
    plan = vst.accumulate(edges, PORTABLE8).regs._jdf.queryExecution().executedPlan().toString()
    assert "partial_max" in plan and plan.count("Exchange") == 1 and "CartesianProduct" not in plan
    per = triangles.edge_triangles(edges, vst.accumulate(edges, PORTABLE8), "ie")
    assert "TakeOrderedAndProject" in triangles.top_edges(per, 5)._jdf.queryExecution().executedPlan().toString()


def test_relative_error_of_zero_truth(spark):
    est = spark.createDataFrame([(1, 2.0), (2, 5.0)], "x long, e double")
    true = spark.createDataFrame([(1, 4), (2, 0), (3, 2)], "x long, t long")
    row = measures.mre(measures.relative_errors(est, true, ["x"], "e", "t")).first()
    assert row["mre"] == 0.75 and row["n"] == 2 and row["undefined"] == 1


def test_lines_of_many_documents_keep_their_pairs(spark, tmp_path):
    # one line in 450 documents, beyond two blocks of 200, and one in three of them
    rows = [(i, "a licence line of all" + ("\nanother shared line" if i < 3 else "")) for i in range(450)]
    spark.createDataFrame(rows, "doc_id long, text string").write.parquet(f"{tmp_path}/documents.parquet")
    got = [tuple(r) for r in graph(spark, str(tmp_path), "docline").collect()]
    assert sorted(got) == [(u, v) for u in range(450) for v in range(u + 1, 450)]


def test_precision_has_every_k(spark):
    from vsketch.plans.measure_queries import precision

    got = precision(spark, "/root/testdata/sf0.001", False, ("docline", "copart")).collect()
    m = {n: graph(spark, "/root/testdata/sf0.001", n).count() for n in ("docline", "copart")}
    assert {(r["graph"], r["k"]) for r in got} == {(n, k) for n in m for k in (10, 100, 1000) if k <= m[n]} and max(m.values()) >= 1000


def test_rank_profile_goes_beyond_a_thousand(spark):
    from vsketch.plans.measure_queries import QUERIES

    got = QUERIES["w05_rank_profiles"](spark, "/root/testdata/sf0.01").groupBy("graph").agg(F.max("rank").alias("r"))
    assert {r["graph"]: r["r"] for r in got.collect()}["docline"] == 10_000


def test_similar_vectors_are_found_across_blocks(spark):
    rows = [(i, [float(i * i % 7) - 3, float(i * 5 % 11) - 5, float(i % 3) - 1]) for i in range(70)]
    frame = spark.createDataFrame(rows, "id long, x array<double>")
    got = {tuple(r) for r in build.similarity(frame, "id", "x", 0.3, block=9).collect()}
    dot = lambda p, q: sum(a * b for a, b in zip(p, q, strict=True))
    kept = [(i, x) for i, x in rows if dot(x, x) > 0]
    assert got == {(i, j) for i, x in kept for j, y in kept if i < j and dot(x, y) >= 0.3 * dot(x, x) ** 0.5 * dot(y, y) ** 0.5}
    many = spark.range(20_500).select("id", F.array((F.col("id") == 7).cast("double"), F.lit(1.0)).alias("x"))  # was refused
    assert "join" in build.similarity(many, "id", "x", 0.3)._jdf.queryExecution().toString().lower()
