"""Times headline queries on $BENCH_SF_DIR with local[$BENCH_CPUS]; prints one JSON line.

Edges are written and read back first, so times are of the methods, not of building graphs from tables.
``--scaling`` also times accumulation and triangles over graphs of growing size and over cores."""

from __future__ import annotations

import json
import math
import os
import sys
import tempfile
import time

from pyspark.sql import SparkSession

SF_DIR = os.environ.get("BENCH_SF_DIR", "/root/testdata/sf0.1")
CPUS = os.environ.get("BENCH_CPUS", "8")


def session(cpus: str) -> SparkSession:
    spark = (
        SparkSession.builder.master(f"local[{cpus}]").appName("bench").config("spark.ui.enabled", "false").config("spark.driver.memory", "16g")
        .config("spark.sql.shuffle.partitions", str(2 * int(cpus))).config("spark.sql.session.timeZone", "UTC").config("spark.ui.showConsoleProgress", "false").getOrCreate()
    )
    spark.sparkContext.setLogLevel("ERROR")
    return spark


def timed(run) -> float:
    start = time.time()
    run().write.format("noop").mode("overwrite").save()
    return round(time.time() - start, 3)


def stored(spark: SparkSession, name: str, root: str):
    from vsketch.sources.graphs import graph

    path = f"{root}/{name}"
    if not os.path.exists(path):
        graph(spark, SF_DIR, name).repartition(int(CPUS)).write.parquet(path)
    return spark.read.parquet(path)


def headline(spark: SparkSession, root: str) -> dict[str, float]:
    from vsketch.functions.spec import SketchSpec
    from vsketch.operators import balls, exact, triangles, vst

    copart, docline, near = (stored(spark, n, root) for n in ("copart", "docline", "event_prox60"))
    p8 = SketchSpec(p=8)
    ready = vst.Vst(balls.shared_table(vst.accumulate(copart, p8).regs, "bench"), p8)
    doc = vst.Vst(balls.shared_table(vst.accumulate(docline, p8).regs, "bench"), p8)
    return {
        "accumulate_copart": timed(lambda: vst.accumulate(copart, p8).regs),
        "accumulate_builtin_hll_copart": timed(lambda: vst.accumulate_builtin(copart, "hll", 8)),
        "degree_copart": timed(lambda: ready.degree("beta")),
        "balls_k2_docline": timed(lambda: balls.ball_sizes(docline, doc, 2, form="auto").total),
        "balls_k3_event_prox60": timed(lambda: balls.ball_sizes(near, vst.accumulate(near, p8), 3, form="auto").total),
        "edge_triangles_packed_copart": timed(lambda: triangles.total(triangles.edge_triangles(copart, ready, "ie_packed"))),
        "edge_top100_packed_docline": timed(lambda: triangles.top_edges(triangles.edge_triangles(docline, doc, "ie_packed"), 100)),
        "vertex_top100_packed_docline": timed(lambda: triangles.top_vertices(triangles.vertex_triangles(triangles.edge_triangles(docline, doc, "ie_packed")), 100)),
        "edge_top100_ml_pruned_docline": timed(lambda: triangles.top_edges_pruned(docline, doc, 100, "ml")),
        "exact_triangles_copart": timed(lambda: exact.global_triangles(copart)),
    }


def scaling(root: str) -> dict:
    """Seconds over graphs (fixed cores) and over cores (fixed graph), with the slope against edges on logs."""
    from vsketch.functions.spec import SketchSpec
    from vsketch.operators import balls, packed, triangles, vst
    from vsketch.sources.build import arcs as both_ways

    p8, out = SketchSpec(p=8), {"graphs": {}, "cores": {}, "passes": {}}

    def both(spark, name):
        edges = stored(spark, name, root)
        acc = timed(lambda: vst.accumulate(edges, p8).regs)
        table = vst.Vst(balls.shared_table(vst.accumulate(edges, p8).regs, "bench"), p8)
        return edges.count(), acc, timed(lambda: triangles.total(triangles.edge_triangles(edges, table, "ie_packed")))

    def passes(spark, name, k=4):
        """Seconds of each ball pass after the first, from a packed layer: sparse where it is sparse, and dense only."""
        edges, times = stored(spark, name, root), {}
        arcs = both_ways(edges)
        for dense in (False, True):
            now, own = balls.shared_table(packed.pack(balls.ball_sizes(edges, vst.accumulate(edges, p8), 1).layers[1], p8, dense), "bench"), []
            for _ in range(2, k + 1):
                start = time.time()
                now = balls.shared_table(packed.ball_step_packed(now, arcs, p8, dense_only=dense), "bench")
                own.append(round(time.time() - start, 3))
            times["dense" if dense else "mixed"] = own
        return times

    spark = session(CPUS)
    both(spark, "docline")
    for name in ("event_prox60", "order_part", "event_prox300", "docline", "copart"):
        out["graphs"][name] = both(spark, name)
    logs = [(math.log(m), math.log(acc), math.log(tri)) for m, acc, tri in out["graphs"].values()]
    mean = [sum(c) / len(logs) for c in zip(*logs, strict=True)]
    var = sum((x[0] - mean[0]) ** 2 for x in logs)
    out["slope"] = [round(sum((x[0] - mean[0]) * (x[i] - mean[i]) for x in logs) / var, 2) for i in (1, 2)]
    spark.stop()
    for cpus in ("1", "2", "4", "8"):
        spark = session(cpus)
        both(spark, "docline")
        out["cores"][cpus] = both(spark, "event_prox60")[1:]
        out["passes"][cpus] = passes(spark, "event_prox60")
        spark.stop()
    return out


def main() -> None:
    with tempfile.TemporaryDirectory() as root:
        spark = session(CPUS)
        queries = headline(spark, root)
        spark.stop()
        line = {"metric": "headline_total", "value": round(sum(queries.values()), 3), "unit": "sec", "queries": queries, "sf": SF_DIR.rsplit("sf", 1)[-1]}
        if "--scaling" in sys.argv:
            line["scaling"] = scaling(root)
    print(json.dumps(line))


if __name__ == "__main__":
    main()
