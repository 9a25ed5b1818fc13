import numpy as np
import pytest
from pyspark.sql import functions as F

from vsketch.functions.spec import SketchSpec
from vsketch.operators import balls, exact, joint, trials, triangles, vst
from vsketch.sources.build import canonical


@pytest.fixture(scope="module")
def edges(spark):
    rng = np.random.default_rng(4)
    rows = [(int(a), int(b)) for a, b in rng.integers(0, 60, (400, 2))] + [(100, 101), (101, 102)]
    return canonical(spark.createDataFrame(rows, "u long, v long")).cache()


def near(a, b):
    assert len(a) == len(b)
    for x, y in zip(sorted(map(tuple, a)), sorted(map(tuple, b)), strict=True):
        assert x == pytest.approx(y, abs=1e-5)


@pytest.mark.parametrize("hash", ["xx", "portable"])
def test_trials_equal_the_operators(edges, hash):
    """A seed's task gives what the distributed operators give with the spec of that seed."""
    spec = SketchSpec(p=6, hash=hash, seed=3)
    got = trials.ball_trials(edges, 3, spec, 2)
    for seed in (0, 1):
        own = SketchSpec(p=6, hash=hash, seed=3 + seed)
        near(got.filter(F.col("seed") == seed).select("x", "t", "n_est").collect(), balls.ball_sizes(edges, vst.accumulate(edges, own), 3).local.collect())
    got = trials.edge_trials(edges, spec, 2, "ml", part=50)
    table = vst.accumulate(edges, SketchSpec(p=6, hash=hash, seed=4))
    near(got.filter("seed = 1").select("u", "v", "t_est").collect(), triangles.edge_triangles(edges, table, "ml").select("u", "v", "t_est").collect())


def test_exact_by_bits(edges, monkeypatch):
    near(trials.exact_balls(edges, 3, block=16).collect(), exact.balls(edges, 3).select("x", "t", "n").collect())
    near(trials.exact_edge_triangles(edges, part=64).collect(), exact.edge_triangles(edges).collect())
    monkeypatch.setattr(trials, "local_graph", lambda *_: None)  # a graph beyond the bound takes the distributed way
    near(trials.exact_balls(edges, 2).select("x", "t", "n").collect(), exact.balls(edges, 2).select("x", "t", "n").collect())
    spec = SketchSpec(p=5)
    near(trials.ball_trials(edges, 2, spec, 1).select("x", "t", "n_est").collect(), balls.ball_sizes(edges, vst.accumulate(edges, spec), 2).local.collect())


def test_precision_is_tie_aware(spark):
    truth = spark.createDataFrame([(i, t) for i, t in enumerate([9, 7, 7, 7, 1, 0])], "x long, t long")
    est = spark.createDataFrame([(0, i, t) for i, t in enumerate([9.0, 1.0, 7.0, 8.0, 6.0, 0.0])], "seed int, x long, t_est double")
    got = {(r["k"], r["kprime"]): (r["tp"], r["fp"], r["fn"]) for r in trials.precision_trials(est, truth, ["x"], (2, 5, 100), (0.5, 1.0, 2.0)).collect()}
    assert got[2, 1] == (1, 0, 3) and got[2, 2] == (2, 0, 2) and got[2, 4] == (3, 1, 1) and got[5, 5] == (5, 0, 0) and not any(k == 100 for k, _ in got)


def test_newton_steps_follow_the_likelihood():
    """Closed-form slopes equal differences of the likelihood, and no near point is likelier than the answer."""
    rng, spec = np.random.default_rng(1), SketchSpec(p=6)
    a, b = (np.minimum(rng.geometric(0.5, (30, 64)), 50).astype(np.uint8) * (rng.random((30, 64)) < 0.8) for _ in range(2))
    a[:10], b[10:15] = b[:10], 0
    counts = joint.count_arrays(a, b, spec.q + 1)
    for k, (mask, value) in enumerate(((a < b, a), (a > b, a), (b < a, b), (b > a, b), (a == b, a))):
        for i in range(30):
            assert (counts[i, k] == np.bincount(value[i][mask[i]], minlength=spec.q + 2)).all()
    theta = rng.normal(3, 1, (30, 3))
    f = lambda t: joint.log_likelihood(t, counts, spec.r, spec.q)
    grad, hess = joint.derivatives(theta, counts, spec.r, spec.q)
    for i in range(3):
        e = np.eye(3)[i] * 1e-5
        assert np.allclose((f(theta + e) - f(theta - e)) / 2e-5, grad[:, i], rtol=1e-4, atol=1e-4)
        up, down = (joint.derivatives(theta + d, counts, spec.r, spec.q)[0] for d in (e, -e))
        assert np.allclose((up - down) / 2e-5, hess[:, i], rtol=1e-4, atol=1e-3)
    size, _ = joint.joint_ml(counts, np.full((30, 3), 20.0), spec)
    best = np.log(size)
    for _ in range(200):
        move = best + rng.normal(0, 0.3, best.shape)
        assert (f(np.clip(move, joint.LOW, joint.HIGH)) <= f(best) + 1e-6).all()
