import numpy as np
import pytest
from pyspark.sql import functions as F

from vsketch.functions.estimate import alpha, beta_polynomial, estimate_array, std_error
from vsketch.functions.hashing import hash_word, index_of, rank_of
from vsketch.functions.spec import PORTABLE8, SketchSpec, assert_compatible
from vsketch.operators import joint, packed, vst


def draw(rng, r, n):
    out = np.zeros(r, np.uint8)
    np.maximum.at(out, rng.integers(0, r, n), rng.geometric(0.5, n).astype(np.uint8))
    return out


def test_alpha_and_standard_error():
    assert abs(alpha(16) - 0.6731) < 1e-4 and abs(alpha(4096) - 0.72116) < 1e-4
    assert abs(std_error(8) - 0.065) < 1e-3


@pytest.mark.parametrize("how", ["beta", "linear"])
def test_estimators_are_nearly_unbiased(how):
    rng = np.random.default_rng(1)
    for n in (10, 100, 400, 2000):
        got = estimate_array(np.array([draw(rng, 256, n) for _ in range(150)]), how)
        assert abs(got.mean() / n - 1) < 0.03 and got.std() / n < 1.3 * std_error(8)
    assert beta_polynomial(np.array([0.0]), (1.0,) * 8)[0] == 0


def test_rank_forms(spark):
    words = [0, 1, 2**51, 2**52 - 1, 2**52 + 1, 2**59]
    rows = spark.createDataFrame([(w,) for w in words], "w long")
    trail = SketchSpec(p=8, hash="portable", rank="trail")
    got = rows.select("w", rank_of(F.col("w"), PORTABLE8).alias("lead"), rank_of(F.col("w"), trail).alias("trail"), index_of(F.col("w"), PORTABLE8).alias("j")).collect()
    for w, lead, trail, j in got:
        low = w & (2**52 - 1)
        assert lead == 53 - low.bit_length() and j == w >> 52
        assert trail == (53 if low == 0 else (low & -low).bit_length())


def test_hash_forms_differ_by_seed(spark):
    row = spark.range(1).select(*(hash_word(F.lit(7), SketchSpec(hash=h, seed=s)).alias(f"{h}{s}") for h in ("xx", "portable") for s in (0, 1))).first()
    assert len(set(row)) == 4


def test_specs_are_checked():
    for bad in (dict(p=3), dict(p=19), dict(hash="no"), dict(bits=8)):
        with pytest.raises(ValueError):
            SketchSpec(**bad)
    with pytest.raises(ValueError, match="seed"):
        assert_compatible(SketchSpec(seed=0), SketchSpec(seed=1))
    assert_compatible(SketchSpec(dense_at=0.5), SketchSpec())


def test_merge_laws_and_packed_forms(spark):
    edges = spark.range(0, 600).select((F.col("id") % 7).alias("u"), (F.col("id") + 10).alias("v"))
    spec = SketchSpec(p=6)
    whole = vst.accumulate(edges, spec)
    parts = [vst.accumulate(edges.filter(F.col("v") % 3 == i), spec) for i in range(3)]
    want = sorted(map(tuple, whole.regs.collect()))
    assert sorted(map(tuple, parts[0].merged(parts[1]).merged(parts[2]).merged(parts[0]).regs.collect())) == want
    assert sorted(map(tuple, parts[2].absorb(edges).regs.collect())) == want
    form = packed.pack(whole.regs, spec)
    modes = {r["mode"] for r in form.collect()}
    assert modes == {packed.SPARSE, packed.DENSE}
    assert sorted(map(tuple, packed.unpack(form, spec).collect())) == want
    mixed = packed.pack(parts[0].regs, spec, dense_only=True).unionByName(packed.pack(parts[1].regs, spec)).unionByName(packed.pack(parts[2].regs, spec))
    assert sorted(map(tuple, packed.unpack(packed.merge_packed(mixed, spec), spec).collect())) == want
    small = packed.merge_packed(mixed, spec, held=3 * spec.r)  # a table of three sketches: ids go on after it is emptied
    assert sorted(map(tuple, packed.unpack(small, spec).collect())) == want
    a = {r[0]: r[1] for r in packed.measure_packed(form, spec, "beta").collect()}
    b = {r[0]: r[1] for r in whole.degree("beta").collect()}
    assert a.keys() == b.keys() and all(abs(a[x] - b[x]) < 1e-6 for x in a)


def test_unknown_vertices_and_save(spark, tmp_path):
    table = vst.accumulate(spark.createDataFrame([(1, 2)], "u long, v long"), PORTABLE8)
    ids = spark.createDataFrame([(1,), (99,)], "x long")
    got = {r[0]: r[1] for r in table.degree(ids=ids).collect()}
    assert got[99] == 0 and abs(got[1] - 1) < 0.1
    table.save(str(tmp_path / "t"))
    back = vst.load(spark, str(tmp_path / "t"))
    assert back.spec == table.spec and back.regs.count() == 2


def test_joint_likelihood_beats_naive():
    rng, spec = np.random.default_rng(3), SketchSpec(p=8)
    for a, b, x in ((100, 100, 20), (5000, 5000, 500)):
        ra, rb = [], []
        for _ in range(40):
            s = draw(rng, 256, x)
            ra.append(np.maximum(draw(rng, 256, a), s))
            rb.append(np.maximum(draw(rng, 256, b), s))
        ra, rb = np.array(ra), np.array(rb)
        na, nb, nu = (estimate_array(m) for m in (ra, rb, np.maximum(ra, rb)))
        naive = na + nb - nu
        size, se = joint.joint_ml(joint.count_arrays(ra, rb, spec.q + 1), np.stack([na - naive, nb - naive, naive], 1), spec)
        assert np.abs(size[:, 2] - x).mean() < np.abs(naive - x).mean()
        assert np.isfinite(se).all()


def test_count_identities():
    rng = np.random.default_rng(5)
    a, b = np.array([draw(rng, 64, 50)]), np.array([draw(rng, 64, 80)])
    c = joint.count_arrays(a, b, 60)[0].sum(1)
    assert c[0] == c[3] and c[1] == c[2] and c[0] + c[1] + c[4] == 64
