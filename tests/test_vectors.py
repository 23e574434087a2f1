"""Hand-computed vector, closed forms, equivalences and edges of the compressors and ladders."""

import math

import numpy as np
import pytest
from pyspark.sql import functions as F

from tierdraw.operators import accuracy, base_compressors as b, vectors
from tierdraw.operators.level_probs import custom_probs, deltas, energy_share_probs, geometric_probs, residual_norm_probs, uniform_probs
from tierdraw.operators.levels import CustomLevels, EntropyGridLevels, FixedPointLevels, FloatPointLevels, GridRoundingLevels, SegmentLevels
from tierdraw.operators.telescoping import enumerate_expectation, exact_variance, level_estimate, replicate_mean, tier_estimate, two_pass_estimate

K = ["id"]
W = [4.0, -3.0, 2.0, -1.0, 0.5]


def coords(spark, *vecs):
    return spark.createDataFrame([(i, p, float(v)) for i, w in enumerate(vecs) for p, v in enumerate(w)], "id int, pos long, val double")


def dense(df, d, key=0):
    out = [0.0] * d
    for r in df.filter(F.col("id") == key).collect():
        out[r["pos"]] = r["val"]
    return out


def test_hand_vector(spark):
    c = coords(spark, W)
    assert dense(b.top_k(c, K, 2), 5) == [4, -3, 0, 0, 0]
    assert accuracy.distortion(c, b.top_k(c, K, 2), K).first()["alpha"] == pytest.approx(25 / 30.25)
    family = SegmentLevels(2)
    q = {r["level"]: r["q"] for r in residual_norm_probs(family.prepare(c, K), K, family).collect()}
    assert q == pytest.approx({1: 0.646323, 2: 0.289045, 3: 0.064632}, abs=1e-6)
    assert accuracy.adaptive_variance(c, K, family).first()["variance"] == pytest.approx(29.596748, abs=1e-6)
    assert accuracy.adaptive_variance(c, K, SegmentLevels(1)).first()["variance"] == pytest.approx(80)
    assert accuracy.closed_form(c, K, "rand", 2).first()["variance"] == pytest.approx(45.375)
    assert accuracy.closed_form(c, K, "fixed").first()["variance"] == pytest.approx(11.75)
    assert accuracy.closed_form(c, K, "float").first()["variance"] == pytest.approx(1.0)
    assert accuracy.closed_form(c, K, "quantize").first()["variance"] == pytest.approx(27.5)
    assert dense(b.round_to_grid(c, K, 2), 5) == pytest.approx([8 / 3, -8 / 3, 8 / 3, 0, 0])
    assert dense(FloatPointLevels().prepare(c, K).select("id", "pos", (F.signum("val") * F.col("lead")).alias("val")), 5) == [4, -2, 2, -1, 0.5]


@pytest.mark.parametrize("family,depth", [(SegmentLevels(2), 0), (SegmentLevels(1), 0), (SegmentLevels(9), 0), (FixedPointLevels(), 63), (FloatPointLevels(), 52), (FloatPointLevels(base="zero"), 52), (GridRoundingLevels(6), 6)])
def test_unbiased_and_variance(spark, family, depth):
    """The enumerated mean is the vector, zero vectors and single coordinates included; the enumerated variance is the measured one."""
    vecs = [W, [0.0, 0.0], [-2.5], [1.0, -1.0, 1.0], [2.0**-29, -(2.0**-47), 2.0**-31]]
    c = coords(spark, *vecs)
    for probs in ["adaptive", *([geometric_probs(spark, depth), uniform_probs(spark, depth)] if depth else [])]:
        mean = enumerate_expectation(c, K, family, probs)
        for i, w in enumerate(vecs):
            assert dense(mean, len(w), i) == pytest.approx(w, abs=2.0**-60 * max(map(abs, w)) + 1e-300, rel=1e-12)
    assert all(r["variance"] >= -1e-9 for r in exact_variance(c, K, family).collect())


def test_variance_orders(spark):
    c = coords(spark, np.random.default_rng(1).normal(size=32).tolist())
    family = FixedPointLevels()
    v = lambda p: exact_variance(c, K, family, p).first()["variance"]
    assert v("adaptive") <= v(geometric_probs(spark, 63)) <= v(uniform_probs(spark, 63))
    assert v(geometric_probs(spark, 63)) == pytest.approx(accuracy.closed_form(c, K, "fixed").first()["variance"])
    assert exact_variance(c, K, FloatPointLevels(), geometric_probs(spark, 52)).first()["variance"] == pytest.approx(accuracy.closed_form(c, K, "float").first()["variance"])
    seg = SegmentLevels(4)
    assert exact_variance(c, K, seg, uniform_probs(spark, 8)).first()["variance"] == pytest.approx(accuracy.closed_form(c, K, "rand", 4).first()["variance"])
    assert exact_variance(c, K, seg).first()["variance"] == pytest.approx(accuracy.adaptive_variance(c, K, seg).first()["variance"])
    profile = accuracy.contraction(c, K, seg).select("id", "level", "alpha")
    a = {r["level"]: r["q"] for r in energy_share_probs(profile, K).collect()}
    p = {r["level"]: r["q"] for r in residual_norm_probs(seg.prepare(c, K), K, seg).collect()}
    assert a == pytest.approx(p)


def test_sampled_mean(spark):
    c = coords(spark, W)
    got = dense(tier_estimate(c, K, SegmentLevels(2), "adaptive", 3, reps=2000), 5)
    sd = math.sqrt(29.6 / 2000)
    assert np.abs(np.array(got) - W).max() < 5 * sd


def test_equivalences(spark):
    c = coords(spark, np.random.default_rng(2).normal(size=12).tolist())
    assert dense(b.segment_top_k(c, K, 3, 1), 12) == dense(b.top_k(c, K, 3), 12)
    assert dense(b.top_k(c, K, 12), 12) == dense(c, 12) and b.top_k(c, K, 0).count() == 0
    assert dense(b.rand_k(c, K, 12, 1), 12) == pytest.approx(dense(c, 12))
    one = tier_estimate(c, K, SegmentLevels(1), "adaptive", 5)
    assert abs(one.first()["val"]) == pytest.approx(sum(map(abs, dense(c, 12))))
    window = {(r["pos"], r["rk"]) for r in vectors.rank_by_magnitude(c, K).collect()}
    assert window == {(r["pos"], r["rk"]) for r in vectors.rank_by_magnitude(c, K, "histogram").collect()}
    blocks = vectors.to_blocks(c, K, 5)
    assert blocks.count() == 3 and dense(vectors.from_blocks(blocks, K, 5).filter("pos < 12"), 12) == pytest.approx(dense(c, 12))


def test_custom_entropy_and_two_pass(spark):
    c = coords(spark, W, [0.0, 1.0, 0.0, 0.0, 0.0])
    family = CustomLevels([lambda x, k: b.top_k(x, k, 1), lambda x, k: b.top_k(x, k, 3), lambda x, k: x])
    assert dense(enumerate_expectation(c, K, family, uniform_probs(spark, 3)), 5) == pytest.approx(W)
    ladder = EntropyGridLevels.fit(c, K, [0.5, 1.5])
    assert dense(enumerate_expectation(c, K, ladder, uniform_probs(spark, 3)), 5) == pytest.approx(W)
    at = lambda rows: vectors.rank_by_magnitude(rows, K).filter(F.col("rk") <= F.col("level")).select("id", "pos", "val")
    out = two_pass_estimate(c, K, at, uniform_probs(spark, 5), 1).filter("val <> 0").collect()
    assert all(abs(r["val"]) == pytest.approx(5 * abs((W if r["id"] == 0 else [0, 1, 0, 0, 0])[r["pos"]])) for r in out)


def test_scalar_levels(spark):
    rows = [(i, l, float(l * l), q) for i in range(300) for l, q in ((0, None), (1, 0.5), (2, 0.5))]
    values = spark.createDataFrame(rows, "id int, level int, value double, q double")
    from tierdraw.functions.draws import hash_uniform

    est = level_estimate(values, K, hash_uniform(1, F.col("id")))
    assert {r["estimate"] for r in est.collect()} == {2.0, 6.0}
    assert replicate_mean(est.withColumn("all", F.lit(1)), ["all"]).first()["estimate"] == pytest.approx(4.0, abs=0.6)


def test_guards(spark):
    with pytest.raises(ValueError):
        custom_probs(spark.createDataFrame([(1, 0.7), (2, 0.0)], "level int, q double"))
    c = coords(spark, [1.0, float("nan"), float("inf")])
    assert vectors.reject_nonfinite(c).count() == 1
    empty = c.limit(0)
    assert tier_estimate(empty, K, SegmentLevels(2)).count() == 0 and deltas(FixedPointLevels().prepare(empty, K), K, FixedPointLevels()).count() == 0


@pytest.mark.parametrize("level,rel", [(1, 1.0), (2, 0.277), (4, 0.0113)])
def test_grid_shrinks_to_identity(spark, level, rel):
    c = vectors.to_coords(spark.read.parquet("/root/testdata/sf0.001/embeddings.parquet").withColumnRenamed("vec_id", "id"), K, "embedding")
    got = accuracy.distortion(c, b.round_to_grid(c, K, level), K).agg(F.avg("rel")).first()[0]
    assert got == pytest.approx(rel, rel=0.2)
