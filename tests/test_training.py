import pytest
from pyspark.sql import functions as F

from tierdraw.operators import accuracy, cost
from tierdraw.operators.levels import SegmentLevels
from tierdraw.plans import losses, theory, trainers, workloads
from tierdraw.sources import catalog

SF = "/root/testdata/sf0.001"


@pytest.fixture(scope="module")
def samples(spark):
    return losses.lineitem_squares(catalog.load(spark, SF, "lineitem"), 4).cache()


def test_plain_is_full_batch_and_marina_with_p_one(spark, samples):
    a, bits = trainers.fit(samples, 4, trainers.Uncompressed(), 3, 0.5, 4)
    one = samples.withColumn("worker", F.lit(0))
    whole = losses.gradient(one, [0.0] * 4).orderBy("pos").collect()
    assert a[1] == pytest.approx([-0.5 * r["val"] for r in whole], rel=0.05)
    m, _ = trainers.fit(samples, 4, trainers.MarinaTemplate(trainers.top_k(1), 1.0), 3, 0.5, 4)
    assert m[-1] == pytest.approx(a[-1]) and bits == [0, 1024, 2048, 3072]


def test_feedback_with_all_coordinates_is_plain(spark, samples):
    a, _ = trainers.fit(samples, 4, trainers.Uncompressed(), 3, 0.5, 4)
    e, _ = trainers.fit(samples, 4, trainers.ErrorFeedbackMomentum(4, beta=1.0), 3, 0.5, 4)
    assert e[-1] == pytest.approx(a[-1])


def test_tier_training_lowers_loss(spark, samples):
    history, _ = trainers.fit(samples, 4, trainers.TierDraw(SegmentLevels(2)), 6, 0.2, 4, seed=3)
    first, last = (losses.squares_value(samples, x).first()[0] for x in (history[0], trainers.average_iterate(history[2:])))
    assert last < first


def test_bound_holds_on_squares(spark, samples):
    """Mean loss of the averaged iterate stays below the bound with derived constants."""
    import numpy as np

    rows = samples.select("a", "y").limit(4000).collect()
    a, y = np.array([r["a"] for r in rows]), np.array([r["y"] for r in rows])
    best, h = np.linalg.lstsq(a, y, rcond=None)[0], a.T @ a / len(a)
    smooth, dist = np.linalg.eigvalsh(h)[-1], np.sqrt(best @ best)
    g = (a * (a @ np.zeros(4) - y)[:, None])
    p = theory.Problem(smooth, float(np.sqrt(g.var(axis=0).sum())), float(dist), 1.0, 20, 4, omega=3.0)
    history, _ = trainers.fit(samples, 4, trainers.TierDraw(SegmentLevels(1)), 20, theory.step_size("homog_convex", p), 4, fraction=0.5, seed=2)
    x = np.array(trainers.average_iterate(history))
    gap = 0.5 * ((a @ x - y) ** 2).mean() - 0.5 * ((a @ best - y) ** 2).mean()
    assert gap <= theory.bound("homog_convex", p)


def test_divergence_fixture():
    assert workloads.divergence("topk") > 1e6
    assert max(workloads.divergence(m) for m in ("tier_segment", "randk", "ef21m", "uncompressed")) < 1e-3


def test_theory_numbers():
    for r, s, d, exact, approx in ((0.1, 5, 640, 7.041623, 7), (0.1, 10, 640, 3.082988, 3), (0.02, 10, 2000, 19.016664, 19)):
        assert theory.decay_variance(r, s, d) == pytest.approx(exact, abs=1e-5)
        assert theory.decay_variance(r, s, d, "approx") == pytest.approx(approx)
    p = theory.Problem(1, 1, 1, 1, 100, 4, 2.0, 0.5)
    assert theory.bound("homog_convex", p) > theory.bound("homog_convex", p, "printed")
    assert theory.max_workers(1e6, "tier") == pytest.approx(1000) and theory.max_workers(1e6, "feedback") == pytest.approx(100)


def test_quantised_methods_order(spark):
    """At two bits the level-sampled fixed point ends above stochastic rounding and plain truncation."""
    log = workloads.curve_image_quantized(spark, SF, seeds=2, steps=30).filter("step = 30 and m = 32").groupBy("method").agg(F.avg("acc").alias("acc")).collect()
    acc = {r["method"]: r["acc"] for r in log}
    assert acc["tier_fixed"] > acc["qsgd_2bit"] and acc["tier_fixed"] > acc["fixed_2bit"]


def test_costs_and_reports(spark):
    d = F.lit(5)
    got = spark.range(1).select(cost.message_bits("fixed_tier", d), cost.message_bits("float_tier", d), cost.message_bits("sparse", d, k=2), cost.index_bits(F.lit(64)), cost.index_bits(F.lit(65)), cost.index_bits(F.lit(1))).first()
    assert tuple(got) == (80, 71, 128, 6, 7, 0)
    log = spark.createDataFrame([("a", s, m, 1.0, t, 10, 0.0, t / 10) for s in range(2) for m in (4, 32) for t in (1, 5, 9)], "method string, seed int, m int, k_frac double, step int, bits long, loss double, acc double")
    cum = cost.cumulative(log)
    assert cost.first_to_reach(cum, 0.5).first()["bits_cum"] == 20
    assert accuracy.seed_summary(cum).count() == 6 and accuracy.speedup(cost.first_to_reach(cum, 0.5, "step")).first()["ratio"] == 1.0
    scored = spark.createDataFrame([(1, 0.9), (0, 0.2), (1, 0.4), (0, 0.4)], "label int, score double")
    r = accuracy.evaluate(scored).first()
    assert r["auc"] == pytest.approx(0.875) and r["acc"] == 0.75


def test_catalog(spark, tmp_path):
    with pytest.raises(TypeError):
        spark.range(3).select(F.col("id").cast("string").alias("vec_id")).write.parquet(str(tmp_path / "embeddings.parquet"))
        catalog.load(spark, str(tmp_path), "embeddings")
    out = str(tmp_path / "log")
    df = spark.range(4).select((F.col("id") % 2).alias("step"), "id")
    catalog.save(df, out, ["step"])
    catalog.save(df.filter("step = 1"), out, ["step"])
    assert spark.read.parquet(out).count() == 4
    spark.range(2).write.json(str(tmp_path / "j"))
    assert catalog.read(spark, str(tmp_path / "j"), "json", df.select("id").schema).count() == 2
