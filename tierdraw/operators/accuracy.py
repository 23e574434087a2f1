"""Bias, distortion, variance and decay of compressors, measured and in closed form; accuracy of models."""

from __future__ import annotations

from collections.abc import Sequence

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .level_probs import alpha_profile, deltas
from .levels import LevelFamily
from .vectors import norms, rank_by_magnitude, subtract


def distortion(coords: DataFrame, compressed: DataFrame, keys: Sequence[str]) -> DataFrame:
    """keys, err2 (squared distance), rel (over the squared norm), alpha (1 - rel)."""
    err = subtract(compressed, coords, keys).groupBy(*keys).agg(F.sum(F.col("val") * F.col("val")).alias("err2"))
    both = err.join(coords.groupBy(*keys).agg(F.sum(F.col("val") * F.col("val")).alias("norm2")), list(keys))
    rel = F.when(F.col("norm2") > 0, F.col("err2") / F.col("norm2")).otherwise(0.0)
    return both.select(*keys, "err2", rel.alias("rel"), (1 - rel).alias("alpha"))


def bias(coords: DataFrame, mean: DataFrame, keys: Sequence[str]) -> DataFrame:
    """keys, bias: distance of a mean estimate from the vector."""
    return distortion(coords, mean, keys).select(*keys, F.sqrt("err2").alias("bias"))


def contraction(coords: DataFrame, keys: Sequence[str], family: LevelFamily) -> DataFrame:
    """keys, level, delta, alpha of a ladder of segments."""
    return alpha_profile(deltas(family.prepare(coords, keys), keys, family), keys)


def adaptive_variance(coords: DataFrame, keys: Sequence[str], family: LevelFamily) -> DataFrame:
    """keys, variance, omega with adaptive probabilities: (sum of residual norms)**2 less the squared norm."""
    sums = deltas(family.prepare(coords, keys), keys, family).groupBy(*keys).agg(F.sum("delta").alias("sd"))
    rows = sums.join(norms(coords, keys), list(keys))
    return rows.select(*keys, (F.col("sd") * F.col("sd") - F.col("l2sq")).alias("variance"), F.when(F.col("l2sq") > 0, F.col("sd") * F.col("sd") / F.col("l2sq") - 1).otherwise(0.0).alias("omega"))


def closed_form(coords: DataFrame, keys: Sequence[str], method: str, k: int = 1) -> DataFrame:
    """keys, variance, omega of: fixed (geometric probabilities), float, rand (k values), quantize (one step)."""
    rows = norms(coords, keys)
    if method == "float":
        from .vectors import floor_log2

        a = F.abs("val")
        lead = F.when(a > 0, F.pow(F.lit(2.0), floor_log2(a).cast("double"))).otherwise(0.0)
        part = lead * (1 - 2.0**-52) * (a - lead) - (a - lead) * (a - lead)
        rows = rows.join(coords.groupBy(*keys).agg(F.sum(part).alias("fv")), list(keys))
    variance = {
        "fixed": lambda: (1 - 2.0**-63) * F.col("top") * F.col("l1") - F.col("l2sq"),
        "float": lambda: F.col("fv"),
        "rand": lambda: (F.col("d") / k - 1) * F.col("l2sq"),
        "quantize": lambda: F.sqrt("l2sq") * F.col("l1") - F.col("l2sq"),
    }[method]()
    return rows.select(*keys, variance.alias("variance"), F.when(F.col("l2sq") > 0, variance / F.col("l2sq")).otherwise(0.0).alias("omega"))


def decay_rate(coords: DataFrame, keys: Sequence[str]) -> DataFrame:
    """keys, d, r (-2 times the slope of ln abs(val) over rank; not a number for one coordinate, as in SQL), regime (1: r d < 1, 2: r < 1 < r d, 0: else)."""
    ranked = rank_by_magnitude(coords.filter("val <> 0"), keys)
    n, slope = F.count(F.lit(1)), F.regr_slope(F.log(F.abs("val")), (F.col("rk") - 1).cast("double"))
    fit = ranked.groupBy(*keys).agg(n.alias("d"), (-2 * F.when(n > 1, slope).otherwise(float("nan"))).alias("r"))
    return fit.withColumn("regime", F.when(F.col("r") * F.col("d") < 1, 1).when((F.col("r") < 1) & (F.col("r") * F.col("d") > 1), 2).otherwise(0))


def variance_split(estimates: DataFrame) -> DataFrame:
    """Parts of the variance of compressed samples per pos: within samples (compression) and between samples (noise). ``estimates``: sample, draw, pos, val."""
    inner = estimates.groupBy("sample", "pos").agg(F.avg("val").alias("m"), F.var_pop("val").alias("v"))
    return inner.groupBy("pos").agg(F.avg("v").alias("compression"), F.var_pop("m").alias("noise"))


def aggregate_variance(messages: DataFrame, truth: DataFrame, m: int) -> DataFrame:
    """step, v2: squared distance of the averaged message from the gradient. ``messages``: step, worker, pos, val; ``truth``: step, pos, val."""
    mean = messages.groupBy("step", "pos").agg((F.sum("val") / m).alias("val"))
    return subtract(mean, truth, ["step"]).groupBy("step").agg(F.sum(F.col("val") * F.col("val")).alias("v2"))


def heterogeneity(worker_grads: DataFrame, grad: DataFrame) -> DataFrame:
    """xi2_mean, xi2_max of the squared distances of workers' gradients from the whole one."""
    rows = worker_grads.join(grad.select("pos", F.col("val").alias("g")), "pos")
    per = rows.groupBy("worker").agg(F.sum((F.col("val") - F.col("g")) * (F.col("val") - F.col("g"))).alias("x"))
    return per.agg(F.avg("x").alias("xi2_mean"), F.max("x").alias("xi2_max"))


def evaluate(scored: DataFrame) -> DataFrame:
    """n, acc, balanced_acc, auc of rows (label 0/1, score); ties of scores count one half."""
    by_score = scored.groupBy("score").agg(F.sum("label").alias("p"), F.sum(1 - F.col("label")).alias("n"))
    below = Window.partitionBy(F.lit(1)).orderBy("score").rowsBetween(Window.unboundedPreceding, -1)
    auc = by_score.withColumn("nb", F.coalesce(F.sum("n").over(below), F.lit(0))).agg((F.sum(F.col("p") * (F.col("nb") + F.col("n") / 2)) / (F.sum("p") * F.sum("n"))).alias("auc"))
    hit = (F.col("score") >= 0.5) == (F.col("label") == 1)
    rate = lambda c: F.avg(F.when(F.col("label") == c, hit.cast("double")))
    return scored.agg(F.count(F.lit(1)).alias("n"), F.avg(hit.cast("double")).alias("acc"), ((rate(0) + rate(1)) / 2).alias("balanced_acc")).crossJoin(auc)


def seed_summary(log: DataFrame) -> DataFrame:
    """Mean and deviation over seeds of each (method, m, k_frac, step)."""
    return log.groupBy("method", "m", "k_frac", "step").agg(F.avg("acc").alias("acc"), F.stddev("acc").alias("acc_sd"), F.avg("loss").alias("loss"), F.avg("bits_cum").alias("bits_cum"), F.count(F.lit(1)).alias("seeds"))


def speedup(reached: DataFrame, few: int = 4, many: int = 32) -> DataFrame:
    """method, steps at ``few`` and at ``many`` workers, ratio. ``reached``: method, m, step."""
    wide = reached.groupBy("method").pivot("m", [few, many]).agg(F.avg("step"))
    return wide.select("method", F.col(str(few)).alias("few"), F.col(str(many)).alias("many"), (F.col(str(few)) / F.col(str(many))).alias("ratio"))


def self_bound(log: DataFrame, smoothness: float, best: float) -> DataFrame:
    """Steps with holds: squared gradient norm at most 2 L (f - f*)."""
    return log.withColumn("holds", F.col("grad_norm2") <= 2 * smoothness * (F.col("loss") - best) * (1 + 1e-9) + 1e-12)
