"""The registered queries of the methods, baselines, measures and operators, and their SQL."""

from __future__ import annotations

from collections.abc import Callable

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions import sql_surface
from ..functions.draws import drawn_by_events, weighted_coordinate
from ..operators import accuracy, base_compressors, cost, vectors
from ..operators.level_probs import cost_aware_probs, custom_probs, deltas, energy_share_probs, geometric_probs, residual_norm_probs, uniform_probs
from ..operators.levels import CustomLevels, FixedPointLevels, FloatPointLevels, GridRoundingLevels, LevelFamily, SegmentLevels
from ..operators.telescoping import enumerate_expectation, exact_variance, tier_estimate
from ..oracle import sql
from ..oracle.training import run
from ..sources.catalog import load
from ..streaming import arrivals, online
from . import checks, constants, losses, relational, theory, trainers, workloads

K = ["vec_id"]
Query = Callable[[SparkSession, str], DataFrame]


def embedding_coords(spark: SparkSession, sf: str) -> DataFrame:
    return vectors.to_coords(load(spark, sf, "embeddings", "vec_id", "embedding"), K, "embedding")


def _rounded(df: DataFrame, *names: str, digits: int = 6) -> DataFrame:
    return df.select(*[(F.round(c, digits) + F.lit(0.0)).alias(c) if c in names else F.col(c) for c in df.columns])


def _on_coords(f: Callable[[DataFrame], DataFrame], *names: str) -> Query:
    return lambda spark, sf: _rounded(f(embedding_coords(spark, sf)), *(names or ("val",)))


def _family(name: str, n: int) -> LevelFamily:
    return {"segment": lambda: SegmentLevels(n), "fixed": FixedPointLevels, "float": FloatPointLevels, "float_zero": lambda: FloatPointLevels(base="zero"), "rtn": lambda: GridRoundingLevels(n)}[name]()


def _tier(name: str, n: int = 0, how: str = "adaptive", seed: int = 0) -> Query:
    def query(spark: SparkSession, sf: str) -> DataFrame:
        probs = "adaptive" if how == "adaptive" else geometric_probs(spark, int(how))
        out = tier_estimate(embedding_coords(spark, sf), K, _family(name, n), probs, seed)
        return _rounded(_rounded(out, "q", digits=9), "val")

    return query


def _expect(name: str, n: int = 0, how: str = "adaptive") -> Query:
    def query(spark: SparkSession, sf: str) -> DataFrame:
        probs = "adaptive" if how == "adaptive" else geometric_probs(spark, int(how))
        return _rounded(enumerate_expectation(embedding_coords(spark, sf), K, _family(name, n), probs), "val")

    return query


def _variance(name: str, n: int = 0, how: str = "adaptive") -> Query:
    def query(spark: SparkSession, sf: str) -> DataFrame:
        probs = "adaptive" if how == "adaptive" else geometric_probs(spark, int(how))
        return _rounded(exact_variance(embedding_coords(spark, sf), K, _family(name, n), probs), "second_moment", "variance", "norm2")

    return query


def _deltas(name: str, n: int = 0) -> Query:
    return _on_coords(lambda c: deltas(_family(name, n).prepare(c, K), K, _family(name, n)), "delta")


def _probs(name: str, n: int = 0) -> Query:
    return _on_coords(lambda c: residual_norm_probs(_family(name, n).prepare(c, K), K, _family(name, n)).drop("delta"), "q")


def _custom(c: DataFrame) -> CustomLevels:
    same = lambda x, k: x
    return CustomLevels([lambda x, k: base_compressors.top_k(x, k, 4), lambda x, k: base_compressors.round_to_grid(x, k, 4), same])


def _line_probs(spark: SparkSession, sf: str) -> DataFrame:
    """Probabilities given by a table, the shares of line numbers among all lines, and the events that draw each."""
    n = load(spark, sf, "lineitem", "l_linenumber").filter("l_linenumber is not null").groupBy(F.col("l_linenumber").alias("level")).agg(F.count(F.lit(1)).cast("double").alias("n"))
    shares = n.crossJoin(F.broadcast(n.agg(F.sum("n").alias("all")))).select("level", (F.col("n") / F.col("all")).alias("q"))  # one row
    return drawn_by_events(custom_probs(shares), load(spark, sf, "events", "event_id"))


def _drawn_probs(levels: Callable[[SparkSession], DataFrame]) -> Query:
    """Static probabilities, and the events that draw each level."""
    return lambda spark, sf: drawn_by_events(levels(spark), load(spark, sf, "events", "event_id"))


def _tier_custom(spark: SparkSession, sf: str) -> DataFrame:
    """Messages of a ladder put together from other compressors: largest four, grid of four bits, all."""
    c = embedding_coords(spark, sf)
    return _rounded(_rounded(tier_estimate(c, K, _custom(c), uniform_probs(spark, 3)), "q", digits=9), "val")


def _alpha(spark: SparkSession, sf: str) -> DataFrame:
    return _rounded(accuracy.contraction(embedding_coords(spark, sf), K, SegmentLevels(8)), "delta", "alpha")


def _energy(spark: SparkSession, sf: str) -> DataFrame:
    profile = accuracy.contraction(embedding_coords(spark, sf), K, SegmentLevels(8)).select("vec_id", "level", "alpha")
    return _rounded(energy_share_probs(profile, K).drop("alpha"), "q")


def _cost_aware(spark: SparkSession, sf: str) -> DataFrame:
    family = GridRoundingLevels(8)
    table = deltas(family.prepare(embedding_coords(spark, sf), K), K, family)
    return _rounded(cost_aware_probs(table, K, family.value_bits(F.lit(64), F.col("level"))).drop("delta"), "q")


def _expected_rtn_bits(spark: SparkSession, sf: str) -> DataFrame:
    family = GridRoundingLevels(8)
    table = residual_norm_probs(family.prepare(embedding_coords(spark, sf), K), K, family)
    return _rounded(table.groupBy("vec_id").agg(F.sum(F.col("q") * family.value_bits(F.lit(64), F.col("level"))).alias("bits")), "bits", digits=4)


def _bits(spark: SparkSession, sf: str) -> DataFrame:
    """Bits of a message of each kind over the values of each user's events, and how many times smaller than all values it is."""
    d = F.col("d")
    kinds = [("uncompressed", {}), ("sparse", {"k": 10}), ("fixed_tier", {}), ("float_tier", {}), ("fixed", {"bits": 1}), ("float", {"bits": 4}), ("stochastic", {"bits": 2}), ("grid", {"bits": 4}), ("grid_tier", {"bits": 3, "depth": 8})]
    rows = F.array(*[F.struct(F.lit(k).alias("kind"), cost.message_bits(k, d, **p).cast("long").alias("bits")) for k, p in kinds])
    sent = load(spark, sf, "events", "user_id").groupBy("user_id").agg(F.count(F.lit(1)).alias("d"))
    return sent.select("user_id", "d", F.explode(rows).alias("x")).select("user_id", "x.kind", "x.bits", F.round(cost.ratio(F.col("x.bits"), d), 6).alias("ratio"))


def _omega(spark: SparkSession, sf: str) -> DataFrame:
    """Mean relative variance of every method over the vectors."""
    c = embedding_coords(spark, sf)
    parts = [(f"segment_{s}", accuracy.adaptive_variance(c, K, SegmentLevels(s))) for s in (1, 4, 8, 16, 32)]
    parts += [(f"rand_{k}", accuracy.closed_form(c, K, "rand", k)) for k in (1, 4, 8, 16, 32)]
    parts += [(m, accuracy.closed_form(c, K, m)) for m in ("fixed", "float", "quantize")]
    out = None
    for name, df in parts:
        row = df.agg(F.round(F.avg("omega"), 6).alias("omega")).select(F.lit(name).alias("method"), "omega")
        out = row if out is None else out.union(row)
    return out


def _omega_sql() -> str:
    segs = [f"SELECT 'segment_{s}' AS method, round(avg(x), 6) AS omega FROM (SELECT sum(dl) * sum(dl) / any_value(l2sq) - 1 AS x FROM (SELECT vec_id, ceil(rk / {s}.0) AS g, sqrt(sum(val * val)) AS dl FROM r GROUP BY 1, 2) JOIN t USING (vec_id) GROUP BY vec_id)" for s in (1, 4, 8, 16, 32)]
    rands = [f"SELECT 'rand_{k}', round(avg(d / {k}.0 - 1), 6) FROM t" for k in (1, 4, 8, 16, 32)]
    fv = f"({sql.LEAD} * (1 - pow(2, -52)) * (abs(val) - {sql.LEAD}) - (abs(val) - {sql.LEAD}) * (abs(val) - {sql.LEAD}))"
    others = ["SELECT 'fixed', round(avg((1 - pow(2, -63)) * top * l1 / l2sq - 1), 6) FROM t", f"SELECT 'float', round(avg(f / l2sq), 6) FROM (SELECT vec_id, sum({fv}) AS f FROM c WHERE val <> 0 GROUP BY vec_id) JOIN t USING (vec_id)", "SELECT 'quantize', round(avg(l1 / sqrt(l2sq) - 1), 6) FROM t"]
    return sql.with_(sql.C, sql.RANKED, sql.TOP, select=" UNION ALL ".join([*segs, *rands, *others]))


def _decay(spark: SparkSession, sf: str) -> DataFrame:
    return _rounded(accuracy.decay_rate(embedding_coords(spark, sf), K), "r")


def _decay_forms(spark: SparkSession, sf: str) -> DataFrame:
    """Variance of segments of each vector, measured, and by the closed forms at the rate of decay fitted to its magnitudes."""
    c = embedding_coords(spark, sf)
    fit, out = accuracy.decay_rate(c, K).filter("r > 0"), None
    for s in (4, 8):
        exact, approx = (theory.decay_variance(F.col("r"), s, F.col("d"), form, F.exp) for form in ("exact", "approx"))
        row = accuracy.adaptive_variance(c, K, SegmentLevels(s)).join(fit, K).select("vec_id", F.round("r", 6).alias("r"), F.lit(s).alias("s"), "d", F.round("omega", 6).alias("measured"), F.round(exact, 6).alias("exact"), F.round(approx, 6).alias("approx"))
        out = row if out is None else out.union(row)
    return out


def _decay_forms_sql() -> str:
    fit = "f AS MATERIALIZED (SELECT vec_id, count(*) AS d, -2 * regr_slope(ln(abs(val)), rk - 1) AS r FROM r WHERE val <> 0 GROUP BY vec_id)"
    one = "SELECT vec_id, {s} AS s, sum(dl) * sum(dl) / sum(dl * dl) - 1 AS measured FROM (SELECT vec_id, sqrt(sum(val * val)) AS dl FROM r GROUP BY vec_id, ceil(rk / {s}.0)) GROUP BY vec_id"
    ex = "round((1 - exp(-r * s)) / (1 - exp(-r * d)) * pow((1 - exp(-r * d / 2.0)) / (1 - exp(-r * s / 2.0)), 2) - 1, 6)"
    return sql.with_(sql.C, sql.RANKED, fit, "m AS (" + " UNION ALL ".join(one.format(s=s) for s in (4, 8)) + ")", select=f"SELECT vec_id, round(r, 6) AS r, s, d, round(measured, 6) AS measured, {ex} AS exact, round(4 / (r * s) - 1, 6) AS approx FROM m JOIN f USING (vec_id) WHERE r > 0")


def _customer_prices(spark: SparkSession, sf: str) -> DataFrame:
    """Adaptive segments on vectors of very different lengths: the prices of each customer's lines."""
    lines = load(spark, sf, "lineitem", "l_orderkey", "l_linenumber", "l_extendedprice").join(load(spark, sf, "orders", "o_orderkey", "o_custkey"), F.col("l_orderkey") == F.col("o_orderkey"))
    c = lines.select(F.col("o_custkey").alias("vec_id"), (F.col("l_orderkey") * 8 + F.col("l_linenumber")).alias("pos"), (F.col("l_extendedprice") / 1000).alias("val"))
    return accuracy.adaptive_variance(c, K, SegmentLevels(4)).select("vec_id", F.round("omega", 6).alias("omega"))


def _user_values(spark: SparkSession, sf: str) -> DataFrame:
    """The same on skewed magnitudes: the values of each user's events, with the fitted rate of decay."""
    c = load(spark, sf, "events", "user_id", "event_id", "value").select(F.col("user_id").alias("vec_id"), F.col("event_id").alias("pos"), F.col("value").alias("val"))
    whole = vectors.norms(c, K).select("vec_id", "d")  # the rate is fitted to magnitudes above zero, the length counts all
    rows = accuracy.adaptive_variance(c, K, SegmentLevels(4)).join(accuracy.decay_rate(c, K).drop("d"), K).join(whole, K).join(accuracy.closed_form(c, K, "rand", 4).select("vec_id", F.col("omega").alias("rand_omega")), K)
    return rows.select("vec_id", "d", F.round("omega", 6).alias("omega"), F.round("rand_omega", 6).alias("rand_omega"), F.round("r", 6).alias("r"))


_RAGGED = "r AS MATERIALIZED (SELECT *, row_number() OVER (PARTITION BY vec_id ORDER BY abs(val) DESC, pos) AS rk, count(*) OVER (PARTITION BY vec_id) AS d FROM c), g AS (SELECT vec_id, any_value(d) AS d, ceil(rk / 4.0) AS seg, sqrt(sum(val * val)) AS dl, sum(val * val) AS s2 FROM r GROUP BY vec_id, ceil(rk / 4.0))"


def _message_variance(spark: SparkSession, sf: str) -> DataFrame:
    """Squared distance of the averaged message from the gradient with 2, 4, 8 and 16 workers: it falls with their number."""
    from ..functions.draws import hash_uniform

    rows = load(spark, sf, "lineitem", "l_orderkey", "l_linenumber", "l_quantity", "l_discount", "l_tax", "l_extendedprice")
    out = None
    for m in (2, 4, 8, 16):
        samples = losses.lineitem_squares(rows, m)
        grads = losses.gradient(samples, [0.0] * 4)
        truth = losses.gradient(samples.withColumn("worker", F.lit(0)), [0.0] * 4).drop("worker")
        reps = grads.withColumn("step", F.explode(F.sequence(F.lit(1), F.lit(64))))
        sent = tier_estimate(reps, ["step", "worker"], SegmentLevels(1), "adaptive", 9)
        v2 = accuracy.aggregate_variance(sent, truth.withColumn("step", F.explode(F.sequence(F.lit(1), F.lit(64)))), m)
        row = v2.agg(F.round(F.avg("v2"), 6).alias("v2")).select(F.lit(m).alias("m"), "v2")
        out = row if out is None else out.union(row)
    return out


def _bits_cumulative(spark: SparkSession, sf: str) -> DataFrame:
    """Cumulative uplink by method and day: each type of event is a worker that sends the values of its day."""
    sent = load(spark, sf, "events", "event_type", "ts").filter("ts is not null").groupBy("event_type", F.col("ts").cast("date").alias("step")).agg(F.count(F.lit(1)).alias("d"))
    per = F.array(*[F.struct(F.lit(k).alias("method"), cost.message_bits(k, F.col("d"), k=10).cast("long").alias("bits")) for k in ("uncompressed", "sparse", "fixed_tier", "float_tier")])
    log = sent.select("step", F.explode(per).alias("x")).groupBy(F.col("x.method").alias("method"), "step").agg(F.sum("x.bits").alias("bits"))
    return cost.cumulative(log.withColumn("seed", F.lit(0)).withColumn("m", F.lit(0))).select("method", "step", "bits_cum")


def _lineitem_samples(spark: SparkSession, sf: str) -> DataFrame:
    return losses.lineitem_squares(load(spark, sf, "lineitem", "l_orderkey", "l_linenumber", "l_quantity", "l_discount", "l_tax", "l_extendedprice"), 1)


def _problem_constants(spark: SparkSession, sf: str) -> DataFrame:
    """Smoothness, noise at zero, gap of the loss and squared distance to the solution."""
    p = constants.LeastSquares.of(_lineitem_samples(spark, sf), 4)
    best = p.best()
    row = (p.smoothness(), p.noise2(), p.c / 2 - p.loss(best), float(best @ best))
    return _rounded(spark.createDataFrame([row], "smoothness double, noise2 double, gap double, distance2 double"), "smoothness", "noise2", "gap", "distance2")


def _self_bound(spark: SparkSession, sf: str) -> DataFrame:
    """Losses and squared gradient norms along a run, and whether these are at most twice the smoothness times the gap."""
    samples = _lineitem_samples(spark, sf)
    p = constants.LeastSquares.of(samples, 4)
    history, _ = trainers.fit(samples, 4, trainers.Uncompressed(), 4, 0.5, 1)
    log = spark.createDataFrame([(t, p.loss(x := np.array(v)), float(p.grad(x) @ p.grad(x))) for t, v in enumerate(history)], "step int, loss double, grad_norm2 double")
    out = accuracy.self_bound(log, p.smoothness(), p.loss(p.best()))
    return out.select("step", F.round("loss", 9).alias("loss"), F.round("grad_norm2", 9).alias("grad_norm2"), "holds")


def _bias(spark: SparkSession, sf: str) -> DataFrame:
    """Distance of the mean message from the vector: of largest-k, which is biased, and of the drawn levels of segments, which is not."""
    c = embedding_coords(spark, sf)
    k = accuracy.bias(c, base_compressors.top_k(c, K, 8), K).select("vec_id", F.lit("topk").alias("method"), "bias")
    drawn = accuracy.bias(c, enumerate_expectation(c, K, SegmentLevels(8)), K).select("vec_id", F.lit("segment_levels").alias("method"), "bias")
    return _rounded(k.union(drawn), "bias")


def _fit(kind: str, steps: int = 3, eta: float = 0.5, m: int = 4, fraction: float = 0.2, seed: int = 5) -> Query:
    def query(spark: SparkSession, sf: str) -> DataFrame:
        samples = losses.lineitem_squares(load(spark, sf, "lineitem", "l_orderkey", "l_linenumber", "l_quantity", "l_discount", "l_tax", "l_extendedprice"), m)
        segment = trainers.TierDraw(SegmentLevels(1))
        method = {
            "plain": trainers.Uncompressed, "fixed": lambda: trainers.TierDraw(FixedPointLevels(), geometric_probs(spark, 63)), "segment": lambda: segment, "topk": lambda: trainers.top_k(2), "randk": lambda: trainers.rand_k(2),
            "ef21m": lambda: trainers.ErrorFeedbackMomentum(2), "marina": lambda: trainers.MarinaTemplate(segment, 0.5), "dasha": lambda: trainers.DashaTemplate(segment, 0.2),
        }[kind]()
        history, _ = trainers.fit(samples, 4, method, steps, eta, m, fraction=1.0 if kind == "dasha" else fraction, seed=seed)
        rows = [(t, p, v) for t, x in enumerate(history) for p, v in enumerate(x)]
        return _rounded(spark.createDataFrame(rows, "step int, pos long, val double"), "val")

    return query


def _marina_bits(spark: SparkSession, sf: str) -> DataFrame:
    """Cumulative bits of four workers over four steps of the full-sync template: steps whose coin sends whole gradients cost 64 bits a coordinate."""
    samples = losses.lineitem_squares(load(spark, sf, "lineitem", "l_orderkey", "l_linenumber", "l_quantity", "l_discount", "l_tax", "l_extendedprice"), 4)
    method = trainers.MarinaTemplate(trainers.TierDraw(SegmentLevels(1), bits_per=lambda n: 64), 0.5)
    _, bits = trainers.fit(samples, 4, method, 4, 0.5, 4, fraction=0.2, seed=5)
    return spark.createDataFrame(list(enumerate(bits)), "step int, bits_cum long")


def _softmax(spark: SparkSession, sf: str) -> DataFrame:
    """Two steps of adaptive segments on a classification of vectors."""
    samples = losses.embedding_classes(load(spark, sf, "embeddings", "vec_id", "embedding", "label"), 4)
    history, bits = trainers.fit(samples, 650, trainers.TierDraw(SegmentLevels(65), bits_per=lambda n: 64 * 65), 2, 1.0, 4, loss="softmax", seed=5)
    rows = [(t, b, float(sum(v * v for v in x))) for t, (x, b) in enumerate(zip(history, bits, strict=True))]
    return spark.createDataFrame(rows, "step int, bits_cum long, norm2 double").withColumn("norm2", F.round("norm2", 6))


_KINDS = ("plain_convex", "plain_nonconvex", "homog_convex", "homog_nonconvex", "heterog_convex", "heterog_nonconvex")
_GRID = [(m, t) for m in (4, 32) for t in (100, 10_000)]


def _bounds(spark: SparkSession, sf: str) -> DataFrame:
    """Bounds and step sizes for the mean and the largest relative variance that adaptive segments have on the values of users' events."""
    c = load(spark, sf, "events", "user_id", "event_id", "value").select(F.col("user_id").alias("vec_id"), F.col("event_id").alias("pos"), F.col("value").alias("val"))
    seen = accuracy.adaptive_variance(c, K, SegmentLevels(4)).agg(F.array(F.round(F.avg("omega"), 6), F.round(F.max("omega"), 6)).alias("o"))

    def grid(parts):
        for part in parts:
            rows = []
            for om in part["omega"]:
                for m, t in _GRID:
                    p = theory.Problem(1.0, 1.0, 1.0, 1.0, t, m, om, 0.5)
                    rows += [(k, c, om, m, t, theory.bound(k, p, c), theory.step_size(k, p, c)) for k in _KINDS for c in ("printed", "derived")]
            yield pd.DataFrame(rows, columns=["kind", "constants", "omega", "m", "t", "bound", "eta"])

    omegas = seen.select(F.explode("o").alias("omega")).filter("omega is not null")
    return _rounded(omegas.mapInPandas(grid, "kind string, constants string, omega double, m int, t int, bound double, eta double"), "bound", "eta", digits=9)


def _bounds_sql() -> str:
    grid = ", ".join(f"({m}, {t})" for m, t in _GRID)
    seen = "c AS (SELECT user_id AS vec_id, event_id AS pos, value AS val FROM events), " + _RAGGED + ", o AS (SELECT CASE WHEN sum(s2) > 0 THEN sum(dl) * sum(dl) / sum(s2) - 1 ELSE 0 END AS om FROM g GROUP BY vec_id), w AS (SELECT unnest([round(avg(om), 6), round(max(om), 6)]) AS omega FROM o)"
    A = "(4 * (3 * omega + 1) + 6 * omega)"
    B = "(3 * omega + 1 + 1.5 * omega)"
    b = {
        "plain_convex": "1.0 / t + 0.5 / m", "plain_nonconvex": "2.0 / t + 1.0 / m",
        "homog_convex": "2.0 / t + 16 * omega / (m * t) + {d2} * sqrt(2 * omega + 1) / sqrt(m * t)", "homog_nonconvex": "4.0 / t + 32 * omega / (m * t) + 4 * sqrt(2 * omega + 1) / sqrt(m * t) * {d1}",
        "heterog_convex": f"2.0 / t + {{h}} * omega / (m * t) + {{d1}} * sqrt({A}) / sqrt(m * t)", "heterog_nonconvex": f"4.0 / t + 48 * omega / (m * t) + 4 * sqrt({B}) / sqrt(m * t) * {{d1}}",
    }
    e = {
        "plain_convex": "0.5", "plain_nonconvex": "1.0", "homog_convex": "least(0.5, m / (16 * omega), sqrt(m) / (2 * sqrt((2 * omega + 1) * t)))", "homog_nonconvex": "least(1.0, m / (8 * omega), sqrt(m) / sqrt((2 * omega + 1) * t))",
        "heterog_convex": f"least(0.5, m / ({{h}} * omega), sqrt(m) / {{r}})", "heterog_nonconvex": f"least(1.0, m / (12 * omega), sqrt(m) / sqrt({B} * t))",
    }
    parts = []
    for k in _KINDS:
        for c, v in (("printed", {"d1": 1, "d2": 2, "h": 16, "r": f"(sqrt({A}) * t)"}), ("derived", {"d1": 2, "d2": 4, "h": 24, "r": f"sqrt({A} * t)"})):
            parts.append(f"SELECT '{k}' AS kind, '{c}' AS constants, omega, m, t, round(({b[k].format(**v)})::DOUBLE, 9) AS bound, round(({e[k].format(**v)})::DOUBLE, 9) AS eta FROM grid")
    return f"WITH {seen}, grid AS (SELECT omega, m, t FROM w, (VALUES {grid}) v(m, t) WHERE omega IS NOT NULL) " + " UNION ALL ".join(parts)


def _limits(spark: SparkSession, sf: str) -> DataFrame:
    """Worker limits of both methods where each supplier's lines are the samples."""
    n = load(spark, sf, "lineitem", "l_suppkey").groupBy("l_suppkey").agg(F.count(F.lit(1)).cast("double").alias("n"))
    return n.select("l_suppkey", "n", *[F.round(theory.max_workers(F.col("n"), m), 6).alias(m) for m in ("tier", "feedback")])


def _heterogeneity(spark: SparkSession, sf: str) -> DataFrame:
    """Spread of workers' gradients at zero, with equal shards and with shards by return flag."""
    rows = load(spark, sf, "lineitem", "l_orderkey", "l_linenumber", "l_quantity", "l_discount", "l_tax", "l_extendedprice", "l_returnflag")
    out = None
    for name, df in (("equal", losses.lineitem_squares(rows, 4)), ("by_flag", losses.lineitem_squares(rows, 4, "l_returnflag").withColumn("worker", F.ascii("l_returnflag")))):
        local = losses.gradient(df, [0.0] * 4)
        whole = losses.gradient(df.withColumn("worker", F.lit(0)), [0.0] * 4)
        row = accuracy.heterogeneity(local, whole).select(F.lit(name).alias("shards"), F.round("xi2_mean", 9).alias("xi2_mean"), F.round("xi2_max", 9).alias("xi2_max"))
        out = row if out is None else out.union(row)
    return out


def _heterogeneity_sql() -> str:
    g = "SELECT {w} AS worker, i AS pos, avg(-y * a[i + 1]) AS val FROM s, (SELECT unnest(range(4)) AS i) GROUP BY 1, 2"
    rows = "s AS MATERIALIZED (SELECT ((l_orderkey * 8 + l_linenumber) % 4)::INT AS worker, ascii(l_returnflag) AS flag, [1.0::DOUBLE, l_quantity / 50, l_discount * 10, l_tax * 12.5] AS a, l_extendedprice / 50000 AS y FROM lineitem)"
    one = "SELECT '{n}' AS shards, round(avg(x), 9) AS xi2_mean, round(max(x), 9) AS xi2_max FROM (SELECT l.worker, sum((l.val - w.val) * (l.val - w.val)) AS x FROM ({l}) l JOIN ({w}) w USING (pos) GROUP BY l.worker)"
    return f"WITH {rows} " + " UNION ALL ".join(one.format(n=n, l=g.format(w=w), w=g.format(w="0")) for n, w in (("equal", "worker"), ("by_flag", "flag")))


def queries() -> dict[str, Query]:
    b = base_compressors
    out: dict[str, Query] = {
        "vec_coords": _on_coords(lambda c: c),
        "vec_norms": _on_coords(lambda c: vectors.norms(c, K), "l1", "l2sq", "top"),
        "vec_rank_magnitude": _on_coords(lambda c: vectors.rank_by_magnitude(c, K)),
        "vec_rank_histogram": _on_coords(lambda c: vectors.rank_by_magnitude(c, K, "histogram")),
        "vec_dense_roundtrip": _on_coords(lambda c: vectors.to_coords(vectors.to_dense(c, K), K, "vec")),
        "vec_block_roundtrip": _on_coords(lambda c: vectors.from_blocks(vectors.to_blocks(c, K, 16), K, 16)),
        "vec_sum_exact": lambda s, sf: vectors.sum_exact(embedding_coords(s, sf), K).select("vec_id", F.round(F.col("total").cast("double"), 9).alias("total")),
        "topk_embed": _on_coords(lambda c: b.top_k(c, K, 8)),
        "segtopk_embed": _on_coords(lambda c: b.segment_top_k(c, K, 2, 8)),
        "randk_embed": _on_coords(lambda c: b.rand_k(c, K, 8, 7)),
        "fixedpoint_1bit": _on_coords(lambda c: b.fixed_point(c, K, 1)),
        "fixedpoint_8bit": _on_coords(lambda c: b.fixed_point(c, K, 8)),
        "floatpoint_4bit": _on_coords(lambda c: b.float_point(c, K, 4)),
        "qsgd_2bit": _on_coords(lambda c: b.stochastic_quantize(c, K, 1, 7)),
        "qsgd_4bit": _on_coords(lambda c: b.stochastic_quantize(c, K, 7, 7)),
        **{f"rtn_l{l}": _on_coords(lambda c, l=l: b.round_to_grid(c, K, l)) for l in (2, 4, 8, 16)},
        "rtn_value_clip": _on_coords(lambda c: b.round_to_grid(c, K, 4, "value")),
        "rtn_printed_clip": _on_coords(lambda c: b.round_to_grid(c, K, 4, "printed")),
        "segment_deltas": _deltas("segment", 8), "fixed_deltas": _deltas("fixed"), "float_deltas": _deltas("float"), "rtn_deltas": _deltas("rtn", 8),
        "segment_alpha_profile": _alpha,
        "probs_geometric_63": _drawn_probs(lambda s: geometric_probs(s, 63)), "probs_geometric_52": _drawn_probs(lambda s: geometric_probs(s, 52)),
        "probs_uniform": _drawn_probs(lambda s: uniform_probs(s, 8)), "probs_custom": _line_probs,
        "probs_adaptive_segment": _probs("segment", 8), "probs_adaptive_fixed": _probs("fixed"), "probs_adaptive_float": _probs("float"), "probs_adaptive_rtn": _probs("rtn", 8), "probs_energy_share": _energy, "probs_cost_aware": _cost_aware,
        "tier_segment_s1": _tier("segment", 1), "tier_segment_s8": _tier("segment", 8), "tier_fixed": _tier("fixed", how="63"), "tier_fixed_adaptive": _tier("fixed"), "tier_float": _tier("float", how="52"), "tier_float_zero_base": _tier("float_zero", how="52"), "tier_rtn": _tier("rtn", 8),
        "tier_custom": _tier_custom,
        "expect_custom": lambda s, sf: _rounded(enumerate_expectation(c := embedding_coords(s, sf), K, _custom(c), uniform_probs(s, 3)), "val"),
        "tier_weighted_coordinate": _on_coords(lambda c: weighted_coordinate(c, K, 7)),
        "expect_segment": _expect("segment", 8), "expect_fixed": _expect("fixed", how="63"), "expect_float": _expect("float", how="52"), "expect_rtn": _expect("rtn", 8),
        "var_segment_exact": _variance("segment", 8), "var_fixed_exact": _variance("fixed", how="63"), "var_float_exact": _variance("float", how="52"), "var_rtn_exact": _variance("rtn", 8),
        "var_segment_closed": _on_coords(lambda c: accuracy.adaptive_variance(c, K, SegmentLevels(8)), "variance", "omega"),
        **{f"var_{n}_closed": _on_coords(lambda c, m=m, k=k: accuracy.closed_form(c, K, m, k), "variance", "omega") for n, m, k in (("fixed", "fixed", 1), ("float", "float", 1), ("randk", "rand", 8), ("qsgd", "quantize", 1))},
        "distortion_topk": _on_coords(lambda c: accuracy.distortion(c, b.top_k(c, K, 8), K), "err2", "rel", "alpha"),
        "omega_table": _omega, "decay_rate_fit": _decay, "decay_closed_form": _decay_forms,
        "bits_per_message": _bits, "bits_expected_rtn": _expected_rtn_bits,
        "sgd_plain_ls_3steps": _fit("plain"), "sgd_tier_fixed_ls_3steps": _fit("fixed"), "sgd_tier_adaptive_ls_3steps": _fit("segment"), "sgd_topk_ls_3steps": _fit("topk"), "sgd_randk_ls_3steps": _fit("randk"), "sgd_ef21m_ls_3steps": _fit("ef21m"), "marina_ls_3steps": _fit("marina"), "dasha_ls_3steps": _fit("dasha"),
        "sgd_tier_adaptive_softmax_2steps": _softmax, "bits_marina_ls": _marina_bits,
        "var_customer_prices": _customer_prices, "var_user_values": _user_values, "message_variance_by_workers": _message_variance, "bits_cumulative": _bits_cumulative, "self_bound_ls": _self_bound, "problem_constants_ls": _problem_constants, "bias_by_method": _bias,
        "bounds_grid": _bounds, "worker_limit_grid": _limits, "heterogeneity_ls": _heterogeneity,
    }
    return out | checks.QUERIES | relational.QUERIES | workloads.QUERIES | online.QUERIES | arrivals.QUERIES | sql_surface.QUERIES


def oracle_sql() -> dict[str, str]:
    s = sql
    closed = {
        "fixed": "(1 - pow(2, -63)) * top * l1 - l2sq",
        "randk": "(d / 8.0 - 1) * l2sq",
        "qsgd": "sqrt(l2sq) * l1 - l2sq",
    }
    fv = f"({s.LEAD} * (1 - pow(2, -52)) * (abs(val) - {s.LEAD}) - (abs(val) - {s.LEAD}) * (abs(val) - {s.LEAD}))"
    levels = lambda f, n, cols: s.with_(*s.probs(f, n), select=f"SELECT vec_id, level, {cols} FROM pr")
    out = {
        "vec_coords": s.VECTOR, "vec_dense_roundtrip": s.VECTOR, "vec_block_roundtrip": s.VECTOR, "expect_segment": s.VECTOR, "expect_fixed": s.VECTOR, "expect_float": s.VECTOR, "expect_rtn": s.VECTOR, "expect_custom": s.VECTOR,
        "tier_custom": s.estimate("custom", 3, "uniform"),
        "vec_norms": s.with_(s.C, s.TOP, select="SELECT vec_id, d, round(l1, 6) AS l1, round(l2sq, 6) AS l2sq, round(top, 6) AS top FROM t"),
        **{k: s.with_(s.C, s.RANKED, select="SELECT vec_id, pos, round(val, 6) AS val, rk::INT AS rk FROM r") for k in ("vec_rank_magnitude", "vec_rank_histogram")},
        "vec_sum_exact": s.with_(s.C, select="SELECT vec_id, round(sum(val::DECIMAL(28,15))::DOUBLE, 9) AS total FROM c GROUP BY vec_id"),
        "topk_embed": s.top_k(8), "segtopk_embed": s.top_k(16), "randk_embed": s.rand_k(8, 7), "fixedpoint_1bit": s.fixed_point(1), "fixedpoint_8bit": s.fixed_point(8), "floatpoint_4bit": s.float_point(4), "qsgd_2bit": s.quantize(1, 7), "qsgd_4bit": s.quantize(7, 7),
        **{f"rtn_l{l}": s.rounded(l) for l in (2, 4, 8, 16)}, "rtn_value_clip": s.rounded(4, "value"), "rtn_printed_clip": s.rounded(4, "printed"),
        **{f"{n}_deltas": s.with_(*s.deltas(f, k), select="SELECT vec_id, level, round(delta, 6) AS delta FROM dl") for n, f, k in (("segment", "segment", 8), ("fixed", "fixed", 0), ("float", "float", 0), ("rtn", "grid", 8))},
        "segment_alpha_profile": s.with_(*s.deltas("segment", 8), select="SELECT vec_id, level, round(delta, 6) AS delta, round(sum(delta * delta) OVER (PARTITION BY vec_id ORDER BY level ROWS UNBOUNDED PRECEDING) / sum(delta * delta) OVER (PARTITION BY vec_id), 6) AS alpha FROM dl"),
        **{f"probs_geometric_{n}": s.drawn_by_events(f"SELECT unnest(range(1, {n + 1}))::INT AS level, pow(2, -unnest(range(1, {n + 1}))) / (1 - pow(2, -{n})) AS q") for n in (63, 52)},
        "probs_uniform": s.drawn_by_events("SELECT unnest(range(1, 9))::INT AS level, 0.125::DOUBLE AS q"), "probs_custom": s.drawn_by_events("SELECT l_linenumber AS level, count(*)::DOUBLE / sum(count(*)) OVER () AS q FROM lineitem WHERE l_linenumber IS NOT NULL GROUP BY 1"),
        **{f"probs_adaptive_{n}": levels(f, k, "round(q, 6) AS q") for n, f, k in (("segment", "segment", 8), ("fixed", "fixed", 0), ("float", "float", 0), ("rtn", "grid", 8))},
        "probs_energy_share": levels("segment", 8, "round(q, 6) AS q"),
        "probs_cost_aware": s.with_(*s.deltas("grid", 8), "w AS (SELECT vec_id, level, delta / sqrt(CASE WHEN level = 8 THEN 64 * 64 ELSE (level + 1) * 64 + 64 + 3 END) AS w FROM dl)", select="SELECT vec_id, level, round(w / sum(w) OVER (PARTITION BY vec_id), 6) AS q FROM w"),
        "tier_segment_s1": s.estimate("segment", 1), "tier_segment_s8": s.estimate("segment", 8), "tier_fixed": s.estimate("fixed", how="63"), "tier_fixed_adaptive": s.estimate("fixed"), "tier_float": s.estimate("float", how="52"), "tier_float_zero_base": s.estimate("float_zero", how="52"), "tier_rtn": s.estimate("grid", 8),
        "tier_weighted_coordinate": s.with_(s.C, s.TOP, f"x AS (SELECT *, -ln(greatest({s.u(7, 'vec_id', 'pos')}, pow(2, -53))) / abs(val) AS race FROM c WHERE val <> 0)", select="SELECT vec_id, pos, round(sign(val) * l1, 6) AS val FROM (SELECT * FROM x QUALIFY row_number() OVER (PARTITION BY vec_id ORDER BY race) = 1) JOIN t USING (vec_id)"),
        "var_segment_exact": s.variance("segment", 8), "var_fixed_exact": s.variance("fixed", how="63"), "var_float_exact": s.variance("float", how="52"), "var_rtn_exact": s.variance("grid", 8),
        "var_segment_closed": s.with_(*s.deltas("segment", 8), select="SELECT vec_id, round(sum(delta) * sum(delta) - any_value(l2sq), 6) AS variance, round(sum(delta) * sum(delta) / any_value(l2sq) - 1, 6) AS omega FROM dl JOIN t USING (vec_id) GROUP BY vec_id"),
        **{f"var_{n}_closed": s.with_(s.C, s.TOP, select=f"SELECT vec_id, round({e}, 6) AS variance, round(({e}) / l2sq, 6) AS omega FROM t") for n, e in closed.items()},
        "var_float_closed": s.with_(s.C, s.TOP, select=f"SELECT vec_id, round(sum({fv}), 6) AS variance, round(sum({fv}) / any_value(l2sq), 6) AS omega FROM c JOIN t USING (vec_id) WHERE val <> 0 GROUP BY vec_id"),
        "distortion_topk": s.with_(s.C, s.TOP, s.RANKED, select="SELECT vec_id, round(sum(CASE WHEN rk > 8 THEN val * val ELSE 0 END), 6) AS err2, round(sum(CASE WHEN rk > 8 THEN val * val ELSE 0 END) / any_value(l2sq), 6) AS rel, round(1 - sum(CASE WHEN rk > 8 THEN val * val ELSE 0 END) / any_value(l2sq), 6) AS alpha FROM r JOIN t USING (vec_id) GROUP BY vec_id"),
        "omega_table": _omega_sql(), "decay_closed_form": _decay_forms_sql(),
        "decay_rate_fit": s.with_(s.C, s.RANKED, select="SELECT vec_id, d, round(r, 6) AS r, CASE WHEN r * d < 1 THEN 1 WHEN r < 1 AND r * d > 1 THEN 2 ELSE 0 END AS regime FROM (SELECT vec_id, count(*) AS d, -2 * regr_slope(ln(abs(val)), rk - 1) AS r FROM r WHERE val <> 0 GROUP BY vec_id)"),
        "bits_per_message": "WITH v AS (SELECT user_id, count(*) AS d FROM events GROUP BY user_id), b AS (SELECT user_id, d, 64 * d AS uncompressed, 64 * least(10, d) AS sparse, 2 * d + 70 AS fixed_tier, 13 * d + 6 AS float_tier, 2 * d + 64 AS fixed, 16 * d AS float, 2 * d + 64 AS stochastic, 4 * d + 64 AS grid, 4 * d + 67 AS grid_tier FROM v) SELECT user_id, kind, bits::BIGINT AS bits, round(64.0::DOUBLE * d / bits, 6) AS ratio FROM (UNPIVOT b ON COLUMNS(* EXCLUDE (user_id, d)) INTO NAME kind VALUE bits)",
        "bits_expected_rtn": s.with_(*s.probs("grid", 8), select="SELECT vec_id, round(sum(q * CASE WHEN level = 8 THEN 4096 ELSE (level + 1) * 64 + 67 END), 4) AS bits FROM pr GROUP BY vec_id"),
        **{f"{name}_ls_3steps": run(kind, 3, 0.5, 4, 1.0 if kind == "dasha" else 0.2, 5, 1 if kind in ("segment", "marina", "dasha") else 2) for name, kind in (("sgd_plain", "plain"), ("sgd_tier_fixed", "fixed"), ("sgd_tier_adaptive", "segment"), ("sgd_topk", "topk"), ("sgd_randk", "randk"), ("sgd_ef21m", "ef21m"), ("marina", "marina"), ("dasha", "dasha"))},
        "var_customer_prices": "WITH c AS (SELECT o_custkey AS vec_id, l_orderkey * 8 + l_linenumber AS pos, l_extendedprice / 1000 AS val FROM lineitem JOIN orders ON l_orderkey = o_orderkey), " + _RAGGED + " SELECT vec_id, round(sum(dl) * sum(dl) / sum(s2) - 1, 6) AS omega FROM g GROUP BY vec_id",
        "var_user_values": "WITH c AS (SELECT user_id AS vec_id, event_id AS pos, value AS val FROM events), " + _RAGGED + ", f AS (SELECT vec_id, -2 * regr_slope(ln(abs(val)), rk - 1) AS r FROM r WHERE val <> 0 GROUP BY vec_id) SELECT vec_id, any_value(d) AS d, round(sum(dl) * sum(dl) / sum(s2) - 1, 6) AS omega, round(any_value(d) / 4.0 - 1, 6)::DOUBLE AS rand_omega, round(any_value(f.r), 6) AS r FROM g JOIN f USING (vec_id) GROUP BY vec_id",
        "bits_marina_ls": f"SELECT 0 AS step, 0::BIGINT AS bits_cum UNION ALL SELECT step, sum(CASE WHEN step = 1 OR {s.u(5, "'coin'", 'step')} < 0.5 THEN 1024 ELSE 256 END) OVER (ORDER BY step)::BIGINT FROM (SELECT unnest(range(1, 5))::INT AS step)",
        "bits_cumulative": "WITH v AS (SELECT event_type, ts::DATE AS step, count(*) AS d FROM events WHERE ts IS NOT NULL GROUP BY 1, 2), b AS (SELECT step, sum(64 * d) AS uncompressed, sum(64 * least(10, d)) AS sparse, sum(2 * d + 70) AS fixed_tier, sum(13 * d + 6) AS float_tier FROM v GROUP BY step) SELECT method, step, sum(bits) OVER (PARTITION BY method ORDER BY step)::BIGINT AS bits_cum FROM (UNPIVOT b ON uncompressed, sparse, fixed_tier, float_tier INTO NAME method VALUE bits)",
        "self_bound_ls": constants.self_bound_sql(4, 0.5), "problem_constants_ls": constants.constants_sql(),
        "bias_by_method": s.with_(s.C, s.RANKED, select="SELECT vec_id, 'topk' AS method, round(sqrt(sum(CASE WHEN rk > 8 THEN val * val ELSE 0 END)), 6) AS bias FROM r GROUP BY vec_id UNION ALL SELECT vec_id, 'segment_levels', 0.0 FROM c GROUP BY vec_id"),
        "bounds_grid": _bounds_sql(), "worker_limit_grid": "SELECT l_suppkey, n, round(pow(n, 0.5), 6) AS tier, round(pow(n, 1.0 / 3), 6) AS feedback FROM (SELECT l_suppkey, count(*)::DOUBLE AS n FROM lineitem GROUP BY l_suppkey)", "heterogeneity_ls": _heterogeneity_sql(),
    }
    return out | checks.ORACLES | relational.ORACLES | online.ORACLES | arrivals.ORACLES | sql_surface.ORACLES
