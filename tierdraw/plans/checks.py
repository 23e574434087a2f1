"""Estimators, variances and error bounds worked out on the given tables, each beside SQL of its own."""

from __future__ import annotations

from collections.abc import Callable
from math import sqrt

import numpy as np
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions.draws import drawn_by_events, hash_uniform
from ..operators import accuracy, vectors
from ..operators.level_probs import uniform_probs
from ..operators.levels import SegmentLevels
from ..operators.telescoping import level_estimate, replicate_mean, tier_draws, tier_estimate, two_pass_estimate
from ..oracle import sql
from ..oracle.training import run
from ..sources.catalog import load
from . import constants, losses, theory, trainers

K = ["vec_id"]
#: Workers and steps of runs that take the same number of batches.
RUNS = ((4, 16), (8, 8), (16, 4), (32, 2))
FRACTION, SEED = 0.2, 5


def _coords(spark: SparkSession, sf: str) -> DataFrame:
    return vectors.to_coords(load(spark, sf, "embeddings", "vec_id", "embedding"), K, "embedding")


def _rounded(c: str) -> Column:
    return (F.round(c, 6) + F.lit(0.0)).alias(c)


def two_pass(spark: SparkSession, sf: str) -> DataFrame:
    """Largest-coordinate messages as the difference of two whole compressions, at the drawn level and below it."""
    ranked = vectors.rank_by_magnitude(_coords(spark, sf), K)
    at_level = lambda rows: rows.filter(F.col("rk") <= 8 * F.col("level")).select(*K, "pos", "val")
    return two_pass_estimate(ranked, K, at_level, uniform_probs(spark, 8), 3).select("vec_id", "pos", _rounded("val"))


def two_pass_sql() -> str:
    return sql.with_(
        sql.C,
        sql.RANKED,
        f"drawn AS MATERIALIZED (SELECT vec_id, 1 + floor(8 * {sql.u(3, 'vec_id')})::INT AS level FROM (SELECT DISTINCT vec_id FROM c))",
        select="SELECT vec_id, pos, CASE WHEN rk > 8 * (level - 1) THEN round(8 * val, 6) ELSE 0 END + 0.0 AS val FROM r JOIN drawn USING (vec_id) WHERE rk <= 8 * level",
    )


def scalar_mean(spark: SparkSession, sf: str) -> DataFrame:
    """Mean of sixteen estimates of each vector's sum, from a ladder of its partial sums of 16 coordinates more a level."""
    levels = F.sequence(F.lit(0), F.lit(4))
    held = _coords(spark, sf).withColumn("level", F.explode(levels))
    sums = held.groupBy("vec_id", "level").agg(F.sum(F.when(F.col("pos") < 16 * F.col("level"), F.col("val")).otherwise(0.0)).alias("value"))
    values = sums.withColumn("q", F.when(F.col("level") > 0, F.lit(0.25))).withColumn("rep", F.explode(F.sequence(F.lit(1), F.lit(16))))
    estimates = level_estimate(values, ["vec_id", "rep"], hash_uniform(6, F.col("vec_id"), F.col("rep")))
    return replicate_mean(estimates, K).select("vec_id", _rounded("estimate"), "n")


def scalar_mean_sql() -> str:
    return sql.with_(
        sql.C,
        "p AS MATERIALIZED (SELECT vec_id, pos // 16 + 1 AS level, sum(val) AS part FROM c WHERE pos < 64 GROUP BY ALL)",
        f"d AS (SELECT vec_id, rep, 1 + floor(4 * {sql.u(6, 'vec_id', 'rep')})::INT AS level FROM (SELECT DISTINCT vec_id FROM c), (SELECT unnest(range(1, 17)) AS rep))",
        select="SELECT vec_id, round(sum(coalesce(part, 0) / 0.25) / 16, 6) + 0.0 AS estimate, count(*) AS n FROM d LEFT JOIN p USING (vec_id, level) GROUP BY vec_id",
    )


def split_variance(spark: SparkSession, sf: str) -> DataFrame:
    """Per coordinate, the variance of messages of segments within the vectors (over eight draws) and between them."""
    c = _coords(spark, sf)
    drawn = tier_draws(c, K, SegmentLevels(16), "adaptive", 4, 8).select("vec_id", "rep", "pos", F.col("val").alias("sent"))
    every = c.withColumn("rep", F.explode(F.sequence(F.lit(1), F.lit(8)))).join(drawn, ["vec_id", "rep", "pos"], "left")
    rows = every.select(F.col("vec_id").alias("sample"), F.col("rep").alias("draw"), "pos", F.coalesce("sent", F.lit(0.0)).alias("val"))
    return accuracy.variance_split(rows).select("pos", _rounded("compression"), _rounded("noise"))


def split_variance_sql() -> str:
    u = sql.u("concat_ws('#', 4, rep)", "vec_id")
    return sql.with_(
        *sql.probs("segment", 16),
        "b AS (SELECT *, sum(q) OVER w AS hi, max(level) OVER (PARTITION BY vec_id) AS last FROM pr WHERE q > 0 WINDOW w AS (PARTITION BY vec_id ORDER BY level ROWS UNBOUNDED PRECEDING))",
        f"x AS (SELECT b.*, rep, {u} AS u FROM b, (SELECT unnest(range(1, 9)) AS rep))",
        "drawn AS MATERIALIZED (SELECT vec_id, rep, level, q FROM x WHERE hi - q <= u AND (u < hi OR level = last))",
        "e AS (SELECT vec_id, pos, CASE WHEN res.level = drawn.level THEN r / drawn.q ELSE 0 END AS v FROM res JOIN drawn USING (vec_id))",
        "s AS (SELECT vec_id, pos, avg(v) AS m, var_pop(v) AS v FROM e GROUP BY vec_id, pos)",
        select="SELECT pos, round(avg(v), 6) + 0.0 AS compression, round(var_pop(m), 6) + 0.0 AS noise FROM s GROUP BY pos",
    )


def realised_bits(spark: SparkSession, sf: str) -> DataFrame:
    """Bits of the messages as drawn, with a shorter last segment: 64 a value, and the places apart."""
    c = _coords(spark, sf)
    sent = tier_estimate(c, K, SegmentLevels(10), "adaptive", 8).groupBy("vec_id").agg(F.count(F.lit(1)).alias("n"))
    d = c.groupBy("vec_id").agg(F.count(F.lit(1)).alias("d"))
    index = F.col("n") * F.ceil(F.log2(F.greatest("d", F.lit(2)).cast("double")))
    return sent.join(d, K).select("vec_id", F.col("n").alias("n_values"), (64 * F.col("n")).alias("value_bits"), index.cast("long").alias("index_bits"))


def realised_bits_sql() -> str:
    return (
        f"SELECT vec_id, n AS n_values, 64 * n AS value_bits, (n * ceil(log2(greatest(d, 2)::DOUBLE)))::BIGINT AS index_bits "
        f"FROM (SELECT vec_id, count(*) AS n FROM ({sql.estimate('segment', 10, seed=8)}) GROUP BY vec_id) JOIN (SELECT vec_id, len(embedding) AS d FROM embeddings) USING (vec_id)"
    )


def error_by_workers(spark: SparkSession, sf: str) -> DataFrame:
    """Runs of level-sampled descent with the same number of batches dealt to 4 to 32 workers: error of the averaged iterate and its convex bound.

    Smoothness, distance and the noise of one sample at the start are measured; the relative variance is its largest value for four coordinates, 3.
    """
    rows = load(spark, sf, "lineitem", "l_orderkey", "l_linenumber", "l_quantity", "l_discount", "l_tax", "l_extendedprice")
    p = constants.LeastSquares.of(losses.lineitem_squares(rows, 1), 4)
    best = p.best()
    out = []
    for m, t in RUNS:
        problem = theory.Problem(p.smoothness(), sqrt(p.noise2()), sqrt(float(best @ best)), p.c / 2 - p.loss(best), t, m, 3.0)
        eta = theory.step_size("homog_convex", problem)
        history, _ = trainers.fit(losses.lineitem_squares(rows, m), 4, trainers.TierDraw(SegmentLevels(1)), t, eta, m, fraction=FRACTION, seed=SEED)
        mean = trainers.average_iterate([[round(v, 6) for v in x] for x in history])
        error, limit = p.loss(np.array(mean)) - p.loss(best), theory.bound("homog_convex", problem)
        out.append((m, t, eta, error, limit, error <= limit))
    table = spark.createDataFrame(out, "m int, steps int, eta double, error double, bound double, holds boolean")
    return table.select("m", "steps", *[F.round(c, 5).alias(c) for c in ("eta", "error", "bound")], "holds")


def error_by_workers_sql() -> str:
    root = "sqrt(m * t)"
    ctes, parts = [], []
    for m, t in RUNS:
        ctes.append(f"e{m} AS MATERIALIZED (SELECT least(1 / (2 * lip), {m} / (48 * lip), dist * sqrt({m}) / (2 * sigma * sqrt(7.0 * {t}))) AS eta FROM cst)")
        one = run("segment", t, f"(SELECT eta FROM e{m})", m, FRACTION, SEED)
        ctes.append(f"z{m} AS MATERIALIZED (SELECT list(v ORDER BY pos) AS z FROM (SELECT pos, avg(val) AS v FROM ({one}) WHERE step < {t} GROUP BY pos))")
        parts.append(f"SELECT {m} AS m, {t} AS t, eta, z FROM e{m}, z{m}")
    limit = f"2 * dist * dist * lip / t + 48 * dist * dist * lip / (m * t) + 4 * sigma * dist * sqrt(7.0) / {root}"
    return f"""WITH RECURSIVE {constants._solved()},
cst AS MATERIALIZED (SELECT l AS lip, sqrt(at_zero - list_dot_product(b, b)) AS sigma, sqrt(list_dot_product(x, x)) AS dist, {constants._loss_sql("x")} AS least FROM mat, best, top),
{", ".join(ctes)},
runs AS ({" UNION ALL ".join(parts)}),
f AS (SELECT r.m, r.t, r.eta, {constants._loss_sql("z")} - cst.least AS error, {limit} AS bound FROM runs r, mat, cst)
SELECT m::INT AS m, t::INT AS steps, round(eta, 5) AS eta, round(error, 5) AS error, round(bound, 5) AS bound, error <= bound AS holds FROM f"""


def recursive_probs(spark: SparkSession, sf: str) -> DataFrame:
    """Geometric probabilities of 63 levels, each half the one before, by recursive SQL, and the events that draw each level."""
    levels = spark.sql(
        """WITH RECURSIVE halves(level, w) AS (SELECT 1, 0.5D UNION ALL SELECT level + 1, w / 2 FROM halves WHERE level < 63)
        SELECT level, w / (1 - pow(2, -63)) AS q FROM halves"""
    )
    return drawn_by_events(levels, load(spark, sf, "events", "event_id"))


def percentiles(spark: SparkSession, sf: str) -> DataFrame:
    """Median and ninth decile of events' values, exact."""
    rows = load(spark, sf, "events", "event_type", "value").groupBy("event_type")
    return rows.agg(*[F.round(F.percentile("value", q), 6).alias(n) for q, n in ((0.5, "p50"), (0.9, "p90"))])


def rollup(spark: SparkSession, sf: str) -> DataFrame:
    """Orders by status and priority, with sub-totals; level 0 is a cell, 3 the whole."""
    rows = load(spark, sf, "orders", "o_orderstatus", "o_orderpriority", "o_totalprice").rollup("o_orderstatus", "o_orderpriority")
    return rows.agg(F.grouping_id().alias("level"), F.count(F.lit(1)).alias("n"), F.round(F.avg("o_totalprice"), 4).alias("price"))


QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {
    "tier_two_pass": two_pass,
    "tier_scalar_mean": scalar_mean,
    "variance_split_segment": split_variance,
    "bits_realised_segment": realised_bits,
    "error_by_workers_ls": error_by_workers,
    "probs_geometric_recursive": recursive_probs,
    "agg_percentiles": percentiles,
    "agg_rollup": rollup,
}
ORACLES = {
    "tier_two_pass": two_pass_sql(),
    "tier_scalar_mean": scalar_mean_sql(),
    "variance_split_segment": split_variance_sql(),
    "bits_realised_segment": realised_bits_sql(),
    "error_by_workers_ls": error_by_workers_sql(),
    "probs_geometric_recursive": sql.drawn_by_events("SELECT unnest(range(1, 64))::INT AS level, pow(2, -unnest(range(1, 64))) / (1 - pow(2, -63)) AS q"),
    "agg_percentiles": "SELECT event_type, round(quantile_cont(value, 0.5), 6) AS p50, round(quantile_cont(value, 0.9), 6) AS p90 FROM events GROUP BY event_type",
    "agg_rollup": "SELECT o_orderstatus, o_orderpriority, grouping(o_orderstatus, o_orderpriority) AS level, count(*) AS n, round(avg(o_totalprice), 4) AS price FROM orders GROUP BY ROLLUP (o_orderstatus, o_orderpriority)",
}
