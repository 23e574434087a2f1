"""Tier-draw estimators: draw one level, send the base and that level's residual over its probability."""

from __future__ import annotations

from collections.abc import Sequence

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..functions.draws import draw_level, hash_uniform
from .level_probs import residual_norm_probs
from .levels import LevelFamily
from .vectors import subtract


def level_estimate(values: DataFrame, keys: Sequence[str], u: Column) -> DataFrame:
    """The estimator over scalar levels. ``values``: keys, level (from 0, the base), value, q (null at 0). Returns keys, level, estimate."""
    base = values.filter("level = 0").select(*keys, F.col("value").alias("base"))
    below = values.select(*keys, (F.col("level") + 1).alias("level"), F.col("value").alias("below"))
    drawn = draw_level(values.filter("level > 0").select(*keys, "level", "q"), keys, u)
    rows = drawn.join(values.select(*keys, "level", "value"), [*keys, "level"]).join(below, [*keys, "level"]).join(base, list(keys))
    return rows.select(*keys, "level", (F.col("base") + (F.col("value") - F.col("below")) / F.col("q")).alias("estimate"))


def replicate_mean(estimates: DataFrame, keys: Sequence[str]) -> DataFrame:
    """Mean over replicates."""
    return estimates.groupBy(*keys).agg(F.avg("estimate").alias("estimate"), F.count(F.lit(1)).alias("n"))


def level_table(prepared: DataFrame, keys: Sequence[str], family: LevelFamily, probs: DataFrame | str) -> DataFrame:
    """keys, level, q: adaptive for each key, or a fixed table of levels for every key."""
    if isinstance(probs, str):
        return residual_norm_probs(prepared, keys, family).select(*keys, "level", "q")
    return prepared.select(*keys).distinct().crossJoin(F.broadcast(probs.select("level", "q")))  # levels: at most 64 rows, or the caller's


def tier_draws(coords: DataFrame, keys: Sequence[str], family: LevelFamily, probs: DataFrame | str = "adaptive", seed: int = 0, reps: int = 1) -> DataFrame:
    """keys, level, q, pos, val of the messages, and rep (from 1) if there are several independent draws.

    Only the drawn level's residual is computed. Coordinates that a level of a sparse family does not touch are not sent; zero vectors send nothing.
    """
    prepared = family.prepare(coords, keys)
    table = level_table(prepared, keys, family, probs)
    draws, by, salt = table, list(keys), F.lit(seed)
    if reps > 1:
        draws, by = table.withColumn("rep", F.explode(F.sequence(F.lit(1), F.lit(reps)))), [*keys, "rep"]
        salt = F.concat_ws("#", F.lit(seed), F.col("rep"))
    drawn = draw_level(draws, by, hash_uniform(salt, *[F.col(k) for k in keys]))
    rows = prepared.join(drawn, list(keys))
    if family.sparse:
        rows = rows.filter(F.array_contains(family.touched(), F.col("level")))
    return rows.select(*by, "level", "q", "pos", (family.base() + family.residual(F.col("level")) / F.col("q")).alias("val"))


def tier_estimate(coords: DataFrame, keys: Sequence[str], family: LevelFamily, probs: DataFrame | str = "adaptive", seed: int = 0, reps: int = 1) -> DataFrame:
    """The messages of ``tier_draws``; with ``reps`` > 1, the mean of that many independent draws (then without level and q)."""
    rows = tier_draws(coords, keys, family, probs, seed, reps)
    if reps == 1:
        return rows
    return rows.groupBy(*keys, "pos").agg((F.sum("val") / reps).alias("val"))


def two_pass_estimate(coords: DataFrame, keys: Sequence[str], at_level, probs: DataFrame, seed: int) -> DataFrame:
    """The same from whole compressions: ``at_level(coords with level)`` compresses at each row's level column; level 0 gives nothing."""
    table = coords.select(*keys).distinct().crossJoin(F.broadcast(probs))
    drawn = draw_level(table, keys, hash_uniform(seed, *[F.col(k) for k in keys]))
    rows = coords.join(drawn, list(keys))
    upper, lower = at_level(rows), at_level(rows.withColumn("level", F.col("level") - 1))
    return subtract(upper, lower, keys).join(drawn, list(keys)).select(*keys, "pos", (F.col("val") / F.col("q")).alias("val"))


def enumerate_expectation(coords: DataFrame, keys: Sequence[str], family: LevelFamily, probs: DataFrame | str = "adaptive") -> DataFrame:
    """Exact mean of the estimator: base plus, over all levels, q times residual over q. It equals the vector whatever the probabilities are."""
    prepared = family.prepare(coords, keys)
    table = level_table(prepared, keys, family, probs).filter("q > 0")
    rows = prepared.withColumn("bv", family.base()).withColumn("level", F.explode(family.touched()))
    rows = rows.join(table, [*keys, "level"], "left").withColumn("part", F.coalesce(F.col("q") * (family.residual(F.col("level")) / F.col("q")), F.lit(0.0)))
    return rows.groupBy(*keys, "pos").agg((F.first("bv") + F.sum("part")).alias("val"))


def exact_variance(coords: DataFrame, keys: Sequence[str], family: LevelFamily, probs: DataFrame | str = "adaptive") -> DataFrame:
    """keys, second_moment (sum of squared residual norms over q), variance (less the squared norm of what is not base), norm2."""
    prepared = family.prepare(coords, keys)
    table = level_table(prepared, keys, family, probs).filter("q > 0")
    rows = prepared.withColumn("level", F.explode(family.touched())).withColumn("r", family.residual(F.col("level")))
    d2 = rows.groupBy(*keys, "level").agg(F.sum(F.col("r") * F.col("r")).alias("d2"))
    second = d2.join(table, [*keys, "level"]).groupBy(*keys).agg(F.sum(F.col("d2") / F.col("q")).alias("second_moment"))
    rest = F.col("val") - family.base()
    plain = prepared.groupBy(*keys).agg(F.sum(rest * rest).alias("rest2"), F.sum(F.col("val") * F.col("val")).alias("norm2"))
    out = plain.join(second, list(keys), "left").withColumn("second_moment", F.coalesce("second_moment", F.lit(0.0)))
    return out.select(*keys, "second_moment", (F.col("second_moment") - F.col("rest2")).alias("variance"), "norm2")
