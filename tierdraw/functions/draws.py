"""Hashed uniforms: every random choice is a function of its seed and keys, the same in each run, retry and engine."""

from __future__ import annotations

from collections.abc import Sequence

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

SCALE = 4503599627370496.0  # 2**52


def hash_uniform(*parts: Column | str | int) -> Column:
    """A number in [0, 1) from the parts joined by bars: thirteen hexadecimal digits of their MD5."""
    cols = [p if isinstance(p, Column) else F.lit(p) for p in parts]
    digits = F.substring(F.md5(F.concat_ws("|", *[c.cast("string") for c in cols]).cast("binary")), 1, 13)
    return F.conv(digits, 16, 10).cast("bigint") / F.lit(SCALE)


def with_bounds(levels: DataFrame, keys: Sequence[str]) -> DataFrame:
    """levels (keys, level, q, ...) with lo and hi, the stretch of [0, 1) of each level; the last level with q > 0 reaches to 1."""
    by = Window.partitionBy(*keys) if keys else Window.partitionBy(F.lit(1))
    run = by.orderBy("level").rowsBetween(Window.unboundedPreceding, Window.currentRow)
    top = F.max(F.when(F.col("q") > 0, F.col("level"))).over(by)
    hi = F.sum("q").over(run)
    return levels.withColumn("hi", F.when(F.col("level") >= top, F.lit(1.0)).otherwise(hi)).withColumn("lo", hi - F.col("q"))


def draw_level(levels: DataFrame, keys: Sequence[str], u: Column) -> DataFrame:
    """keys, level, q of the level whose stretch holds ``u`` (an expression over the keys); keys whose q are all 0 draw nothing."""
    held = with_bounds(levels, keys).withColumn("u", u)
    return held.filter((F.col("q") > 0) & (F.col("lo") <= F.col("u")) & (F.col("u") < F.col("hi"))).select(*keys, "level", "q")


def drawn_counts(levels: DataFrame, u: DataFrame) -> DataFrame:
    """level, q, n of static probabilities (level, q): how many rows of ``u`` (u) draw each level."""
    held = with_bounds(levels, [])
    hits = u.join(F.broadcast(held.filter("q > 0").select("level", "lo", "hi")), (F.col("lo") <= F.col("u")) & (F.col("u") < F.col("hi")))  # at most 64 rows
    counts = hits.groupBy("level").agg(F.count(F.lit(1)).alias("n"))
    return levels.join(counts, "level", "left").select("level", F.round("q", 12).alias("q"), F.coalesce("n", F.lit(0).cast("long")).alias("n"))


def drawn_by_events(levels: DataFrame, events: DataFrame, seed: int = 13) -> DataFrame:
    """level, q, n: probabilities, and the events whose hashed uniform draws each level."""
    return drawn_counts(levels, events.select(hash_uniform(seed, F.col("event_id")).alias("u")))


def draw_static(probs: Sequence[float], u: Column) -> Column:
    """The level (from 1) that ``u`` draws from fixed probabilities: a cascade of constants, no join."""
    out, hi = None, 0.0
    for level, q in enumerate(probs, 1):
        hi = 1.0 if level == len(probs) else hi + q
        out = F.when(u < hi, F.lit(level)) if out is None else out.when(u < hi, F.lit(level))
    return out


def weighted_coordinate(coords: DataFrame, keys: Sequence[str], seed: int) -> DataFrame:
    """One coordinate per key, drawn in proportion to its magnitude, with the value sign * L1 norm: the ladder of single coordinates with adaptive
    probabilities, in one pass and without a sort. The least of -ln(u) / abs(val) wins; all aggregates are of primitives, so they stay hashed and partial."""
    u = hash_uniform(seed, *[F.col(k) for k in keys], F.col("pos"))
    race = -F.log(F.greatest(u, F.lit(2.0**-53))) / F.abs("val")
    rows = coords.filter(F.col("val") != 0).withColumn("race", race)
    return rows.groupBy(*keys).agg(F.min_by("pos", "race").alias("pos"), F.min_by(F.signum("val"), "race").alias("sg"), F.sum(F.abs("val")).alias("l1")).select(*keys, "pos", (F.col("sg") * F.col("l1")).alias("val"))
