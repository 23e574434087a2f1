"""Baselines: compressors of coordinates (keys, pos, val) that are applied to each key's vector by itself."""

from __future__ import annotations

from collections.abc import Sequence

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..functions.draws import hash_uniform
from .vectors import floor_log2, rank_by_magnitude


def _top(coords: DataFrame, keys: Sequence[str]) -> DataFrame:
    """Adds top, the largest magnitude of the key, by an aggregate that is joined back: no task holds a vector."""
    return coords.join(coords.groupBy(*keys).agg(F.max(F.abs("val")).alias("top")), list(keys))


def top_k(coords: DataFrame, keys: Sequence[str], k: int) -> DataFrame:
    """The k largest magnitudes, ties to the smaller position (biased)."""
    return rank_by_magnitude(coords, keys).filter(F.col("rk") <= k).drop("rk")


def segment_top_k(coords: DataFrame, keys: Sequence[str], k: int, s: int) -> DataFrame:
    """The k largest segments of s coordinates in order of magnitude (biased)."""
    return top_k(coords, keys, k * s)


def rand_k(coords: DataFrame, keys: Sequence[str], k: int, seed: int, scale: bool = True) -> DataFrame:
    """k coordinates at random, times d / k so that the mean is kept; ``scale=False``: as they are (biased)."""
    d = coords.groupBy(*keys).agg(F.count(F.lit(1)).alias("d"))
    u = hash_uniform(seed, *[F.col(c) for c in keys], F.col("pos"))
    kept = coords.withColumn("u", u).withColumn("rn", F.row_number().over(Window.partitionBy(*keys).orderBy("u", "pos"))).filter(F.col("rn") <= k)
    factor = F.col("d") / F.least(F.col("d"), F.lit(k)) if scale else F.lit(1.0)
    return kept.join(d, list(keys)).select(*keys, "pos", (F.col("val") * factor).alias("val"))


def fixed_point(coords: DataFrame, keys: Sequence[str], bits: int) -> DataFrame:
    """Sign and the first bits of abs(val) / max (biased): error at most max / 2**bits. A zero vector stays zero."""
    y, two = F.abs("val") / F.col("top"), F.lit(2.0**bits)
    kept = F.when(y >= 1, (two - 1) / two).otherwise(F.floor(y * two) / two)
    return _top(coords, keys).select(*keys, "pos", F.when(F.col("top") > 0, F.signum("val") * F.col("top") * kept).otherwise(0.0).alias("val"))


def float_point(coords: DataFrame, keys: Sequence[str], bits: int) -> DataFrame:
    """Sign, exponent and the first mantissa bits (biased): alpha at least 1 - 2**-bits."""
    a = F.abs("val")
    lead = F.pow(F.lit(2.0), floor_log2(a).cast("double"))
    kept = lead * (1 + F.floor((a / lead - 1) * 2.0**bits) / 2.0**bits)
    return coords.select(*keys, "pos", F.when(a > 0, F.signum("val") * kept).otherwise(0.0).alias("val"))


def stochastic_quantize(coords: DataFrame, keys: Sequence[str], steps: int, seed: int) -> DataFrame:
    """norm * sign * a level of a grid of ``steps``, rounded up or down at random (unbiased). b bits: 2**(b-1) - 1 steps."""
    l2 = coords.groupBy(*keys).agg(F.sqrt(F.sum(F.col("val") * F.col("val"))).alias("l2"))
    z = steps * F.abs("val") / F.col("l2")
    u = hash_uniform(seed, *[F.col(c) for c in keys], F.col("pos"))
    level = F.floor(z) + F.when(u < z - F.floor(z), 1).otherwise(0)
    return coords.join(l2, list(keys)).select(*keys, "pos", F.when(F.col("l2") > 0, F.col("l2") * F.signum("val") * level / steps).otherwise(0.0).alias("val"))


def grid_value(val, c, level: int, clip: str = "grid"):
    """Column: ``val`` rounded to the grid of ``level`` bits over [-c, c], step 2c / (2**level - 1), halves to even.

    ``clip``: ``grid`` bounds the index by 2**(level-1) - 1, ``value`` the result by c, ``printed`` the index by c.
    """
    delta = 2 * c / (2.0**level - 1)
    index = F.rint(val / delta)
    bound = F.lit(2.0 ** (level - 1) - 1) if clip == "grid" else c
    if clip == "value":
        return F.greatest(-c, F.least(c, delta * index))
    return delta * F.greatest(-bound, F.least(bound, index))


def round_to_grid(coords: DataFrame, keys: Sequence[str], level: int, clip: str = "grid", c: float | None = None) -> DataFrame:
    """Rounding to nearest on a grid of ``level`` bits (biased); the range is the largest magnitude unless ``c`` is given."""
    rows = _top(coords, keys)
    edge = F.col("top") if c is None else F.lit(float(c))
    return rows.select(*keys, "pos", F.when(edge > 0, grid_value(F.col("val"), edge, level, clip)).otherwise(0.0).alias("val"))
