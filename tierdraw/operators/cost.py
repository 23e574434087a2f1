"""Bits that a worker sends per step: values and side information as the headline, indices and downlink apart."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

VALUE_BITS = 64


def index_bits(d: Column) -> Column:
    """Bits that name one of d positions: ceil(log2 d)."""
    return F.when(d > 1, F.length(F.bin((d - 1).cast("bigint")))).otherwise(0)


def message_bits(kind: str, d: Column, k: int = 0, bits: int = 0, depth: int = 0) -> Column:
    """Value and side bits of a message over d coordinates.

    uncompressed; sparse (k values: largest, random, a segment, error feedback); fixed_tier, float_tier (drawn level of bit ladders);
    fixed, float (truncation to ``bits``); stochastic and grid (``bits`` an entry and a scale); grid_tier (a drawn level ``bits`` of ``depth``).
    """
    return {
        "uncompressed": VALUE_BITS * d,
        "sparse": VALUE_BITS * F.least(F.lit(k), d),
        "fixed_tier": 2 * d + 64 + F.lit(6),
        "float_tier": 13 * d + F.lit(6),
        "fixed": (1 + bits) * d + 64,
        "float": (12 + bits) * d,
        "stochastic": bits * d + 64,
        "grid": bits * d + 64,
        "grid_tier": VALUE_BITS * d if bits == depth else (bits + 1) * d + 64 + F.lit(max(depth - 1, 0).bit_length()),
    }[kind]


def ratio(bits: Column, d: Column) -> Column:
    """How many times smaller a message is than all coordinates."""
    return VALUE_BITS * d / bits


def cumulative(log: DataFrame) -> DataFrame:
    """Adds bits_cum over the steps of each run. ``log``: method, seed, m, step, bits."""
    run = Window.partitionBy("method", "seed", "m").orderBy("step").rowsBetween(Window.unboundedPreceding, Window.currentRow)
    return log.withColumn("bits_cum", F.sum("bits").over(run))


def first_to_reach(log: DataFrame, target: float, axis: str = "bits_cum") -> DataFrame:
    """Least bits (or step) at which each run's accuracy reaches the target; runs that never do have null."""
    return log.groupBy("method", "seed", "m").agg(F.min(F.when(F.col("acc") >= target, F.col(axis))).alias(axis))


def observe_round(df: DataFrame, name: str) -> DataFrame:
    """The same rows, with their number and values counted while they are computed."""
    return df.observe(name, F.count(F.lit(1)).alias("rows"), F.sum(F.lit(VALUE_BITS)).alias("value_bits"))
