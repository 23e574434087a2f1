"""Probabilities of levels: given, uniform, geometric, and adapted to each vector's residuals."""

from __future__ import annotations

from collections.abc import Sequence

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from .levels import LevelFamily


def custom_probs(levels: DataFrame) -> DataFrame:
    """level, q as given, if they are positive and sum to one."""
    low, total = levels.agg(F.min("q"), F.sum("q")).first()
    if low is None or low <= 0 or abs(total - 1) > 1e-9:
        raise ValueError(f"probabilities must be positive and sum to 1: least {low}, sum {total}")
    return levels.select("level", "q")


def uniform_probs(spark: SparkSession, depth: int) -> DataFrame:
    """1 / depth each."""
    return spark.range(1, depth + 1).select(F.col("id").cast("int").alias("level"), F.lit(1.0 / depth).alias("q"))


def geometric_probs(spark: SparkSession, depth: int) -> DataFrame:
    """2**-l / (1 - 2**-depth): least variance of bit ladders whose bits are not known."""
    return spark.range(1, depth + 1).select(F.col("id").cast("int").alias("level"), (F.pow(F.lit(2.0), -F.col("id").cast("double")) / (1 - 2.0**-depth)).alias("q"))


def deltas(prepared: DataFrame, keys: Sequence[str], family: LevelFamily) -> DataFrame:
    """keys, level, delta: norms of residuals, by one aggregation that is combined on the map side."""
    rows = prepared.withColumn("level", F.explode(family.touched()))
    res = family.residual(F.col("level"))
    return rows.withColumn("r", res).groupBy(*keys, "level").agg(F.sqrt(F.sum(F.col("r") * F.col("r"))).alias("delta"))


def normalised(levels: DataFrame, keys: Sequence[str], weight) -> DataFrame:
    """q in proportion to ``weight`` within the key; 0 where all weights are 0."""
    whole = F.sum(weight).over(Window.partitionBy(*keys))
    return levels.withColumn("q", F.when(whole > 0, weight / whole).otherwise(0.0))


def residual_norm_probs(prepared: DataFrame, keys: Sequence[str], family: LevelFamily) -> DataFrame:
    """keys, level, delta, q with q in proportion to the residual's norm: least variance for each vector."""
    return normalised(deltas(prepared, keys, family), keys, F.col("delta"))


def alpha_profile(levels: DataFrame, keys: Sequence[str]) -> DataFrame:
    """Adds alpha, the share of the squared norm in levels up to this one. ``levels``: keys, level, delta of a ladder of segments."""
    by = Window.partitionBy(*keys)
    run = by.orderBy("level").rowsBetween(Window.unboundedPreceding, Window.currentRow)
    d2 = F.col("delta") * F.col("delta")
    return levels.withColumn("alpha", F.when(F.sum(d2).over(by) > 0, F.sum(d2).over(run) / F.sum(d2).over(by)).otherwise(1.0))


def energy_share_probs(profile: DataFrame, keys: Sequence[str]) -> DataFrame:
    """q in proportion to the root of each level's share of energy. ``profile``: keys, level, alpha."""
    gain = F.col("alpha") - F.coalesce(F.lag("alpha").over(Window.partitionBy(*keys).orderBy("level")), F.lit(0.0))
    return normalised(profile.withColumn("root", F.sqrt(F.greatest(gain, F.lit(0.0)))), keys, F.col("root")).drop("root")


def cost_aware_probs(levels: DataFrame, keys: Sequence[str], bits) -> DataFrame:
    """q in proportion to delta / sqrt(bits): least variance times expected bits, for ladders whose levels cost differently."""
    return normalised(levels, keys, F.col("delta") / F.sqrt(bits))
