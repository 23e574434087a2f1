"""Vectors as coordinates (keys, pos, val), as arrays and as blocks; norms, ranks, differences, averages."""

from __future__ import annotations

from collections.abc import Sequence

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

#: Values of a block, and finest magnitude buckets of a histogram ranking (per power of two).
BLOCK, BUCKETS_PER_OCTAVE = 65_536, 64


def to_coords(rows: DataFrame, keys: Sequence[str], array: str) -> DataFrame:
    """Coordinates of an array column; null arrays and elements have none."""
    return rows.select(*keys, F.posexplode(array).alias("pos", "val")).select(*keys, F.col("pos").cast("bigint").alias("pos"), F.col("val").cast("double").alias("val")).filter("val is not null")


def to_dense(coords: DataFrame, keys: Sequence[str], d: int | None = None) -> DataFrame:
    """keys, vec: arrays with 0 where there is no coordinate. For vectors that fit a row; longer ones stay in blocks."""
    pairs = coords.groupBy(*keys).agg(F.map_from_entries(F.sort_array(F.collect_list(F.struct("pos", "val")))).alias("m"), F.max("pos").alias("top"))
    last = F.lit(d - 1) if d else F.col("top")
    return pairs.select(*keys, F.transform(F.sequence(F.lit(0).cast("bigint"), last.cast("bigint")), lambda p: F.coalesce(F.try_element_at("m", p), F.lit(0.0))).alias("vec"))


def to_blocks(coords: DataFrame, keys: Sequence[str], size: int = BLOCK) -> DataFrame:
    """keys, block, vals: at most ``size`` consecutive coordinates a row, missing ones 0; no row grows with the length of the vector."""
    at = coords.withColumn("block", F.floor(F.col("pos") / size)).withColumn("at", F.pmod("pos", F.lit(size)))
    return to_dense(at.select(*keys, "block", F.col("at").alias("pos"), "val"), [*keys, "block"], size).withColumnRenamed("vec", "vals")


def from_blocks(blocks: DataFrame, keys: Sequence[str], size: int = BLOCK) -> DataFrame:
    """Coordinates of blocks."""
    return blocks.select(*keys, "block", F.posexplode("vals").alias("p", "val")).select(*keys, (F.col("block") * size + F.col("p")).alias("pos"), "val")


def reject_nonfinite(coords: DataFrame) -> DataFrame:
    """Coordinates without NaN and infinities."""
    return coords.filter(~F.isnan("val") & (F.abs("val") < float("inf")))


def norms(coords: DataFrame, keys: Sequence[str]) -> DataFrame:
    """keys, d, l1, l2sq, top."""
    return coords.groupBy(*keys).agg(F.count(F.lit(1)).alias("d"), F.sum(F.abs("val")).alias("l1"), F.sum(F.col("val") * F.col("val")).alias("l2sq"), F.max(F.abs("val")).alias("top"))


def magnitude_key(val: Column) -> Column:
    """A whole number that grows with abs(val): power of two, then equal steps within it."""
    a = F.abs(val)
    octave = floor_log2(a)
    step = F.floor((a / F.pow(F.lit(2.0), octave) - 1) * BUCKETS_PER_OCTAVE)
    return F.when(a > 0, octave.cast("bigint") * BUCKETS_PER_OCTAVE + step).otherwise(F.lit(-(10**9)))


def floor_log2(a: Column) -> Column:
    """Exponent of a positive number: floor of the logarithm, put right where rounding has it off by one."""
    x = F.floor(F.log2(a))
    two = lambda e: F.pow(F.lit(2.0), e.cast("double"))
    return F.when(two(x + 1) <= a, x + 1).when(two(x) > a, x - 1).otherwise(x)


def rank_by_magnitude(coords: DataFrame, keys: Sequence[str], mode: str = "window") -> DataFrame:
    """Adds rk: 1 for the largest magnitude of the key, ties by position.

    ``histogram`` ranks one very long vector without one task for it: counts per magnitude bucket give each bucket's offset, and only
    the coordinates of a bucket are sorted together.
    """
    order = [F.abs("val").desc(), F.col("pos")]
    if mode == "window":
        return coords.withColumn("rk", F.row_number().over(Window.partitionBy(*keys).orderBy(*order)))
    rows = coords.withColumn("bucket", magnitude_key(F.col("val")))
    counts = rows.groupBy(*keys, "bucket").agg(F.count(F.lit(1)).alias("n"))
    above = Window.partitionBy(*keys).orderBy(F.col("bucket").desc()).rowsBetween(Window.unboundedPreceding, -1)
    offsets = counts.withColumn("before", F.coalesce(F.sum("n").over(above), F.lit(0))).drop("n")
    inner = Window.partitionBy(*keys, "bucket").orderBy(*order)
    return rows.withColumn("within", F.row_number().over(inner)).join(offsets, [*keys, "bucket"]).select(*coords.columns, (F.col("within") + F.col("before")).cast("int").alias("rk"))


def subtract(a: DataFrame, b: DataFrame, keys: Sequence[str]) -> DataFrame:
    """a - b over the coordinates of either."""
    both = a.select(*keys, "pos", F.col("val").alias("va")).join(b.select(*keys, "pos", F.col("val").alias("vb")), [*keys, "pos"], "full")
    return both.select(*keys, "pos", (F.coalesce("va", F.lit(0.0)) - F.coalesce("vb", F.lit(0.0))).alias("val"))


def average(messages: DataFrame, keys: Sequence[str], m: int) -> DataFrame:
    """Server average: sums of messages per (keys, pos) over ``m`` workers, combined on the map side."""
    return messages.groupBy(*keys, "pos").agg((F.sum("val") / m).alias("val"))


def sum_exact(coords: DataFrame, keys: Sequence[str]) -> DataFrame:
    """Sums that do not depend on the order of rows, in decimals of 15 places."""
    return coords.groupBy(*keys).agg(F.sum(F.col("val").cast("decimal(28,15)")).alias("total"))
