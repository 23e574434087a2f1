"""Ladders of compressors T_1 .. T_L that end in the identity.

A family prepares coordinates once per vector (ranks, scale, exponent) and then states, as column expressions, which levels touch a coordinate and what a level adds to it
(its residual). Estimators use only that, so the residual of the drawn level is computed alone and never as the difference of two compressions.
"""

from __future__ import annotations

from collections.abc import Callable, Sequence

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .base_compressors import _top, grid_value
from .vectors import floor_log2, rank_by_magnitude


class LevelFamily:
    """Contract of a ladder. ``sparse``: a level touches only some coordinates, and the others are not sent."""

    sparse = False
    depth = 0

    def prepare(self, coords: DataFrame, keys: Sequence[str]) -> DataFrame:
        """Coordinates with the columns that the expressions below read."""
        return coords

    def touched(self) -> Column:
        """Array of the levels whose residual at the coordinate may differ from 0."""
        return F.sequence(F.lit(1), F.lit(self.depth))

    def residual(self, level: Column) -> Column:
        """What the level adds to the coordinate."""
        raise NotImplementedError

    def base(self) -> Column:
        """What is always sent of the coordinate."""
        return F.lit(0.0)

    def value_bits(self, d: Column, level: Column) -> Column:
        """Bits of a message, as counted without indices."""
        raise NotImplementedError


class SegmentLevels(LevelFamily):
    """Level l adds the l-th segment of s largest magnitudes; s = 1 is the ladder of single coordinates; the last segment may be short."""

    sparse = True

    def __init__(self, s: int, rank_mode: str = "window") -> None:
        self.s, self.rank_mode = s, rank_mode

    def prepare(self, coords: DataFrame, keys: Sequence[str]) -> DataFrame:
        return rank_by_magnitude(coords, keys, self.rank_mode).withColumn("seg", F.ceil(F.col("rk") / self.s).cast("int"))

    def touched(self) -> Column:
        return F.array("seg")

    def residual(self, level: Column) -> Column:
        return F.when(F.col("seg") == level, F.col("val")).otherwise(0.0)

    def value_bits(self, d: Column, level: Column) -> Column:
        return 64 * F.least(F.lit(self.s), d - (level - 1) * self.s)


class FixedPointLevels(LevelFamily):
    """Level l adds bit l of abs(val) / max, with 63 bits; a coordinate at the maximum has every bit set."""

    def __init__(self, depth: int = 63) -> None:
        self.depth = depth

    def prepare(self, coords: DataFrame, keys: Sequence[str]) -> DataFrame:
        return _top(coords, keys)

    def residual(self, level: Column) -> Column:
        y, two = F.abs("val") / F.col("top"), F.pow(F.lit(2.0), level.cast("double"))
        bit = F.when(y >= 1, 1).otherwise(F.floor(y * two) % 2)
        return F.when(F.col("top") > 0, F.signum("val") * F.col("top") * bit / two).otherwise(0.0)

    def value_bits(self, d: Column, level: Column) -> Column:
        return 2 * d + 64 + 6


class FloatPointLevels(LevelFamily):
    """Level l adds mantissa bit l; sign and exponent are always sent (``base='exponent'``) or belong to level 1 (``base='zero'``)."""

    def __init__(self, depth: int = 52, base: str = "exponent") -> None:
        self.depth, self.start = depth, base

    def prepare(self, coords: DataFrame, keys: Sequence[str]) -> DataFrame:
        a = F.abs("val")
        return coords.withColumn("lead", F.when(a > 0, F.pow(F.lit(2.0), floor_log2(a).cast("double"))).otherwise(0.0))

    def residual(self, level: Column) -> Column:
        two = F.pow(F.lit(2.0), level.cast("double"))
        bit = F.floor((F.abs("val") / F.col("lead") - 1) * two) % 2
        part = F.signum("val") * F.col("lead") * bit / two
        if self.start == "zero":
            part = part + F.when(level == 1, F.signum("val") * F.col("lead")).otherwise(0.0)
        return F.when(F.col("lead") > 0, part).otherwise(0.0)

    def base(self) -> Column:
        return F.signum("val") * F.col("lead") if self.start == "exponent" else F.lit(0.0)

    def value_bits(self, d: Column, level: Column) -> Column:
        return 13 * d + 6


class GridRoundingLevels(LevelFamily):
    """Rounding to grids of 1 .. depth-1 bits, then the identity."""

    def __init__(self, depth: int, clip: str = "grid", c: float | None = None) -> None:
        self.depth, self.clip, self.c = depth, clip, c

    def prepare(self, coords: DataFrame, keys: Sequence[str]) -> DataFrame:
        return _top(coords, keys)

    def at(self, level: int) -> Column:
        """The coordinate at a level; 0 below the first."""
        if level == 0:
            return F.lit(0.0)
        if level == self.depth:
            return F.col("val")
        edge = F.col("top") if self.c is None else F.lit(float(self.c))
        return F.when(edge > 0, grid_value(F.col("val"), edge, level, self.clip)).otherwise(0.0)

    def residual(self, level: Column) -> Column:
        out = F.when(level == 1, self.at(1))
        for l in range(2, self.depth + 1):
            out = out.when(level == l, self.at(l) - self.at(l - 1))
        return out.otherwise(0.0)

    def value_bits(self, d: Column, level: Column) -> Column:
        return F.when(level == self.depth, 64 * d).otherwise((level + 1) * d + 64 + (self.depth - 1).bit_length())


class EntropyGridLevels(GridRoundingLevels):
    """Uniform grids whose step is chosen so that the entropy of the indices stays below the level's rate: the finest of the bit grids that does, then the identity.

    ``bins`` maps each level to the bits of its grid; ``fit`` measures entropies on a sample of coordinates with DataFrame aggregates.
    """

    def __init__(self, bins: Sequence[int]) -> None:
        super().__init__(len(bins) + 1)
        self.bins = list(bins)

    @classmethod
    def fit(cls, coords: DataFrame, keys: Sequence[str], rates: Sequence[float], widest: int = 12) -> EntropyGridLevels:
        rows = _top(coords, keys).filter("top > 0")
        grids = F.array(*[F.struct(F.lit(b).alias("b"), F.rint(grid_value(F.col("val"), F.col("top"), b) * (2.0**b - 1) / (2 * F.col("top"))).alias("i")) for b in range(1, widest + 1)])
        counts = rows.select(F.explode(grids).alias("g")).groupBy("g.b", "g.i").agg(F.count(F.lit(1)).alias("n"))
        totals = counts.groupBy("b").agg(F.sum("n").alias("t"), F.sum(F.col("n") * F.log2("n")).alias("nl"))
        entropy = {r["b"]: r["e"] for r in totals.select("b", (F.log2("t") - F.col("nl") / F.col("t")).alias("e")).collect()}  # one row a grid
        return cls([max([b for b, e in entropy.items() if e <= rate], default=1) for rate in rates])

    def at(self, level: int) -> Column:
        if level in (0, self.depth):
            return super().at(level)
        return F.when(F.col("top") > 0, grid_value(F.col("val"), F.col("top"), self.bins[level - 1])).otherwise(0.0)


class CustomLevels(LevelFamily):
    """A ladder from any compressors: functions of (coords, keys) that return coordinates, the last one the identity."""

    def __init__(self, compressors: Sequence[Callable[[DataFrame, Sequence[str]], DataFrame]]) -> None:
        self.compressors, self.depth = list(compressors), len(compressors)

    def prepare(self, coords: DataFrame, keys: Sequence[str]) -> DataFrame:
        """One array of the coordinate's values at all levels: the compressions are joined once."""
        out = coords
        for l, f in enumerate(self.compressors, 1):
            out = out.join(f(coords, keys).select(*keys, "pos", F.col("val").alias(f"t{l}")), [*keys, "pos"], "left")
        return out.withColumn("t", F.array(F.lit(0.0), *[F.coalesce(f"t{l}", F.lit(0.0)) for l in range(1, self.depth + 1)])).drop(*[f"t{l}" for l in range(1, self.depth + 1)])

    def residual(self, level: Column) -> Column:
        return F.element_at("t", level + 1) - F.element_at("t", level)

    def value_bits(self, d: Column, level: Column) -> Column:
        return 64 * d
