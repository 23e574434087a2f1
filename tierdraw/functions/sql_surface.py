"""Functions for SQL users: hashed uniforms, level probabilities and message sizes as SQL functions, bit planes as Arrow functions, ladders as table functions."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

SQL_FUNCTIONS = (
    "CREATE OR REPLACE TEMPORARY FUNCTION hash_uniform(k STRING) RETURNS DOUBLE RETURN CAST(conv(substr(md5(CAST(k AS BINARY)), 1, 13), 16, 10) AS BIGINT) / 4503599627370496D",
    "CREATE OR REPLACE TEMPORARY FUNCTION geo_prob(l INT, depth INT) RETURNS DOUBLE RETURN power(2D, -l) / (1 - power(2D, -depth))",
    "CREATE OR REPLACE TEMPORARY FUNCTION tier_bits(kind STRING, d BIGINT, k BIGINT) RETURNS BIGINT RETURN CASE kind WHEN 'uncompressed' THEN 64 * d WHEN 'fixed_tier' THEN 2 * d + 70 WHEN 'float_tier' THEN 13 * d + 6 ELSE 64 * least(k, d) END",
)


class GeoLevels:
    """level, q of geometric probabilities."""

    def eval(self, depth: int):
        for l in range(1, (depth or 0) + 1):
            yield l, 2.0**-l / (1 - 2.0**-depth)


class LevelLadder:
    """level, delta, q, alpha of one vector's ladder: ``segment`` with size s, or ``fixed`` with 63 bits."""

    def eval(self, vec: list, family: str, s: int):
        w = np.abs(np.array([v or 0.0 for v in vec or []], float))
        if family == "segment":
            w = np.sort(w)[::-1]
            delta = np.array([np.sqrt((w[i : i + s] ** 2).sum()) for i in range(0, len(w), s)])
        else:
            top = w.max(initial=0.0) or 1.0
            y = w / top
            delta = np.array([top * 2.0**-l * np.sqrt(np.where(y >= 1, 1, np.floor(y * 2.0**l) % 2).sum()) for l in range(1, 64)])
        total, energy = delta.sum(), np.cumsum(delta**2)
        for l, x in enumerate(delta, 1):
            yield l, float(x), float(x / total) if total else 0.0, float(energy[l - 1] / energy[-1]) if total else 1.0


def register(spark: SparkSession) -> None:
    """Makes all functions known to the session."""
    for text in SQL_FUNCTIONS:
        spark.sql(text)
    spark.udtf.register("geo_levels", F.udtf(GeoLevels, returnType="level int, q double"))
    spark.udtf.register("level_ladder", F.udtf(LevelLadder, returnType="level int, delta double, q double, alpha double"))
    spark.udf.register("entropy_bits", entropy_bits)


@F.pandas_udf(T.DoubleType())
def entropy_bits(v: pd.Series) -> float:
    """Entropy, in bits, of the values of a group."""
    p = v.value_counts(normalize=True).to_numpy()
    return float(-(p * np.log2(p)).sum())


def pack_planes(bits: list) -> bytes:
    """Bits of an array of 0 and 1, eight a byte, first bit highest."""
    return np.packbits(np.asarray(bits, np.uint8)).tobytes()


@F.pandas_udf(T.BinaryType())
def pack_column(parts: Iterator[pd.Series]) -> Iterator[pd.Series]:
    """Arrays of 0 and 1 as packed bytes."""
    for s in parts:
        yield s.map(pack_planes)


def unpack_column(n: int):
    """Packed bytes as arrays of ``n`` bits."""

    @F.pandas_udf(T.ArrayType(T.IntegerType()))
    def f(parts: Iterator[pd.Series]) -> Iterator[pd.Series]:
        for s in parts:
            yield s.map(lambda b: np.unpackbits(np.frombuffer(b, np.uint8))[:n].astype("int32"))

    return f


def fn_hash_uniform(spark: SparkSession, sf: str):
    register(spark)
    spark.read.parquet(f"{sf}/embeddings.parquet").createOrReplaceTempView("tierdraw_vectors")
    return spark.sql("SELECT vec_id, hash_uniform(concat('a|', vec_id)) AS u, tier_bits('fixed_tier', size(embedding), 1) AS bits FROM tierdraw_vectors")


def fn_geo_levels(spark: SparkSession, sf: str):
    """Geometric probabilities of each vector's levels, one for each of its coordinates."""
    register(spark)
    spark.read.parquet(f"{sf}/embeddings.parquet").createOrReplaceTempView("tierdraw_vectors")
    return spark.sql("SELECT vec_id, level, round(q, 12) AS q FROM tierdraw_vectors, LATERAL geo_levels(size(embedding))")


def fn_level_ladder(spark: SparkSession, sf: str):
    register(spark)
    spark.read.parquet(f"{sf}/embeddings.parquet").createOrReplaceTempView("tierdraw_vectors")
    return spark.sql("SELECT vec_id, level, round(delta, 6) AS delta, round(q, 6) AS q, round(alpha, 6) AS alpha FROM tierdraw_vectors, LATERAL level_ladder(CAST(embedding AS ARRAY<DOUBLE>), 'segment', 8)")


def fn_bit_planes(spark: SparkSession, sf: str):
    """Signs of vectors as packed planes and back."""
    rows = spark.read.parquet(f"{sf}/embeddings.parquet").select("vec_id", F.transform("embedding", lambda x: (x < 0).cast("int")).alias("s"))
    wire = rows.select("vec_id", pack_column("s").alias("p"))
    back = wire.select("vec_id", F.length("p").alias("bytes"), unpack_column(64)("p").alias("s"))
    return back.select("vec_id", "bytes", F.aggregate("s", F.lit(0), lambda a, x: a + x).alias("negative"))


QUERIES = {f.__name__: f for f in (fn_hash_uniform, fn_geo_levels, fn_level_ladder, fn_bit_planes)}
ORACLES = {
    "fn_hash_uniform": "SELECT vec_id, ('0x' || substr(md5('a|' || vec_id), 1, 13))::BIGINT / 4503599627370496.0 AS u, (2 * len(embedding) + 70)::BIGINT AS bits FROM embeddings",
    "fn_geo_levels": "SELECT vec_id, level, round(pow(2, -level) / (1 - pow(2, -d)), 12) AS q FROM (SELECT vec_id, len(embedding) AS d, unnest(range(1, len(embedding) + 1))::INT AS level FROM embeddings)",
    "fn_level_ladder": "WITH c AS (SELECT vec_id, unnest(embedding)::DOUBLE AS val FROM embeddings), r AS (SELECT *, row_number() OVER (PARTITION BY vec_id ORDER BY abs(val) DESC) AS rk FROM c), d AS (SELECT vec_id, ceil(rk / 8.0)::INT AS level, sqrt(sum(val * val)) AS delta FROM r GROUP BY 1, 2) SELECT vec_id, level, round(delta, 6) AS delta, round(delta / sum(delta) OVER (PARTITION BY vec_id), 6) AS q, round(sum(delta * delta) OVER (PARTITION BY vec_id ORDER BY level ROWS UNBOUNDED PRECEDING) / sum(delta * delta) OVER (PARTITION BY vec_id), 6) AS alpha FROM d",
    "fn_bit_planes": "SELECT vec_id, 8 AS bytes, len(list_filter(embedding, lambda x: x < 0))::INT AS negative FROM embeddings",
}
