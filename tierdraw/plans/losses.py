"""Samples, shards, batches and gradients as DataFrame plans. A sample is a row key, worker, a (features), y."""

from __future__ import annotations

from collections.abc import Sequence

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..functions.draws import hash_uniform


def assign_worker(df: DataFrame, key: str, m: int, by: str | None = None) -> DataFrame:
    """Adds worker in 0 .. m-1: from the key (equal shards), or from a category, so that shards differ."""
    worker = F.pmod(F.col(key), F.lit(m)) if by is None else F.pmod(F.xxhash64(F.col(by).cast("string")), F.lit(m))
    return df.withColumn("worker", worker.cast("int"))


def split(df: DataFrame, key: str, fractions: Sequence[float], seed: int) -> list[DataFrame]:
    """Disjoint parts by a hash of the key."""
    u, out, lo = hash_uniform(seed, "split", F.col(key)), [], 0.0
    for f in fractions:
        out.append(df.filter((u >= lo) & (u < lo + f)))
        lo += f
    return out


def minibatch(df: DataFrame, step: int, fraction: float, seed: int) -> DataFrame:
    """The step's samples: rows whose hash for this step is below the fraction; no shuffle."""
    return df if fraction >= 1 else df.filter(hash_uniform(seed, "b", step, F.col("key")) < fraction)


def array_of(values: Sequence[float]) -> Column:
    """A model of few coordinates as one constant of the plan."""
    return F.split(F.lit(",".join(map(repr, map(float, values)))), ",").cast("array<double>")


def dot(a: Column, b: Column) -> Column:
    return F.aggregate(F.zip_with(a, b, lambda x, y: x * y), F.lit(0.0), lambda s, x: s + x)


def gradient(batch: DataFrame, model: Sequence[float], loss: str = "squares", l2: float = 0.0) -> DataFrame:
    """worker, pos, val: each worker's mean gradient over its samples.

    squares: (a.x - y)**2 / 2; logistic: y in 0, 1; softmax: y a class, model rows class by class. Partial sums per (worker, pos) are what is shuffled.
    """
    x = array_of(model)
    if loss == "softmax":
        d, n = F.size("a"), len(model)
        once = lambda value, body: F.transform(F.array(value), body)[0]  # noqa: E731  computed once a row, whatever the body does with it
        z = F.transform(F.sequence(F.lit(0), F.floor(F.lit(n) / d).cast("int") - 1), lambda c: dot(F.col("a"), F.slice(x, c * d + 1, d)))
        share = lambda e: once(F.aggregate(e, F.lit(0.0), lambda s, v: s + v), lambda t: F.transform(e, lambda v, c: v / t - F.when(c == F.col("y").cast("int"), 1.0).otherwise(0.0)))
        r = once(z, lambda zs: once(F.array_max(zs), lambda top: once(F.transform(zs, lambda v: F.exp(v - top)), share)))
        parts = batch.withColumn("g", once(r, lambda rs: F.flatten(F.transform(rs, lambda r: F.transform("a", lambda v: r * v)))))
    else:
        z = dot(F.col("a"), x)
        r = z - F.col("y") if loss == "squares" else 1 / (1 + F.exp(-z)) - F.col("y")
        parts = batch.withColumn("r", r).withColumn("g", F.transform("a", lambda v: F.col("r") * v))
    out = parts.select("worker", F.posexplode("g").alias("pos", "v")).groupBy("worker", "pos").agg(F.avg("v").alias("val"))
    return out.select("worker", F.col("pos").cast("bigint").alias("pos"), (F.col("val") + l2 * F.element_at(x, F.col("pos") + 1)).alias("val"))


def squares_value(samples: DataFrame, model: Sequence[float]) -> DataFrame:
    """loss: mean of half squared residuals."""
    r = dot(F.col("a"), array_of(model)) - F.col("y")
    return samples.agg(F.avg(r * r / 2).alias("loss"))


def lineitem_squares(lineitem: DataFrame, m: int, by: str | None = None) -> DataFrame:
    """Samples of a regression of price on quantity, discount and tax; fixed scales, no pass for statistics."""
    key = F.col("l_orderkey") * 8 + F.col("l_linenumber")
    a = F.array(F.lit(1.0), F.col("l_quantity") / 50, F.col("l_discount") * 10, F.col("l_tax") * 12.5)
    keep = [by] if by else []
    return assign_worker(lineitem.select(key.alias("key"), a.alias("a"), (F.col("l_extendedprice") / 50000).alias("y"), *keep), "key", m, by)


def embedding_classes(embeddings: DataFrame, m: int) -> DataFrame:
    """Samples of a classification of vectors by label, with a constant feature."""
    a = F.concat(F.col("embedding").cast("array<double>"), F.array(F.lit(1.0)))
    return assign_worker(embeddings.select(F.col("vec_id").alias("key"), a.alias("a"), F.col("label").cast("double").alias("y")), "key", m)


def hashed_text(documents: DataFrame, size: int) -> DataFrame:
    """doc_id, f: sparse features (pos, val) of a text: log counts of hashed words over their norm, and a constant at ``size``."""
    words = F.filter(F.split(F.regexp_replace(F.lower(F.coalesce("text", F.lit(""))), r"[^\p{L}\p{N}]+", " "), " "), lambda w: w != "")
    rows = documents.select("doc_id", F.explode_outer(words).alias("w")).filter("w is not null")
    at = F.pmod(F.conv(F.substring(F.md5(F.col("w").cast("binary")), 1, 8), 16, 10).cast("bigint"), F.lit(size))
    counts = rows.groupBy("doc_id", at.alias("pos")).agg(F.log1p(F.count(F.lit(1)).cast("double")).alias("v"))
    lists = counts.groupBy("doc_id").agg(F.sort_array(F.collect_list(F.struct("pos", "v"))).alias("f"), F.sqrt(F.sum(F.col("v") * F.col("v"))).alias("norm"))
    return lists.select("doc_id", F.concat(F.transform("f", lambda x: F.struct(x["pos"].alias("pos"), (x["v"] / F.col("norm")).alias("v"))), F.array(F.struct(F.lit(size).cast("bigint").alias("pos"), F.lit(1.0).alias("v")))).alias("f"))
