"""Mixing sources to target weights by pivotal dependent rounding.

Targets: sources share a budget by weight, each stopping at a multiple of what it holds; the rest is
shared again by weight. Every document of a source then has the same fractional number of copies.
Rounding: within a bucket of a source, two documents with fractional copies exchange word mass, at
random and without bias, until one of them is integral; one fractional document stays per bucket,
and these meet again, 64 buckets at a time, in a reduction tree of Spark groups up to one per source.
Word mass is conserved by every exchange, so what a source misses is what the coin of its last document adds or takes. Large documents are
rounded first, and what they miss is spread, without bias, over the copies of the smaller ones: the last coin is that of a small document.
"""

from __future__ import annotations

from collections.abc import Iterator, Sequence

import pandas as pd
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F
from pyspark.sql import types as T

from .common import MASK64, cut, n_words, other_columns, unit

#: Documents, and words, of a bucket: bounds the group that one task holds.
BUCKET_DOCS, BUCKET_WORDS, FAN_IN = 4096, 4_000_000, 64
#: Size classes, from large to small, begin at these shares of the source's mean size.
CLASSES = (1.0, 0.25, 0.0)
EPS = 1e-12


def source_targets(sizes: DataFrame, weights: Sequence[float] = (5, 2, 1), cap: float = 3.0) -> DataFrame:
    """Word targets of sources.

    ``sizes`` has source, size (words of one document). Returns one row per source: source, docs,
    source_size, target. Sources in code point order, null last, take the weights in turn and share the sum of all sizes;
    no target exceeds ``cap`` times the source's size. A source of size 0 has target 0. No rows: no rows.
    The windows run over one row per source.
    """
    per = sizes.groupBy("source").agg(F.sum("size").alias("source_size"), F.count(F.lit(1)).alias("docs"))
    by_name = Window.partitionBy(F.lit(1)).orderBy(F.col("source").asc_nulls_last())
    cycle = F.array(*[F.lit(float(w)) for w in weights])
    per = per.withColumn("weight", F.element_at(cycle, (F.pmod(F.row_number().over(by_name) - 1, F.lit(len(weights))) + 1).cast("int")))
    # level of water: the first lambda, from the tightest cap on, at which capped sources and lambda * weight of the others fill the budget
    by_ratio = Window.partitionBy(F.lit(1)).orderBy(F.col("ratio"), F.col("source").asc_nulls_last())
    before, whole = by_ratio.rowsBetween(Window.unboundedPreceding, -1), by_ratio.rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing)
    per = per.withColumn("ratio", F.lit(float(cap)) * F.col("source_size") / F.col("weight"))
    capped = F.coalesce(F.sum(F.lit(float(cap)) * F.col("source_size")).over(before), F.lit(0.0))
    open_weight = F.sum("weight").over(whole) - F.coalesce(F.sum("weight").over(before), F.lit(0.0))
    per = per.withColumn("level", (F.sum("source_size").over(whole) - capped) / open_weight)
    per = per.withColumn("level", F.first(F.when(F.col("level") <= F.col("ratio"), F.col("level")), ignorenulls=True).over(whole))
    target = F.least(F.lit(float(cap)) * F.col("source_size"), F.col("level") * F.col("weight"))
    return per.select("source", "docs", "source_size", F.coalesce(target, F.lit(0.0)).alias("target"))


def exchange(sizes: Sequence[int], probs: Sequence[float], keys: Sequence[int], seed: int) -> tuple[list[float], int]:
    """Pivotal rounding of one group, in the order given.

    ``probs`` in [0, 1]; a transfer keeps the sum of size * prob. Returns the probabilities after it, all 0 or 1 but one at most,
    and the index of that one or -1.
    """
    out, held = list(probs), -1
    for j, p in enumerate(out):
        if p <= EPS or p >= 1 - EPS or sizes[j] <= 0:
            out[j] = 0.0 if sizes[j] <= 0 else float(round(p))
            continue
        if held < 0:
            held = j
            continue
        i = held
        si, sj, pi, pj = sizes[i], sizes[j], out[i], p
        to_j, to_i = min(pi * si, (1 - pj) * sj), min(pj * sj, (1 - pi) * si)
        if unit(int(keys[i]) * 0x9E3779B97F4A7C15 ^ int(keys[j]) ^ seed & MASK64) * (to_i + to_j) < to_i:
            out[i], out[j] = pi - to_j / si, pj + to_j / sj
        else:
            out[i], out[j] = pi + to_i / si, pj - to_i / sj
        for k in (i, j):
            if out[k] <= EPS or out[k] >= 1 - EPS:
                out[k] = float(round(out[k]))
        left = [k for k in (i, j) if 0 < out[k] < 1]
        held = left[0] if left else -1  # at most one is left
    return out, held


def _rounder(seed: int):
    def step(pdf: pd.DataFrame) -> pd.DataFrame:
        pdf = pdf.sort_values(["size", "mix_key"], ascending=[False, True], kind="stable")
        out, held = exchange(pdf["size"].tolist(), pdf["mix_p"].tolist(), pdf["mix_key"].tolist(), seed)
        pdf["mix_p"] = out
        pdf["mix_open"] = [k == held for k in range(len(out))]
        return pdf

    return step


def _closer(seed: int):
    def step(parts: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for pdf in parts:  # one open document per source at most: a biased coin rounds it
            pdf["mix_p"] = [float(unit(int(k) ^ seed & MASK64) < p) for k, p in zip(pdf["mix_key"], pdf["mix_p"], strict=True)]
            yield pdf

    return step


def mix_copies(docs: DataFrame, id_col: str = "doc_id", source_col: str = "source", size_col: str | None = None, weights: Sequence[float] = (5, 2, 1), cap: float = 3.0, seed: int = 42) -> DataFrame:
    """All rows of ``docs`` with how often the mix takes each.

    Adds mix_size (words), mix_source_size, mix_target (of the row's source) and mix_copies (0 to ``cap`` rounded up); such columns that
    are there already are replaced. Null text counts as empty; rows of size 0 get the source's whole copies and never the fractional one.
    Equal rows are interchangeable. Reruns agree: every draw is a hash of the ids. Empty table: no rows.
    """
    names = [c for c in docs.columns if c not in ("mix_size", "mix_source_size", "mix_target", "mix_copies")]
    base = docs.select(*[F.col(f"`{c}`").alias(f"d{k}") for k, c in enumerate(names)])
    at = {c: f"d{k}" for k, c in enumerate(names)}
    base = base.withColumn("size", F.coalesce(F.col(at[size_col]).cast("long"), F.lit(0)) if size_col else n_words(F.col(at["text"])))
    base = cut(base.withColumn("source", F.col(at[source_col])))  # sizes are counted once
    targets = source_targets(base.select("source", "size"), weights, cap).withColumnRenamed("source", "t_source")
    targets = targets.withColumn("ratio", F.when(F.col("source_size") > 0, F.col("target") / F.col("source_size")).otherwise(F.lit(0.0)))
    rows = base.join(targets, F.col("source").eqNullSafe(F.col("t_source")), "left").drop("t_source")
    rows = rows.withColumn("mix_key", F.xxhash64(F.lit(seed), F.col(at[id_col]), F.col("size")))
    # the hot source is spread over its buckets before the groups are shuffled
    buckets = F.greatest(F.ceil(F.col("docs") / BUCKET_DOCS), F.ceil(F.col("source_size") / BUCKET_WORDS), F.lit(1))
    rows = rows.withColumn("bucket", F.pmod(F.xxhash64(F.lit(seed + 1), F.col(at[id_col])), buckets))
    share = F.col("size") * F.col("docs") / F.greatest(F.col("source_size"), F.lit(1))
    rows = rows.withColumn("class", F.when(share >= CLASSES[0], 0).when(share >= CLASSES[1], 1).otherwise(2))
    held = rows.groupBy("source", "class").agg(F.sum("size").alias("words"))
    out, missed = None, None
    for k in range(len(CLASSES)):
        part = rows.filter(F.col("class") == k).withColumn("mix_r", F.col("ratio"))
        if missed is not None:
            rest = held.filter(F.col("class") >= k).groupBy("source").agg(F.sum("words").alias("open_words"))
            shift = missed.join(rest.withColumnRenamed("source", "r_source"), F.col("source").eqNullSafe(F.col("r_source"))).select(F.col("source").alias("s_source"), (F.col("missed") / F.greatest(F.col("open_words"), F.lit(1))).alias("shift"))
            part = part.join(shift, F.col("source").eqNullSafe(F.col("s_source")), "left").withColumn("mix_r", F.greatest(F.lit(0.0), F.least(F.lit(float(cap)), F.col("ratio") + F.coalesce("shift", F.lit(0.0))))).drop("s_source", "shift")
        done = _rounded(part, seed + 7 * k)
        out = done if out is None else out.unionByName(done)
        missed = out.groupBy("source").agg(F.sum(F.col("size") * (F.col("ratio") - F.col("copies"))).alias("missed"))
    return out.select(
        *[F.col(f"d{k}").alias(c) for k, c in enumerate(names)],
        F.col("size").alias("mix_size"), F.col("source_size").alias("mix_source_size"), F.col("target").alias("mix_target"),
        F.col("copies").alias("mix_copies"),
    )


def _rounded(rows: DataFrame, seed: int) -> DataFrame:
    """Rows with mix_r as whole copies, by exchanges in buckets and then in the reduction tree of what is left of these."""
    rows = rows.withColumn("whole", F.floor(F.col("mix_r") + F.lit(1e-9)))
    rows = rows.withColumn("mix_p", F.greatest(F.lit(0.0), F.col("mix_r") - F.col("whole"))).withColumn("mix_open", F.lit(False)).drop("mix_r")
    schema = T.StructType([T.StructField(f.name, f.dataType) for f in rows.schema.fields])
    step = _rounder(seed)
    level = cut(rows.groupBy("source", "bucket").applyInPandas(step, schema))
    out, left = level.filter("not mix_open"), level.filter("mix_open")
    widest = level.agg(F.max("bucket")).first()[0] or 0  # one number
    while widest > 0:
        widest //= FAN_IN
        level = cut(left.withColumn("bucket", F.floor(F.col("bucket") / FAN_IN)).groupBy("source", "bucket").applyInPandas(step, schema))
        out, left = out.unionByName(level.filter("not mix_open")), level.filter("mix_open")
    out = out.unionByName(left.mapInPandas(_closer(seed), schema))
    return out.withColumn("copies", F.col("whole") + F.round("mix_p").cast("bigint")).drop("whole", "mix_p", "mix_open")


def mixture(docs: DataFrame, id_col: str = "doc_id", source_col: str = "source", text_col: str = "text", weights: Sequence[float] = (5, 2, 1), cap: float = 3.0, seed: int = 42) -> DataFrame:
    """The mixture itself: the columns of ``docs``, every row as often as it is taken.

    Only ids, sources and sizes go through the rounding; texts are moved once, to meet their copies. Rows equal in id, source and text pool their copies on the one
    that comes first by its other columns, so reruns agree. Null ids and sources are values like others; null texts have size 0 and, like empty ones, are taken
    as often as their source's target is whole times its size. Empty table: no rows.
    """
    names = docs.columns
    rest = other_columns([f"d{k}" for k in range(len(names))], [f"d{names.index(c)}" for c in (id_col, source_col, text_col)])
    rows = docs.select(*[F.col(f"`{c}`").alias(f"d{k}") for k, c in enumerate(names)])
    at = {c: F.col(f"d{k}") for k, c in enumerate(names)}
    rows = rows.withColumn("k1", F.coalesce(at[id_col].cast("string"), F.lit(""))).withColumn("k2", F.xxhash64(at[source_col], at[text_col]))
    rows = rows.withColumn("k3", rest)
    narrow = rows.select("k1", "k2", at[source_col].alias("source"), n_words(at[text_col]).alias("words"))
    mixed = mix_copies(narrow.withColumn("k", F.xxhash64("k1", "k2")), "k", "source", "words", weights, cap, seed)
    copies = mixed.groupBy("k1", "k2").agg(F.sum("mix_copies").alias("copies")).filter("copies > 0")
    first = rows.withColumn("rn", F.row_number().over(Window.partitionBy("k1", "k2").orderBy("k3"))).filter("rn = 1").drop("rn")
    out = first.join(copies, ["k1", "k2"]).withColumn("copy", F.explode(F.sequence(F.lit(1), F.col("copies").cast("int"))))
    return out.select(*[F.col(f"d{k}").alias(c) for k, c in enumerate(names)])
