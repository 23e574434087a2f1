"""Quality rules whose cutoffs are chosen with controlled risk, in DataFrame functions only.

Base rules are fixed. Beyond them, each measure gets one cutoff per stratum (language): labelled documents are a holdout, and a cutoff is certified
if an exact binomial bound says that it rejects at most a given share of good documents; the level is divided by the number of measures and strata.
Cutoffs of one measure are tested from the loosest on and the exact bound grows with every step, so no more correction is needed along them.
Of the certified cutoffs, the one that parts bad from good best is used; where none is certified or none helps, the measure rejects nothing.
"""

from __future__ import annotations

import math

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from .common import SPACE_CHARS, WORD_RE, cut

#: Share of a stratum's good documents that all measures together may reject, and the chance of being wrong.
RISK, DELTA = 0.02, 0.05
#: Symbols that count, and measures with the step of their cutoffs (whole numbers: per mille, tenths of a character).
SYMBOLS = "#*$%&|<>"
MEASURES = {"symbol": 5, "repeat": 5, "dupline": 10, "wordlen": 4}
WINDOW = 5


def bound(value: Column, body) -> Column:
    """``body`` of a value that is computed once a row."""
    return F.transform(F.array(value), body)[0]


def repeated_words(words: Column) -> Column:
    """Number of words that lie in a run of WINDOW words found twice or more in the text."""

    def covered(wins: Column) -> Column:
        placed = F.sort_array(F.transform(wins, lambda h, i: F.struct(h.alias("h"), i.alias("i"))))

        def several(xs: Column) -> Column:
            same = lambda k: (k > 0) & (xs[k]["h"] == xs[F.greatest(k - 1, F.lit(0))]["h"]) | (k < F.size(xs) - 1) & (xs[k]["h"] == xs[F.least(k + 1, F.size(xs) - 1)]["h"])
            return F.sort_array(F.transform(F.filter(F.sequence(F.lit(0), F.size(xs) - 1), same), lambda k: xs[k]["i"]))

        add = lambda a, p: F.struct((a["n"] + F.least(F.lit(WINDOW), p - a["last"])).alias("n"), p.alias("last"))
        return F.aggregate(bound(placed, several), F.struct(F.lit(0).alias("n"), F.lit(-WINDOW).alias("last")), add, lambda a: a["n"])

    def of(hs: Column) -> Column:
        window = F.transform(F.sequence(F.lit(0), F.size(hs) - WINDOW), lambda i: F.xxhash64(*[hs[i + k] for k in range(WINDOW)]))
        some = lambda wins: F.when(F.size(F.array_distinct(wins)) == F.size(wins), F.lit(0)).otherwise(covered(wins))
        return F.when(F.size(hs) < WINDOW, F.lit(0)).otherwise(bound(window, some))

    return bound(F.transform(words, lambda w: F.xxhash64(w)), of)


def measures(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", stratum_col: str = "lang") -> DataFrame:
    """doc_id, stratum, n_words, word_chars, n_symbols, n_dup_lines, n_repeat_words, n_lines, base_failed for every row.

    Null text has no words; null strata are one stratum of their own, apart from the empty name. Whole texts; no shuffle.
    """
    text = F.coalesce(F.col(text_col), F.lit(""))
    words = F.regexp_extract_all(text, F.lit(WORD_RE), F.lit(0))
    stats = bound(words, lambda w: F.struct(F.size(w).cast("long").alias("n_words"), repeated_words(w).cast("long").alias("n_repeat_words")))
    lines = F.filter(F.split(text, "\n"), lambda x: F.trim(F.translate(x, SPACE_CHARS[1:], " " * (len(SPACE_CHARS) - 1))) != "")
    per_line = bound(lines, lambda x: F.struct(F.size(x).cast("long").alias("n_lines"), (F.size(x) - F.size(F.array_distinct(x))).cast("long").alias("n_dup_lines")))
    word_chars = F.length(F.translate(text, SPACE_CHARS, "")).cast("long")
    n_symbols = (F.length(text) - F.length(F.translate(text, SYMBOLS, ""))).cast("long")
    rows = docs.select(F.col(id_col).alias("doc_id"), F.col(stratum_col).cast("string").alias("stratum"), stats.alias("a"), per_line.alias("b"), word_chars.alias("word_chars"), n_symbols.alias("n_symbols"))
    failed = (F.col("n_words") < 10) | (100 * F.col("n_repeat_words") > 20 * F.col("n_words"))
    return rows.select("doc_id", "stratum", "a.n_words", "word_chars", "n_symbols", "b.n_dup_lines", "a.n_repeat_words", "b.n_lines").withColumn("base_failed", failed)


def measure_columns() -> dict[str, Column]:
    """Whole-number measures, larger for worse text; 0 where they are undefined."""
    ratio = lambda scale, a, b: F.when(F.col(b) > 0, F.expr(f"{scale} * {a} div {b}")).otherwise(F.lit(0)).cast("long")
    return {"symbol": ratio(1000, "n_symbols", "word_chars"), "repeat": ratio(1000, "n_repeat_words", "n_words"), "dupline": ratio(1000, "n_dup_lines", "n_lines"), "wordlen": ratio(10, "word_chars", "n_words")}


def binomial_tail(n: Column, k: Column, rate: float) -> Column:
    """P(X <= k) of a binomial with ``n`` trials at ``rate``, for k below the mean; 1 from the mean on. Exact up to rounding."""
    log_top = F.aggregate(F.sequence(F.lit(1), F.greatest(k, F.lit(1))), F.lit(0.0), lambda a, i: a + F.when(i <= k, F.log((n - k + i) / i)).otherwise(0.0))
    log_top = log_top + k * math.log(rate) + (n - k) * math.log1p(-rate)
    # terms below, each from the one above it
    step = lambda a, i: F.when(i <= k, F.struct((a["t"] * (k - i + 1) * (1 - rate) / ((n - k + i) * rate)).alias("t"), (a["s"] + a["t"] * (k - i + 1) * (1 - rate) / ((n - k + i) * rate)).alias("s"))).otherwise(a)
    total = F.aggregate(F.sequence(F.lit(1), F.greatest(k, F.lit(1))), F.struct(F.lit(1.0).alias("t"), F.lit(1.0).alias("s")), step, lambda a: a["s"])
    return F.when(k >= n * rate, F.lit(1.0)).otherwise(F.exp(log_top) * total)


def cutoffs(measured: DataFrame, labels: DataFrame, risk: float = RISK, delta: float = DELTA) -> DataFrame:
    """stratum and, for each measure, its cutoff (null: none is certified, or none helps).

    ``labels``: doc_id, quality (1 good; of several labels of an id the highest counts, nulls are left out). The counts come from one map-side
    combined aggregation into cutoffs, so only one row per stratum, measure and step that labelled documents reach is left for the windows.
    """
    marks = labels.filter("doc_id is not null and quality is not null").groupBy("doc_id").agg(F.max("quality").alias("quality"))
    held = measured.filter("not base_failed").join(marks, "doc_id")
    steps = zip(MEASURES.items(), measure_columns().values(), strict=True)
    cells = F.explode(F.array(*[F.struct(F.lit(m).alias("measure"), F.ceil(col / step).cast("long").alias("cell")) for (m, step), col in steps]))
    good = F.sum(F.when(F.col("quality") == 1, 1).otherwise(0))
    counts = held.select("stratum", "quality", cells.alias("c")).groupBy("stratum", "c.measure", "c.cell").agg(good.alias("g"), (F.count(F.lit(1)) - good).alias("b"))
    # cutoff number c rejects the cells above it
    by = Window.partitionBy("stratum", "measure")
    above = by.orderBy(F.col("cell").desc()).rowsBetween(Window.unboundedPreceding, -1)
    zero = lambda c: F.coalesce(c, F.lit(0)).cast("long")
    totals = [F.sum(c).over(by).cast("long").alias(n) for c, n in (("g", "n_good"), ("b", "n_bad"))]
    rows = counts.select("*", *totals, *[zero(F.sum(c).over(above)).alias(n) for c, n in (("g", "k_good"), ("b", "k_bad"))])
    n_strata = measured.select("stratum").distinct().agg(F.count(F.lit(1)).alias("n_strata"))
    rows = rows.join(F.broadcast(n_strata))  # one row
    tail = binomial_tail(F.col("n_good"), F.col("k_good"), risk / len(MEASURES))
    gain = F.col("k_bad") * F.col("n_good") - F.col("k_good") * F.col("n_bad")
    sure = rows.withColumn("gain", gain).filter((F.col("gain") > 0) & (tail <= F.lit(delta) / (len(MEASURES) * F.col("n_strata"))))
    best = sure.groupBy("stratum", "measure").agg(F.max(F.struct("gain", "cell")).alias("top"))
    pick = lambda m, step: F.max(F.when(F.col("measure") == m, F.col("top.cell") * step)).alias(f"cut_{m}")
    return best.groupBy("stratum").agg(*[pick(m, step) for m, step in MEASURES.items()])


def judge(docs: DataFrame, labels: DataFrame) -> DataFrame:
    """Measures of every row with kept: false if a base rule fails or a measure is above its stratum's cutoff.

    Rows with null ids, repeated rows and unlabelled strata are judged like others; without labels only the base rules reject.
    """
    measured = cut(measures(docs))
    cuts = cutoffs(measured, labels).withColumnRenamed("stratum", "cut_stratum")
    rows = measured.join(cuts, F.col("stratum").eqNullSafe(F.col("cut_stratum")), "left")
    over = F.lit(False)
    for m, col in measure_columns().items():
        over = over | F.coalesce(col > F.col(f"cut_{m}"), F.lit(False))
    return rows.withColumn("kept", ~(F.col("base_failed") | over)).drop("cut_stratum")
