"""The experiments on the given tables: many small runs as one Spark job, one group a configuration.

Runs are fitted, and their learning rates chosen, on a bounded sample (MAX_ROWS, the first by a hash of the key) that travels with the tasks; what they report is measured
on all held-out rows of the table. Large models are trained by ``trainers`` instead.
"""

from __future__ import annotations

from collections.abc import Iterator, Sequence
from itertools import product

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..operators import accuracy, cost
from ..sources.catalog import load
from . import kernels
from .losses import hashed_text

#: Most rows that runs are fitted on, share of test rows, learning rates that are tried, hashed features of text.
MAX_ROWS, TEST, RATES, TEXT_SIZE, CLASSES = 4000, 0.25, (0.5, 1.5, 5.0, 15.0, 40.0), 2**11, 10


def held_out(key: str):
    """Rows that no run is fitted on, by a hash of the key."""
    return F.pmod(F.xxhash64(F.lit("test"), F.col(key)), F.lit(round(1 / TEST))) == 0


def _parts(a: np.ndarray, y: np.ndarray, test: np.ndarray, classes: int, model: str, rows: DataFrame, dense) -> dict:
    """The sample without test rows, a fifth of it kept back to choose learning rates by; reports are of the test rows, which nothing is fitted or chosen by."""
    whole = test.all() or not test.any()
    mine = np.flatnonzero(~test | whole)
    check = np.arange(len(mine)) % 5 == 4
    fit, chosen = (mine[~check], mine[check]) if check.any() else (mine, mine)
    rows = rows if whole else rows.filter("test")
    return {"a": a[fit], "y": y[fit], "ta": a[chosen], "ty": y[chosen], "classes": classes, "model": model, "rows": rows, "dense": dense}


def _image_dense(batch: pa.RecordBatch) -> np.ndarray:
    a = np.stack(batch.column("f").to_numpy(zero_copy_only=False)).astype(float)
    return np.concatenate([a, np.ones((len(a), 1))], axis=1)


def _text_dense(batch: pa.RecordBatch) -> np.ndarray:
    a, f = np.zeros((batch.num_rows, TEXT_SIZE + 1)), batch.column("f")
    x = f.flatten()
    a[np.repeat(np.arange(len(a)), f.value_lengths().to_numpy()), x.field("pos").to_numpy()] = x.field("v").to_numpy()
    return a


def _sample(rows: DataFrame, dense) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    got = rows.toArrow().combine_chunks()  # MAX_ROWS at most
    batches = got.to_batches()
    a = np.concatenate([dense(b) for b in batches])
    return a, got["y"].to_numpy().astype(int), got["test"].to_numpy()


def image_data(spark: SparkSession, sf: str, model: str = "softmax") -> dict:
    """Vectors of ``embeddings`` with the number of their largest of ten components as class: the given labels cannot be told from held-out vectors."""
    rows = load(spark, sf, "embeddings", "vec_id", "embedding").filter("size(embedding) >= 10")
    first = F.slice("embedding", 1, CLASSES)
    rows = rows.select("vec_id", F.col("embedding").alias("f"), (F.array_position(first, F.array_max(first)) - 1).cast("int").alias("y"), F.coalesce(held_out("vec_id"), F.lit(False)).alias("test"))
    picked = rows.orderBy(F.xxhash64("vec_id"), "vec_id").limit(MAX_ROWS)
    return _parts(*_sample(picked, _image_dense), CLASSES, model, rows, _image_dense)


def text_data(spark: SparkSession, sf: str, task: str = "lang") -> dict:
    """Hashed words of ``documents``: is the language English, or the quality label."""
    docs = load(spark, sf, "documents", "doc_id", "text", "lang").filter("doc_id is not null")
    marks = docs.select("doc_id", (F.col("lang") == "en").cast("int").alias("y")) if task == "lang" else load(spark, sf, "labels", "doc_id", "quality").select("doc_id", F.col("quality").alias("y"))
    marks = marks.filter("y is not null").withColumn("test", held_out("doc_id"))
    picked = marks.orderBy(F.xxhash64("doc_id"), "doc_id").limit(MAX_ROWS)
    sample = hashed_text(docs.join(F.broadcast(picked), "doc_id", "left_semi"), TEXT_SIZE).join(F.broadcast(picked), "doc_id").orderBy("doc_id")
    return _parts(*_sample(sample, _text_dense), 2, "softmax", hashed_text(docs, TEXT_SIZE).join(marks, "doc_id"), _text_dense)


def evaluate(data: dict, models: list[np.ndarray]) -> DataFrame:
    """model (its number), loss, acc over all rows of ``data['rows']``: every task adds its rows up, for all models."""
    classes, kind, dense = data["classes"], data["model"], data["dense"]
    shared = data["rows"].sparkSession.sparkContext.broadcast(models)  # as many as the sweep has runs and logged steps, whatever the rows

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        n, sums = 0, np.zeros((2, len(shared.value)))
        for batch in batches:
            for s in range(0, batch.num_rows, 1024):
                b = batch.slice(s, 1024)
                a, y = dense(b), b.column("y").to_numpy().astype(int)
                n += len(y)
                for k, x in enumerate(shared.value):
                    loss, hits = kernels.judged(x, a, y, classes, kind)
                    sums[:, k] += loss.sum(), hits.sum()
        if n:
            yield pa.RecordBatch.from_arrays([pa.array(np.arange(len(shared.value)), pa.int32()), pa.array(sums[0]), pa.array(sums[1]), pa.array(np.full(len(shared.value), n))], names=["model", "l", "h", "n"])

    parts = data["rows"].select("f", "y").mapInArrow(run, "model int, l double, h double, n long")
    return parts.groupBy("model").agg((F.sum("l") / F.sum("n")).alias("loss"), (F.sum("h") / F.sum("n")).alias("acc"))


def sweep(spark: SparkSession, data: dict, configs: list[tuple[str, float, int, int, int]], steps: int) -> DataFrame:
    """Run logs of configurations (method, k_frac, m, batch, seed); each run takes the learning rate with the least loss at its end on the sample's validation rows.

    Runs are fitted on the sample; loss and acc of the logs are of all held-out rows.
    """
    shared = spark.sparkContext.broadcast({k: data[k] for k in ("a", "y", "ta", "ty", "classes", "model")})

    def one(key: tuple, pdf: pd.DataFrame) -> pd.DataFrame:
        out = []
        for r in pdf.itertuples():
            runs = []
            for eta in RATES:
                kept: list[np.ndarray] = []
                runs.append((eta, kernels.train(shared.value, r.method, r.k_frac, r.m, r.batch, r.seed, eta, steps, models=kept), kept))
            eta, best, kept = min(runs, key=lambda x: (not np.isfinite(x[1][-1][2]), x[1][-1][2]))
            out += [(r.method, r.seed, r.m, r.k_frac, eta, step, bits, norm, x.tobytes()) for (step, bits, _, _, norm), x in zip(best, kept, strict=True)]
        return pd.DataFrame(out, columns=["method", "seed", "m", "k_frac", "eta", "step", "bits_cum", "grad_norm2", "x"])

    rows = [(k, *c) for k, c in enumerate(configs)]
    table = spark.createDataFrame(rows, "config int, method string, k_frac double, m int, batch int, seed int")
    fitted = table.repartition(len(rows), "config").groupBy("config").applyInPandas(one, "method string, seed int, m int, k_frac double, eta double, step int, bits_cum long, grad_norm2 double, x binary").collect()
    found = evaluate(data, [np.frombuffer(r["x"]) for r in fitted])
    logs = spark.createDataFrame([(k, *r[:-1]) for k, r in enumerate(fitted)], "model int, method string, seed int, m int, k_frac double, eta double, step int, bits_cum long, grad_norm2 double")
    return logs.join(found, "model").select("method", "seed", "m", "k_frac", "eta", "step", "bits_cum", "loss", "acc", "grad_norm2")


def sparse_configs(fractions, m_batch, seeds: int) -> list:
    kept = [(meth, k, m, b, s) for meth, k, (m, b), s in product(("tier_segment", "topk", "randk", "ef21m"), fractions, m_batch, range(seeds))]
    return kept + [("uncompressed", 1.0, m, b, s) for (m, b), s in product(m_batch, range(seeds))]


def curve_text_sparse(spark: SparkSession, sf: str, seeds: int = 5, steps: int = 30) -> DataFrame:
    """Accuracy over bits and over steps of sparse messages, text task."""
    return sweep(spark, text_data(spark, sf), sparse_configs((0.01, 0.05, 0.1, 0.5), ((4, 16), (32, 16)), seeds), steps)


def curve_image_quantized(spark: SparkSession, sf: str, seeds: int = 5, steps: int = 40) -> DataFrame:
    """Two-bit messages, image task: level-sampled fixed point, plain fixed point, stochastic rounding, none."""
    configs = [(meth, 1.0, m, b, s) for meth, (m, b), s in product(("tier_fixed", "fixed_2bit", "qsgd_2bit", "uncompressed"), ((4, 128), (32, 64)), range(seeds))]
    return sweep(spark, image_data(spark, sf), configs, steps)


def curve_image_sparse(spark: SparkSession, sf: str, seeds: int = 5, steps: int = 20) -> DataFrame:
    """Sparse messages, image task with a hidden layer."""
    return sweep(spark, image_data(spark, sf, "mlp"), sparse_configs((0.001, 0.005, 0.01, 0.05), ((4, 128), (32, 64)), seeds), steps)


def curve_text_rounding(spark: SparkSession, sf: str, seeds: int = 5, steps: int = 30) -> DataFrame:
    """Rounding to nearest at 2, 4, 8, 16 bits against its level-sampled ladder and none, text task."""
    configs = [(meth, 1.0, m, 16, s) for meth, m, s in product(("tier_rtn", "rtn_2", "rtn_4", "rtn_8", "rtn_16", "uncompressed"), (4, 32), range(seeds))]
    return sweep(spark, text_data(spark, sf), configs, steps)


def report_seed_summary(spark: SparkSession, sf: str) -> DataFrame:
    return accuracy.seed_summary(curve_image_quantized(spark, sf, steps=30))


def report_bits_to_accuracy(spark: SparkSession, sf: str) -> DataFrame:
    """Least bits at which runs reach an accuracy of one half."""
    return cost.first_to_reach(curve_image_quantized(spark, sf, steps=30), 0.5)


def report_speedup(spark: SparkSession, sf: str) -> DataFrame:
    """Steps to an accuracy with 4 and with 32 workers."""
    return accuracy.speedup(cost.first_to_reach(curve_image_quantized(spark, sf, steps=30), 0.5, "step"))


def divergence(method: str, eta: float = 0.01, steps: int = 2000, seed: int = 0, start: Sequence[float] = (1.0, 1.0, 1.0)) -> float:
    """Norm reached on three quadratics whose largest partial derivatives cancel: naive largest-coordinate messages grow without end."""
    rng, x = np.random.default_rng(seed), np.array(start, float)
    a = np.array([[-3.0, 2, 2], [2, -3, 2], [2, 2, -3]])
    factory = {"topk": lambda: kernels.top_k(1), "tier_segment": lambda: kernels.segment_tier(1), "randk": lambda: kernels.rand_k(1), "ef21m": lambda: kernels.Feedback(1), "uncompressed": lambda: kernels.uncompressed}[method]
    workers = [factory() for _ in range(3)]
    for _ in range(steps):
        x = x - eta * sum(c(2 * (v @ x) * v + 0.5 * x, rng)[0] for c, v in zip(workers, a, strict=True)) / 3
        if not np.isfinite(x).all() or np.abs(x).max() > 1e100:
            return float("inf")
    return float(np.sqrt(x @ x))


def divergence_fixture(spark: SparkSession, sf: str) -> DataFrame:
    """label, method, start, norm, grows: the norm that each method reaches from the mean of a class of vectors, by its first three components."""
    rows = load(spark, sf, "embeddings", "label", "embedding")
    means = rows.groupBy("label").agg(*[F.avg(F.get("embedding", F.lit(k)).cast("double")).alias(f"x{k}") for k in range(3)]).dropna(subset=["x0", "x1", "x2"])
    runs = means.withColumn("method", F.explode(F.array(*[F.lit(m) for m in ("topk", "tier_segment", "randk", "ef21m", "uncompressed")]))).repartition(16, "label", "method")

    def reached(parts: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for part in parts:
            x = part[["x0", "x1", "x2"]].to_numpy()
            part["start"], part["norm"] = np.sqrt((x * x).sum(axis=1)), [divergence(m, start=s) for m, s in zip(part["method"], x, strict=True)]
            yield part[["label", "method", "start", "norm"]]

    return runs.mapInPandas(reached, "label int, method string, start double, norm double").withColumn("grows", F.col("norm") > F.col("start"))


QUERIES = {f.__name__: f for f in (curve_text_sparse, curve_image_quantized, curve_image_sparse, curve_text_rounding, report_seed_summary, report_bits_to_accuracy, report_speedup, divergence_fixture)}
