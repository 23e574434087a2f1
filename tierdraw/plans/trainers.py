"""Data-parallel descent with compressed messages: one Spark job a step, the model of n numbers on the driver, everything per worker in DataFrames.

A method turns the workers' gradients of a step into what the server averages. State (momentum, trackers) is a table keyed by worker and position and is written every step.
"""

from __future__ import annotations

from collections.abc import Callable, Sequence
from dataclasses import dataclass, field

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.draws import hash_uniform
from ..operators import base_compressors as base
from ..operators.levels import LevelFamily
from ..operators.telescoping import tier_estimate
from ..operators.vectors import subtract
from .lineage import cut
from .losses import gradient, minibatch

KEYS = ["step", "worker"]


class Method:
    """``message(gradient of the step, step, again)``: messages with step, worker, pos, val that are averaged; ``again(model)`` gives gradients on the same samples."""

    label = "uncompressed"

    def start(self) -> None:
        """Forgets the state of an earlier run."""

    def message(self, grads: DataFrame, step: int, seed: int, model: Sequence[float], again: Callable[[Sequence[float]], DataFrame]) -> DataFrame:
        return grads

    def bits(self, n: int, step: int) -> int:
        """Bits that one worker sends."""
        return 64 * n


class Uncompressed(Method):
    """Plain averaging."""


@dataclass
class TierDraw(Method):
    """Level-sampled messages with fixed (a table) or adaptive probabilities."""

    family: LevelFamily
    probs: DataFrame | str = "adaptive"
    bits_per: Callable[[int], int] = field(default=lambda n: 64 * n)
    label = "tier"

    def message(self, grads, step, seed, model, again):
        return tier_estimate(grads, KEYS, self.family, self.probs, seed).select(*KEYS, "pos", "val")

    def bits(self, n, step):
        return self.bits_per(n)


@dataclass
class Compressed(Method):
    """A baseline compressor applied to each message: ``f(coords, keys, seed)``."""

    title: str
    f: Callable[[DataFrame, Sequence[str], int], DataFrame]
    bits_per: Callable[[int], int] = field(default=lambda n: 64 * n)

    def message(self, grads, step, seed, model, again):
        return self.f(grads, KEYS, seed).select(*KEYS, "pos", "val")

    def bits(self, n, step):
        return self.bits_per(n)


def top_k(k: int) -> Compressed:
    return Compressed("topk", lambda c, g, s: base.top_k(c, g, k), lambda n: 64 * k)


def rand_k(k: int) -> Compressed:
    return Compressed("randk", lambda c, g, s: base.rand_k(c, g, k, s), lambda n: 64 * k)


@dataclass
class ErrorFeedbackMomentum(Method):
    """EF21 with momentum: workers send the k largest coordinates of momentum less tracker; beta = 1 is EF21. ``init='full'`` sends the first gradient whole."""

    k: int
    beta: float = 0.1
    init: str = "full"
    label = "ef21m"
    state: DataFrame | None = None

    def start(self):
        self.state = None

    def message(self, grads, step, seed, model, again):
        g = grads.select("worker", "pos", F.col("val").alias("g"))
        if self.state is None:
            first = F.col("g") if self.init == "full" else F.lit(0.0)
            self.state = cut(g.select("worker", "pos", first.alias("momentum"), first.alias("tracked")))
            if self.init == "full":
                return self._tracked(step)
        rows = self.state.join(g, ["worker", "pos"], "full").na.fill(0.0)
        rows = rows.select("worker", "pos", ((1 - self.beta) * F.col("momentum") + self.beta * F.col("g")).alias("momentum"), "tracked")
        sent = base.top_k(rows.select("worker", "pos", (F.col("momentum") - F.col("tracked")).alias("val")), ["worker"], self.k)
        new = rows.join(sent.withColumnRenamed("val", "c"), ["worker", "pos"], "left").na.fill(0.0)
        self.state = cut(new.select("worker", "pos", "momentum", (F.col("tracked") + F.col("c")).alias("tracked")))
        return self._tracked(step)

    def _tracked(self, step: int) -> DataFrame:
        return self.state.select(F.lit(step).alias("step"), "worker", "pos", F.col("tracked").alias("val"))

    def bits(self, n, step):
        return 64 * n if step == 1 and self.init == "full" else 64 * self.k


@dataclass
class MarinaTemplate(Method):
    """Whole gradients with chance p (one coin for all), else compressed differences of gradients on the same samples, added to the running estimate."""

    inner: Method
    p: float
    label = "marina"
    state: DataFrame | None = None
    before: list[float] | None = None
    whole: bool = True

    def start(self):
        self.state = self.before = None
        self.whole = True

    def coin(self, spark, seed: int, step: int) -> bool:
        """Whether this step sends whole gradients."""
        return step == 1 or spark.range(1).select(hash_uniform(seed, "coin", step).alias("u")).first()[0] < self.p

    def message(self, grads, step, seed, model, again):
        self.whole = self.coin(grads.sparkSession, seed, step)
        if self.whole:
            new = grads
        else:
            diff = subtract(grads, again(self.before).withColumn("step", F.lit(step)), KEYS)
            sent = self.inner.message(diff, step, seed, model, again)
            held = self.state.withColumn("step", F.lit(step)).select(*KEYS, "pos", "val")
            new = held.unionByName(sent.select(*KEYS, "pos", "val")).groupBy(*KEYS, "pos").agg(F.sum("val").alias("val"))
        self.state, self.before = cut(new.select(*KEYS, "pos", "val")), list(model)
        return self.state

    def bits(self, n, step):
        """Of the step whose message was made last."""
        return 64 * n if self.whole else self.inner.bits(n, step)


@dataclass
class DashaTemplate(Method):
    """Compressed tracker with momentum correction, for whole gradients of shards: never sends a whole gradient after the first step."""

    inner: Method
    a: float
    label = "dasha"
    state: DataFrame | None = None

    def start(self):
        self.state = None

    def message(self, grads, step, seed, model, again):
        h = grads.select("worker", "pos", F.col("val").alias("h1"))
        if self.state is None:
            self.state = cut(h.select("worker", "pos", F.col("h1").alias("h"), F.col("h1").alias("g")))
        else:
            rows = self.state.join(h, ["worker", "pos"], "full").na.fill(0.0)
            change = rows.select(F.lit(step).alias("step"), "worker", "pos", (F.col("h1") - F.col("h") - self.a * (F.col("g") - F.col("h"))).alias("val"))
            sent = self.inner.message(change, step, seed, model, again).select("worker", "pos", F.col("val").alias("c"))
            new = rows.join(sent, ["worker", "pos"], "left").na.fill(0.0)
            self.state = cut(new.select("worker", "pos", F.col("h1").alias("h"), (F.col("g") + F.col("c")).alias("g")))
        return self.state.select(F.lit(step).alias("step"), "worker", "pos", F.col("g").alias("val"))

    def bits(self, n, step):
        return 64 * n if step == 1 else self.inner.bits(n, step)


def fit(samples: DataFrame, n: int, method: Method, steps: int, eta: float, m: int, loss: str = "squares", fraction: float = 1.0, seed: int = 0, start: Sequence[float] | None = None) -> tuple[list[list[float]], list[int]]:
    """Models of every step (the first is the start) and cumulative bits of all workers.

    A step is one job: gradients, messages and their average, of which n numbers reach the driver. ``samples`` is scanned with pruned columns; a
    table partitioned by batch is filtered to the step's files.
    """
    method.start()
    model = [float(v) for v in (start or [0.0] * n)]
    history, bits = [model], [0]
    for step in range(1, steps + 1):
        batch = minibatch(samples, step, fraction, seed)
        again = lambda x, b=batch: gradient(b, x, loss)
        grads = again(model).withColumn("step", F.lit(step)).select(*KEYS, "pos", "val")
        sent = method.message(grads, step, seed, model, again)
        mean = dict(sent.groupBy("pos").agg((F.sum("val") / m).alias("val")).collect())  # n rows at most
        model = [v - eta * mean.get(p, 0.0) for p, v in enumerate(model)]
        history.append(model)
        bits.append(bits[-1] + m * method.bits(n, step))
    return history, bits


def average_iterate(history: Sequence[Sequence[float]]) -> list[float]:
    """Mean of the models before each step, to which convex bounds apply."""
    used = history[:-1] or history
    return [sum(c) / len(used) for c in zip(*used, strict=True)]
