"""Structured Streaming around the methods: watermarks, windows, deduplication, joins, stateful error feedback and online training."""

from __future__ import annotations

import uuid
from collections.abc import Iterator
from contextlib import contextmanager

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

from ..plans.lineage import prepare
from ..sources.catalog import SCHEMAS

#: Setting of a session that names the store of streams' states, and the store on disk.
STORE, ROCKS = "spark.sql.streaming.stateStore.providerClass", "org.apache.spark.sql.execution.streaming.state.RocksDBStateStoreProvider"


def event_stream(spark: SparkSession, folder: str, glob: str = "*.parquet", files: int = 1) -> DataFrame:
    """Events of a folder as they come, ``files`` a batch; ts as a timestamp, as watermarks need."""
    rows = spark.readStream.schema(SCHEMAS["events"]).option("maxFilesPerTrigger", files).option("pathGlobFilter", glob).parquet(folder)
    return rows.withColumn("ts", F.col("ts").cast("timestamp"))


def with_watermark(events: DataFrame, delay: str = "1 day") -> DataFrame:
    return events.withWatermark("ts", delay)


def windowed_sums(events: DataFrame, kind: str = "tumbling", length: str = "1 day", slide: str = "6 hours") -> DataFrame:
    """Counts and sums per event type and tumbling, sliding or session window."""
    w = {"tumbling": lambda: F.window("ts", length), "sliding": lambda: F.window("ts", length, slide), "session": lambda: F.session_window("ts", slide)}[kind]()
    return events.groupBy(w.alias("w"), "event_type").agg(F.count(F.lit(1)).alias("n"), F.sum("value").alias("value")).select(F.col("w.start").alias("start"), "event_type", "n", "value")


def dedup(events: DataFrame) -> DataFrame:
    """First arrival of each event id within the watermark."""
    return events.dropDuplicatesWithinWatermark(["event_id"])


def enrich(events: DataFrame, users: DataFrame) -> DataFrame:
    """Stream joined with a static table by user."""
    return events.join(users, "user_id", "left")


def pair(a: DataFrame, b: DataFrame, minutes: int = 10) -> DataFrame:
    """Stream-stream join: events of one user within some minutes of each other. Both sides need watermarks, which bound the state."""
    x, y = a.select(F.col("event_id").alias("a_id"), F.col("user_id").alias("a_user"), F.col("ts").alias("a_ts")), b.select(F.col("event_id").alias("b_id"), F.col("user_id").alias("b_user"), F.col("ts").alias("b_ts"))
    near = F.expr(f"a_user = b_user AND a_id < b_id AND b_ts BETWEEN a_ts - INTERVAL {minutes} MINUTES AND a_ts + INTERVAL {minutes} MINUTES")
    return x.join(y, near)


def error_feedback(grads: DataFrame, k: int, beta: float = 0.1) -> DataFrame:
    """Stateful compression of a stream of gradients (worker, step, vec): per worker, momentum and tracker are kept and the k largest differences are sent."""

    def step(key: tuple, parts: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
        momentum, tracked = (list(x) for x in state.get) if state.exists else (None, None)
        rows = pd.concat(list(parts)).sort_values("step", kind="stable")
        out = []
        for r in rows.itertuples():
            g = [float(v) for v in r.vec]
            momentum = g if momentum is None else [(1 - beta) * m + beta * v for m, v in zip(momentum, g, strict=True)]
            tracked = [0.0] * len(g) if tracked is None else tracked
            diff = [m - t for m, t in zip(momentum, tracked, strict=True)]
            for p in sorted(range(len(g)), key=lambda p: (-abs(diff[p]), p))[:k]:
                tracked[p] += diff[p]
                out.append((key[0], r.step, p, diff[p]))
        state.update((momentum, tracked))
        yield pd.DataFrame(out, columns=["worker", "step", "pos", "val"])

    return grads.groupBy("worker").applyInPandasWithState(step, "worker int, step long, pos int, val double", "momentum array<double>, tracked array<double>", "append", GroupStateTimeout.NoTimeout)


@contextmanager
def states_on_disk(spark: SparkSession) -> Iterator[None]:
    """Streams that start here keep their states in RocksDB, on the executors' disks, unless the session names another store: ids of a whole stream need not fit memory."""
    mine = spark.conf.get(STORE, None) is None
    if mine:
        spark.conf.set(STORE, ROCKS)
    try:
        yield
    finally:
        if mine:
            spark.conf.unset(STORE)


def drain(stream: DataFrame, mode: str, each=None) -> DataFrame | None:
    """Runs a stream over what is there. Without ``each``: its result as a table; else ``each(batch, id)`` for every batch.

    Appended rows, as many as the stream has, go to files in the shared checkpoint folder; the results of ``complete`` and ``update`` are aggregates and are held by the driver.
    """
    spark = stream.sparkSession
    prepare(spark)
    name = f"stream_{uuid.uuid4().hex}"
    place = f"{spark.sparkContext.getCheckpointDir()}/{name}"
    writer = stream.writeStream.outputMode(mode).option("checkpointLocation", place).trigger(availableNow=True)
    files = not each and mode == "append"
    if files:
        writer = writer.format("parquet").option("path", f"{place}_rows")
    elif each:
        writer = writer.foreachBatch(each)
    else:
        writer = writer.format("memory").queryName(name)
    with states_on_disk(spark):
        query = writer.start()
    query.awaitTermination()
    if files:
        return spark.read.schema(stream.schema).parquet(f"{place}_rows")
    return None if each else spark.table(name)


def online_sgd(stream: DataFrame, eta: float = 0.5, start: tuple[float, float] = (0.0, 0.0)) -> tuple[float, float]:
    """Least squares of ln(1 + value) on a constant and the event's hour, one step a batch. A batch that comes again is passed over, by its number."""
    state = {"x": start, "done": set()}

    def step(batch: DataFrame, number: int) -> None:
        if number in state["done"]:
            return
        a = F.hour("ts") / 24.0
        r = state["x"][0] + state["x"][1] * a - F.log1p("value")
        g = batch.agg(F.avg(r), F.avg(r * a)).first()
        if g[0] is not None:
            state["x"] = (state["x"][0] - eta * g[0], state["x"][1] - eta * g[1])
        state["done"].add(number)

    drain(stream, "append", step)
    return state["x"]


def stream_tumbling(spark: SparkSession, sf: str) -> DataFrame:
    rows = windowed_sums(event_stream(spark, sf, "events.parquet"), "tumbling")
    return drain(rows, "complete").select(F.col("start").cast("date").alias("day"), "event_type", "n", F.round("value", 2).alias("value"))


def stream_online_sgd(spark: SparkSession, sf: str) -> DataFrame:
    x = online_sgd(event_stream(spark, sf, "events.parquet"))
    return spark.createDataFrame([(0, round(x[0], 6)), (1, round(x[1], 6))], "pos int, val double")


def stream_dedup(spark: SparkSession, sf: str) -> DataFrame:
    got = drain(dedup(with_watermark(event_stream(spark, sf, "events.parquet"))).select("event_type"), "append")
    return got.groupBy("event_type").agg(F.count(F.lit(1)).alias("n"))


QUERIES = {f.__name__: f for f in (stream_tumbling, stream_online_sgd, stream_dedup)}
ORACLES = {
    "stream_tumbling": "SELECT ts::DATE AS day, event_type, count(*) AS n, round(sum(value), 2) AS value FROM events GROUP BY 1, 2",
    "stream_online_sgd": "SELECT 0 AS pos, round(0.5 * avg(ln(1 + value)), 6) AS val FROM events UNION ALL SELECT 1, round(0.5 * avg(ln(1 + value) * hour(ts) / 24.0), 6) FROM events",
    "stream_dedup": "SELECT event_type, count(DISTINCT event_id) AS n FROM events GROUP BY event_type",
}
