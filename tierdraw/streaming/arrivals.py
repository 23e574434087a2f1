"""Events replayed in order of arrival, some of them late, and what a watermark drops of them."""

from __future__ import annotations

import uuid

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions.draws import hash_uniform
from ..plans.lineage import cut, prepare
from ..sources.catalog import load
from .online import drain, event_stream, windowed_sums, with_watermark

#: Files of the replay, share of events that come late, files by which they are late, seed of the choice.
FILES, LATE_SHARE, LATE_BY, SEED = 10, 0.02, 3, 11


def with_part(events: DataFrame) -> DataFrame:
    """Adds part, the file an event arrives in: equal stretches of time in order; a hashed share of the events comes some files later, in the last one at most."""
    us = F.unix_micros(F.col("ts").cast("timestamp"))
    span = events.agg(F.min(us).alias("lo"), F.max(us).alias("hi"))
    rows = events.crossJoin(F.broadcast(span))  # one row
    part = F.least(F.floor((us - F.col("lo")) * FILES / F.greatest(F.col("hi") - F.col("lo"), F.lit(1))), F.lit(FILES - 1))
    late = hash_uniform(SEED, F.col("event_id")) < LATE_SHARE
    return rows.withColumn("part", F.when(late, F.least(part + LATE_BY, F.lit(FILES - 1))).otherwise(part).cast("int")).drop("lo", "hi")


def replay(events: DataFrame) -> str:
    """Folder with one file a part, written one after another into the shared checkpoint folder; a part without events is an empty file."""
    spark = events.sparkSession
    prepare(spark)
    folder = f"{spark.sparkContext.getCheckpointDir()}/arrivals_{uuid.uuid4().hex}"
    held = cut(with_part(events))
    for part in range(FILES):
        held.filter(F.col("part") == part).drop("part").coalesce(1).write.mode("append").parquet(folder)
    return folder


def late_counts(events: DataFrame, folder: str, delay: str = "1 day") -> DataFrame:
    """day, arrived, counted, late: events of a day, those that a stream of the folder counts under the watermark, and those that it drops.

    A day without counted events has counted 0; rows without a time are in no day; an empty table gives no rows.
    """
    windows = windowed_sums(with_watermark(event_stream(events.sparkSession, folder), delay), "tumbling")
    counted = drain(windows, "update").groupBy("start", "event_type").agg(F.max("n").alias("n"))  # the last update of a window is the largest
    counted = counted.groupBy(F.col("start").cast("date").alias("day")).agg(F.sum("n").alias("counted"))
    arrived = events.filter("ts is not null").groupBy(F.col("ts").cast("date").alias("day")).agg(F.count(F.lit(1)).alias("arrived"))
    both = arrived.join(counted, "day", "left").withColumn("counted", F.coalesce("counted", F.lit(0).cast("long")))
    return both.withColumn("late", F.col("arrived") - F.col("counted"))


def stream_late_data(spark: SparkSession, sf: str) -> DataFrame:
    events = load(spark, sf, "events")
    return late_counts(events, replay(events))


def late_data_sql(delay_ms: int = 86_400_000) -> str:
    """The watermark that a batch drops by is the latest time of all batches but the last two, in milliseconds, less the delay."""
    uniform = f"('0x' || substr(md5({SEED} || '|' || event_id), 1, 13))::BIGINT / 4503599627370496.0"
    return (
        "WITH span AS (SELECT epoch_us(min(ts)) AS lo, epoch_us(max(ts)) AS hi FROM events), "
        f"placed AS (SELECT *, least((epoch_us(ts) - lo) * {FILES} // greatest(hi - lo, 1), {FILES - 1}) AS p FROM events, span), "
        f"parts AS (SELECT *, CASE WHEN {uniform} < {LATE_SHARE} THEN least(p + {LATE_BY}, {FILES - 1}) ELSE p END AS part FROM placed), "
        f"marks AS (SELECT b, (SELECT epoch_us(max(ts)) // 1000 FROM parts WHERE part <= b - 2) - {delay_ms} AS mark FROM (SELECT unnest(range({FILES})) AS b)), "
        "judged AS (SELECT ts::DATE AS day, coalesce(epoch_us(ts::DATE + INTERVAL 1 DAY) <= mark * 1000, false) AS late FROM parts JOIN marks ON part = b) "
        "SELECT day, count(*) AS arrived, count(*) FILTER (WHERE NOT late) AS counted, count(*) FILTER (WHERE late) AS late FROM judged GROUP BY day"
    )


QUERIES = {"stream_late_data": stream_late_data}
ORACLES = {"stream_late_data": late_data_sql()}
