import pytest
from pyspark.sql import functions as F

from tierdraw.streaming import online

SF = "/root/testdata/sf0.001"


@pytest.fixture(scope="module")
def folder(spark, tmp_path_factory):
    """Events in order of time as four files; some rows come in a later file."""
    path = str(tmp_path_factory.mktemp("events") / "parts")
    rows = spark.read.parquet(f"{SF}/events.parquet").withColumn("part", F.ntile(4).over(__import__("pyspark").sql.Window.orderBy("ts")))
    rows = rows.withColumn("part", F.when(F.xxhash64("event_id") % 50 == 0, F.least(F.col("part") + 2, F.lit(4))).otherwise(F.col("part")))
    for p in range(1, 5):
        rows.filter(F.col("part") == p).drop("part").coalesce(1).write.mode("append").parquet(path)
    return path


def test_windows_equal_batch(spark, folder):
    got = online.drain(online.windowed_sums(online.event_stream(spark, folder)), "complete").agg(F.sum("n"), F.round(F.sum("value"), 2)).first()
    want = spark.read.parquet(folder).agg(F.count(F.lit(1)), F.round(F.sum("value"), 2)).first()
    assert tuple(got) == tuple(want)
    for kind in ("sliding", "session"):
        assert online.drain(online.windowed_sums(online.with_watermark(online.event_stream(spark, folder)), kind), "append" if kind == "session" else "complete").count() > 0


def test_late_rows_are_dropped_past_the_watermark(spark, folder):
    rows = online.windowed_sums(online.with_watermark(online.event_stream(spark, folder), "1 hour"), "tumbling", "1 hour")
    got = online.drain(rows, "append").agg(F.sum("n")).first()[0]
    assert 0 < got < spark.read.parquet(folder).count()


def test_online_steps_and_dedup(spark, folder):
    x = online.online_sgd(online.event_stream(spark, folder))
    assert x[0] > 0
    twice = online.dedup(online.with_watermark(online.event_stream(spark, folder), "60 days"))
    assert online.drain(twice, "append").count() == spark.read.parquet(folder).select("event_id").distinct().count()


def test_joins(spark, folder):
    users = spark.read.parquet(folder).select("user_id").distinct().withColumn("tier", F.col("user_id") % 3)
    assert online.drain(online.enrich(online.event_stream(spark, folder), users), "append").filter("tier is null").count() == 0
    e = lambda: online.with_watermark(online.event_stream(spark, folder, files=10), "1 day")
    got = online.drain(online.pair(e(), e()), "append").count()
    b = spark.read.parquet(folder)
    want = b.alias("a").join(b.alias("b"), F.expr("a.user_id = b.user_id AND a.event_id < b.event_id AND b.ts BETWEEN a.ts - INTERVAL 10 MINUTES AND a.ts + INTERVAL 10 MINUTES")).count()
    assert got == want


def test_stateful_feedback(spark, tmp_path):
    rows = spark.createDataFrame([(w, s, [float(s), -2.0 * w, 1.0]) for w in (0, 1) for s in (1, 2, 3)], "worker int, step long, vec array<double>")
    rows.write.parquet(str(tmp_path / "g"))
    stream = spark.readStream.schema(rows.schema).parquet(str(tmp_path / "g"))
    got = online.drain(online.error_feedback(stream, 1), "append").collect()
    assert len(got) == 6 and {r["worker"] for r in got} == {0, 1}


def test_appended_rows_are_not_held_by_the_driver(spark, folder):
    """Appended rows are files in the shared folder, states are kept on disk, and the session's own setting stays as it was."""
    got = online.drain(online.dedup(online.with_watermark(online.event_stream(spark, folder), "60 days")), "append")
    files = got.inputFiles()
    assert files and all(spark.sparkContext.getCheckpointDir().split(":")[-1] in f for f in files)
    with online.states_on_disk(spark):
        assert "RocksDB" in spark.conf.get(online.STORE)
    assert spark.conf.get(online.STORE, None) is None
    assert got.count() == spark.read.parquet(folder).select("event_id").distinct().count()


def test_stream_without_files(spark, tmp_path):
    assert online.drain(online.event_stream(spark, str(tmp_path)), "append").count() == 0
