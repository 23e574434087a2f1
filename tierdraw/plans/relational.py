"""Relational operators around the methods, each a small query on the given tables with its SQL."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..functions.draws import hash_uniform
from ..operators.vectors import to_coords
from ..sources.catalog import load


def model_asof(events: DataFrame, models: DataFrame) -> DataFrame:
    """Each event with the latest model step at or before its time: both sides in one sorted stream per user, the last step carried forward."""
    both = events.select("user_id", "ts", "event_id", F.lit(None).cast("long").alias("step")).unionByName(models.select("user_id", "ts", F.lit(None).cast("long").alias("event_id"), "step"))
    w = Window.partitionBy("user_id").orderBy("ts", F.col("step").asc_nulls_last()).rowsBetween(Window.unboundedPreceding, Window.currentRow)
    return both.withColumn("last", F.last("step", ignorenulls=True).over(w)).filter("event_id is not null").select("event_id", F.col("last").alias("step"))


def rel_asof(spark: SparkSession, sf: str) -> DataFrame:
    events = load(spark, sf, "events", "event_id", "user_id", "ts")
    return model_asof(events.filter("event_id % 10 <> 0"), events.filter("event_id % 10 = 0").select("user_id", "ts", F.col("event_id").alias("step")))


def rel_range_draw(spark: SparkSession, sf: str) -> DataFrame:
    """Theta join of hashed uniforms with the bounds of a fixed table of levels."""
    levels = spark.range(1, 9).select(F.col("id").cast("int").alias("level"), ((F.col("id") - 1) / 8).alias("lo"), (F.col("id") / 8).alias("hi"))
    rows = load(spark, sf, "embeddings", "vec_id").withColumn("u", hash_uniform(11, F.col("vec_id")))
    return rows.join(F.broadcast(levels), (F.col("lo") <= F.col("u")) & (F.col("u") < F.col("hi"))).select("vec_id", "level")  # eight rows


def rel_semi_batch(spark: SparkSession, sf: str) -> DataFrame:
    """Coordinates of the rows of a batch."""
    rows = load(spark, sf, "embeddings", "vec_id", "embedding")
    batch = rows.select("vec_id").filter(hash_uniform(3, "batch", F.col("vec_id")) < 0.1)
    return to_coords(rows.join(batch, "vec_id", "left_semi"), ["vec_id"], "embedding").select("vec_id", "pos", F.round("val", 6).alias("val"))


def rel_anti_unlabelled(spark: SparkSession, sf: str) -> DataFrame:
    return load(spark, sf, "documents", "doc_id", "lang").join(load(spark, sf, "labels", "doc_id"), "doc_id", "left_anti").groupBy("lang").agg(F.count(F.lit(1)).alias("n"))


def rel_cube(spark: SparkSession, sf: str) -> DataFrame:
    return load(spark, sf, "lineitem", "l_returnflag", "l_linestatus", "l_quantity").cube("l_returnflag", "l_linestatus").agg(F.count(F.lit(1)).alias("n"), F.round(F.sum("l_quantity"), 2).alias("qty"))


def rel_rollup_pivot(spark: SparkSession, sf: str) -> DataFrame:
    rows = load(spark, sf, "lineitem", "l_returnflag", "l_linestatus")
    return rows.groupBy("l_returnflag").pivot("l_linestatus", ["F", "O"]).agg(F.count(F.lit(1))).select("l_returnflag", F.coalesce("F", F.lit(0)).alias("f"), F.coalesce("O", F.lit(0)).alias("o"))


def rel_sessions(spark: SparkSession, sf: str) -> DataFrame:
    """Sessions of a user: events less than six hours apart."""
    rows = load(spark, sf, "events", "user_id", "ts", "value")
    w = Window.partitionBy("user_id").orderBy("ts")
    far = F.coalesce((F.unix_micros(F.col("ts").cast("timestamp")) - F.unix_micros(F.lag("ts").over(w).cast("timestamp")) > 6 * 3_600_000_000).cast("int"), F.lit(1))
    marked = rows.withColumn("far", far).withColumn("session", F.sum("far").over(w.rowsBetween(Window.unboundedPreceding, Window.currentRow)))
    return marked.groupBy("user_id", "session").agg(F.count(F.lit(1)).alias("n"), F.round(F.sum("value"), 4).alias("value"))


def rel_json(spark: SparkSession, sf: str) -> DataFrame:
    rows = load(spark, sf, "events", "event_type", "props")
    return rows.withColumn("k", F.from_json("props", "k int")["k"]).groupBy("event_type").agg(F.sum("k").alias("k"), F.count("k").alias("n"))


def rel_interval(spark: SparkSession, sf: str) -> DataFrame:
    """Pairs of a user's events of different types within ten minutes."""
    e = load(spark, sf, "events", "event_id", "user_id", "event_type", "ts")
    a, b = e.alias("a"), e.alias("b")
    near = (F.col("a.user_id") == F.col("b.user_id")) & (F.col("a.event_type") < F.col("b.event_type")) & F.col("b.ts").between(F.col("a.ts") - F.expr("INTERVAL 10 MINUTES"), F.col("a.ts") + F.expr("INTERVAL 10 MINUTES"))
    return a.join(b, near).groupBy(F.col("a.event_type").alias("ta"), F.col("b.event_type").alias("tb")).agg(F.count(F.lit(1)).alias("n"))


def _support(spark: SparkSession, sf: str, sign: int) -> DataFrame:
    rows = to_coords(load(spark, sf, "embeddings", "vec_id", "embedding"), ["vec_id"], "embedding")
    return rows.filter(F.col("val") * sign > 0.25).select("pos")


def rel_set_overlap(spark: SparkSession, sf: str) -> DataFrame:
    """Positions with large positive and with large negative values: sizes of union, intersection and differences."""
    a, b = _support(spark, sf, 1), _support(spark, sf, -1)
    size = lambda df, name: df.agg(F.count(F.lit(1)).alias("n")).select(F.lit(name).alias("part"), "n")
    return size(a.union(b).distinct(), "union").union(size(a.intersect(b), "both")).union(size(a.exceptAll(b), "except_all")).union(size(a.intersectAll(b), "intersect_all"))


def rel_windows(spark: SparkSession, sf: str) -> DataFrame:
    """Ranking, offset and moving frames over the daily sums of event types."""
    day = load(spark, sf, "events", "ts", "event_type", "value").groupBy("event_type", F.date_trunc("day", "ts").cast("date").alias("day")).agg(F.round(F.sum("value"), 2).alias("v"))
    w = Window.partitionBy("event_type").orderBy("day")
    r = Window.partitionBy("event_type").orderBy(F.col("v").desc(), "day")
    return day.select("event_type", "day", "v", F.rank().over(r).alias("rk"), F.ntile(4).over(r).alias("quarter"), F.round(F.avg("v").over(w.rowsBetween(-2, 0)), 4).alias("smooth"), F.coalesce(F.lag("v").over(w), F.lit(0.0)).alias("before"))


def rel_lateral_levels(spark: SparkSession, sf: str) -> DataFrame:
    """Geometric levels up to each label's own depth, by a lateral join."""
    load(spark, sf, "embeddings", "label").groupBy("label").agg(F.count(F.lit(1)).alias("n")).createOrReplaceTempView("tierdraw_depths")
    return spark.sql("SELECT label, level, round(power(2, -level), 9) AS q FROM tierdraw_depths, LATERAL (SELECT explode(sequence(1, label + 1)) AS level)")


QUERIES = {f.__name__: f for f in (rel_asof, rel_range_draw, rel_semi_batch, rel_anti_unlabelled, rel_cube, rel_rollup_pivot, rel_sessions, rel_json, rel_interval, rel_set_overlap, rel_windows, rel_lateral_levels)}

_U = "(('0x' || substr(md5('{0}' || vec_id), 1, 13))::BIGINT / 4503599627370496.0)"
_BIG = "SELECT unnest(range(len(embedding))) AS pos, unnest(embedding)::DOUBLE AS val FROM embeddings"
ORACLES = {
    "rel_asof": "SELECT e.event_id, m.event_id AS step FROM (SELECT * FROM events WHERE event_id % 10 <> 0) e LEFT JOIN LATERAL (SELECT event_id FROM events x WHERE x.event_id % 10 = 0 AND x.user_id = e.user_id AND x.ts <= e.ts ORDER BY x.ts DESC, x.event_id DESC LIMIT 1) m ON true",
    "rel_range_draw": f"SELECT vec_id, floor({_U.format('11|')} * 8)::INT + 1 AS level FROM embeddings",
    "rel_semi_batch": f"SELECT vec_id, unnest(range(len(embedding))) AS pos, round(unnest(embedding)::DOUBLE, 6) AS val FROM embeddings WHERE {_U.format('3|batch|')} < 0.1",
    "rel_anti_unlabelled": "SELECT lang, count(*) AS n FROM documents WHERE doc_id NOT IN (SELECT doc_id FROM labels WHERE doc_id IS NOT NULL) GROUP BY lang",
    "rel_cube": "SELECT l_returnflag, l_linestatus, count(*) AS n, round(sum(l_quantity), 2) AS qty FROM lineitem GROUP BY CUBE (l_returnflag, l_linestatus)",
    "rel_rollup_pivot": "SELECT l_returnflag, count(*) FILTER (l_linestatus = 'F') AS f, count(*) FILTER (l_linestatus = 'O') AS o FROM lineitem GROUP BY l_returnflag",
    "rel_sessions": "WITH a AS (SELECT *, CASE WHEN epoch_us(ts) - epoch_us(lag(ts) OVER w) <= 21600000000 THEN 0 ELSE 1 END AS far FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts)), b AS (SELECT *, sum(far) OVER (PARTITION BY user_id ORDER BY ts ROWS UNBOUNDED PRECEDING)::BIGINT AS session FROM a) SELECT user_id, session, count(*) AS n, round(sum(value), 4) AS value FROM b GROUP BY user_id, session",
    "rel_json": "SELECT event_type, sum((props->>'k')::INT)::BIGINT AS k, count(props->>'k') AS n FROM events GROUP BY event_type",
    "rel_interval": "SELECT a.event_type AS ta, b.event_type AS tb, count(*) AS n FROM events a JOIN events b ON a.user_id = b.user_id AND a.event_type < b.event_type AND b.ts BETWEEN a.ts - INTERVAL 10 MINUTE AND a.ts + INTERVAL 10 MINUTE GROUP BY 1, 2",
    "rel_set_overlap": f"WITH a AS (SELECT pos FROM ({_BIG}) WHERE val > 0.25), b AS (SELECT pos FROM ({_BIG}) WHERE -val > 0.25) SELECT 'union' AS part, count(*) AS n FROM (SELECT * FROM a UNION SELECT * FROM b) UNION ALL SELECT 'both', count(*) FROM (SELECT * FROM a INTERSECT SELECT * FROM b) UNION ALL SELECT 'except_all', count(*) FROM (SELECT * FROM a EXCEPT ALL SELECT * FROM b) UNION ALL SELECT 'intersect_all', count(*) FROM (SELECT * FROM a INTERSECT ALL SELECT * FROM b)",
    "rel_windows": "WITH d AS (SELECT event_type, ts::DATE AS day, round(sum(value), 2) AS v FROM events GROUP BY 1, 2) SELECT event_type, day, v, rank() OVER r AS rk, ntile(4) OVER r AS quarter, round(avg(v) OVER (PARTITION BY event_type ORDER BY day ROWS BETWEEN 2 PRECEDING AND CURRENT ROW), 4) AS smooth, coalesce(lag(v) OVER (PARTITION BY event_type ORDER BY day), 0) AS before FROM d WINDOW r AS (PARTITION BY event_type ORDER BY v DESC, day)",
    "rel_lateral_levels": "SELECT label, level, round(pow(2, -level), 9) AS q FROM (SELECT DISTINCT label FROM embeddings), LATERAL (SELECT unnest(range(1, label + 2))::INT AS level)",
}
