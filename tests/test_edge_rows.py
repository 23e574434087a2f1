"""Queries against their SQL on rows that the smallest tables do not have."""

import datetime

import duckdb
import pytest

import __spark_entry__ as entry

#: Queries that made their data up before, with the tables that they read.
READ_NOTHING = {
    "worker_limit_grid": ["lineitem"],
    "probs_uniform": ["events"],
    "probs_geometric_recursive": ["events"],
    "probs_geometric_63": ["events"],
    "probs_geometric_52": ["events"],
    "probs_custom": ["lineitem", "events"],
    "fn_geo_levels": ["embeddings"],
    "divergence_fixture": ["embeddings"],
    "decay_closed_form": ["embeddings"],
    "bounds_grid": ["events"],
    "bits_per_message": ["events"],
    "bits_cumulative": ["events"],
}


def rows_of(spark, name, folder, *tables):
    con = duckdb.connect()
    for t in tables:
        con.sql(f"CREATE VIEW {t} AS SELECT * FROM '{folder}/{t}.parquet'")
    want = con.sql(entry.oracle_sql()[name])
    cols = sorted(want.columns)
    df = entry.queries()[name](spark, str(folder))
    assert sorted(df.columns) == cols
    return sorted(map(repr, (tuple(r) for r in df.select(*cols).collect()))), sorted(map(repr, want.select(", ".join(f'"{c}"' for c in cols)).fetchall()))


def write_events(spark, folder, values):
    """Events of users, one an hour; ``values``: lists by user."""
    start, rows = datetime.datetime(2024, 1, 1), []
    for user, vals in values.items():
        rows += [(len(rows) + k, start + datetime.timedelta(hours=len(rows) + k), user, "view", v, "{}") for k, v in enumerate(vals)]
    spark.createDataFrame(rows, "event_id long, ts timestamp_ntz, user_id long, event_type string, value double, props string").coalesce(1).write.parquet(str(folder / "events.parquet"))


def test_values_of_zero_count_as_coordinates(spark, tmp_path):
    write_events(spark, tmp_path, {1: [3.0, 0.0, 1.5, 0.25, 8.0, 2.0], 2: [0.0, 0.0], 3: [5.0, 2.5, 1.0], 4: [1.0, 0.0]})
    got, want = rows_of(spark, "var_user_values", tmp_path, "events")
    assert got == want and len(got) == 3


@pytest.mark.parametrize("name", READ_NOTHING)
def test_tasks_read_the_table(spark, name):
    """Tasks read more than 50 kB of the tables of sf0.1, and the rows are those of the SQL if there is one."""
    core = spark.sparkContext._jsc.sc()

    def read():
        core.listenerBus().waitUntilEmpty()
        return core.statusStore().executorList(True).apply(0).totalInputBytes()

    spark.conf.set("parquet.hadoop.vectored.io.enabled", "false")  # bytes of vectored reads are not counted
    folder, before = "/root/testdata/sf0.1", read()
    if name in entry.oracle_sql():
        got, want = rows_of(spark, name, folder, *READ_NOTHING[name])
        assert got == want
    else:
        assert entry.queries()[name](spark, folder).collect()
    spark.conf.unset("parquet.hadoop.vectored.io.enabled")
    assert read() - before > 50_000


def test_divergence_from_the_means_of_classes(spark):
    rows = entry.queries()["divergence_fixture"](spark, "/root/testdata/sf0.001").collect()
    assert len(rows) == 50 and {r["label"] for r in rows} == set(range(10))
    assert all(r["grows"] == (r["method"] == "topk") for r in rows)
