"""Queries against their SQL on the smallest tables, and the entry module without the training-data operators."""

import subprocess
import sys

import duckdb
import pytest

import __spark_entry__ as entry

SF = "/root/testdata/sf0.001"
TABLES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()
SLOW = ("expect_", "var_", "tier_f", "fixed_deltas", "float_deltas", "probs_adaptive", "omega")
NAMES = [k for k in entry.registry.oracle_sql() if not k.startswith(SLOW)]


def canonical(rows):
    return sorted(repr(tuple(x + 0.0 if isinstance(x, float) else x for x in r)) for r in rows)


@pytest.mark.parametrize("name", NAMES)
def test_query_equals_sql(spark, name):
    con = duckdb.connect()
    for t in TABLES:
        con.sql(f"CREATE VIEW {t} AS SELECT * FROM '{SF}/{t}.parquet'")
    df = entry.registry.queries()[name](spark, SF)
    want = con.sql(entry.registry.oracle_sql()[name])
    cols = sorted(want.columns)
    assert sorted(df.columns) == cols
    got = [tuple(r) for r in df.select(*cols).collect()]
    assert canonical(got) == canonical(want.select(", ".join(f'"{c}"' for c in cols)).fetchall())


def test_entry(spark):
    assert entry.entry(spark).count() > 0


def test_rest_imports_nothing_of_llm():
    code = "import sys; sys.modules['tierdraw.llm'] = None; sys.modules['corpus_pipeline'] = None; import __spark_entry__ as e; assert 'pipeline' not in e.queries() and e.queries() and not [k for k in e.queries() if k.startswith('op')]; print(len(e.oracle_sql()))"
    done = subprocess.run([sys.executable, "-c", code], capture_output=True, text=True, cwd=sys.path[0] if False else __import__("os").path.dirname(entry.__file__))
    assert done.returncode == 0, done.stderr
