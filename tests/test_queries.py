"""Every query with SQL against DuckDB on the raw rows of the smallest tables."""

import os

import duckdb
import pytest

import __spark_entry__ as entry

SF = "/root/testdata/sf0.001"
#: The labels of sf0.001 are too few, and separated.
LARGER = dict.fromkeys(("logistic_quality",), "/root/testdata/sf0.01")
TABLES = [f[:-8] for f in sorted(os.listdir(SF)) if f.endswith(".parquet")]


def _methods():
    from lincompress import relops, studies, workloads

    return workloads.QUERIES | studies.QUERIES | relops.QUERIES, workloads.SQL | studies.SQL | relops.SQL


def normal(rows):
    cell = lambda v: None if v is None or v != v else f"{v:.7g}" if isinstance(v, float) else str(v)
    return sorted((tuple(map(cell, r)) for r in rows), key=str)


@pytest.mark.parametrize("name", sorted(_methods()[1]))
def test_equals_sql(spark, name):
    queries, sql = _methods()
    folder = LARGER.get(name, SF)
    con = duckdb.connect()
    for t in TABLES:
        con.sql(f"CREATE VIEW {t} AS SELECT * FROM read_parquet('{folder}/{t}.parquet')")
    df = queries[name](spark, folder)
    got, want = df.toPandas(), con.sql(sql[name]).df()
    columns = sorted(got.columns)
    assert columns == sorted(want.columns)
    assert normal(got[columns].itertuples(index=False)) == normal(want[columns].itertuples(index=False))


@pytest.mark.parametrize("name", sorted(set(_methods()[0]) - set(_methods()[1])))
def test_runs(spark, name):
    assert _methods()[0][name](spark, LARGER.get(name, SF)).count() > 0


def test_contract():
    queries, sql = entry.queries(), entry.oracle_sql()
    assert set(sql) <= set(queries) and "flagship" in queries


def test_entry(spark):
    assert entry.entry(spark).count() > 0


def test_names_need_no_session():
    import subprocess
    import sys

    code = "import __spark_entry__ as e; print(len(e.queries()), len(e.oracle_sql()))"
    done = subprocess.run([sys.executable, "-B", "-c", code], cwd=os.path.dirname(os.path.abspath(entry.__file__)), capture_output=True, text=True, timeout=120)
    assert done.returncode == 0 and int(done.stdout.split()[0]) > 150
