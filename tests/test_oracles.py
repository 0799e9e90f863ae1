"""Every query that has SQL, against DuckDB on the smallest tables; and the driver's contract."""

import decimal
import glob
import os
import subprocess
import sys

import duckdb
import pytest

from hamcover import registry

ROOT = os.path.dirname(os.path.dirname(os.path.abspath(__file__)))
NAMES = sorted(registry.oracle_sql())


@pytest.fixture(scope="module")
def con(sf):
    c = duckdb.connect()
    for p in glob.glob(f"{sf}/*.parquet"):
        g = f"{p}/*.parquet" if os.path.isdir(p) else p
        c.execute(f"create view {os.path.basename(p)[:-8]} as select * from '{g}'")
    return c


def plain(v):
    if isinstance(v, (float, decimal.Decimal)):
        return f"{float(v):.9g}"
    if isinstance(v, (list, tuple)):
        return tuple(map(plain, v))
    return str(v)


def compare(df, rel):
    columns = sorted(df.columns)
    assert sorted(rel.columns) == columns
    at = [rel.columns.index(c) for c in columns]
    got = sorted(tuple(map(plain, r)) for r in df.select(*columns).collect())
    assert got == sorted(tuple(plain(r[i]) for i in at) for r in rel.fetchall())


@pytest.mark.parametrize("name", NAMES)
def test_query_equals_sql(spark, sf, con, name):
    compare(registry.queries()[name](spark, sf), con.sql(registry.oracle_sql()[name]))


def test_queries_without_the_llm_folders(tmp_path):
    code = f"""
import sys
class Missing:
    def find_spec(self, name, path=None, target=None):
        if name.startswith("hamcover.llm") or name == "corpus_pipeline":
            raise ModuleNotFoundError(name)
sys.meta_path.insert(0, Missing())
sys.path.insert(0, {ROOT!r})
import __spark_entry__ as e
assert len(e.queries()) > 100 and not any(n.startswith("op1_") for n in e.queries())
assert set(e.oracle_sql()) <= set(e.queries())
"""
    subprocess.run([sys.executable, "-c", code], check=True, cwd=tmp_path, timeout=120)


def test_entry(spark):
    sys.path.insert(0, ROOT)
    import __spark_entry__

    assert __spark_entry__.entry(spark).count() > 0


def test_late_rows_are_left_out(spark, sf):
    found = {r.event_type: r.n for r in registry.queries()["st_late_rows"](spark, sf).collect()}
    every = {r.event_type: r.n for r in registry.queries()["st_totals_complete"](spark, sf).collect()}
    assert all(found[k] < every[k] for k in found)
