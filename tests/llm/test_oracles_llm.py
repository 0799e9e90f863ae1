import glob
import os

import duckdb
import pytest

from hamcover.llm import registry
from tests.llm.tests_helpers import compare


@pytest.mark.parametrize("name", sorted(registry.oracle_sql()))
def test_query_equals_sql(spark, sf, name):
    con = duckdb.connect()
    for p in glob.glob(f"{sf}/*.parquet"):
        g = f"{p}/*.parquet" if os.path.isdir(p) else p
        con.execute(f"create view {os.path.basename(p)[:-8]} as select * from '{g}'")
    compare(registry.queries()[name](spark, sf), con.sql(registry.oracle_sql()[name]))


def test_every_operator_has_one_query():
    names = sorted(int(n[2:].split("_")[0]) for n in registry.queries())
    assert names == list(range(1, 11))
