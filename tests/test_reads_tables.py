"""Queries that once made their data up: they read the given tables and equal their SQL."""

import duckdb
import pytest
from pyspark.errors import AnalysisException

import __spark_entry__ as entry
from rippletide.sources.tables import TABLES

SF = "/root/testdata/sf0.001"
NAMES = [
    "violation_window",
    "submodularity_two_layer",
    "repeated_paths",
    "op_udtf",
    "op_recursive",
    "expected_path_mass",
]


@pytest.mark.parametrize("name", NAMES)
def test_query_reads_its_table(spark, name):
    con = duckdb.connect()
    for t in TABLES:
        con.execute(f"CREATE VIEW {t} AS SELECT * FROM '{SF}/{t}.parquet'")
    want = con.execute(entry.oracle_sql()[name])
    columns = [c[0] for c in want.description]
    got = sorted(tuple(r) for r in entry.queries()[name](spark, SF).select(*columns).collect())
    assert got and got == sorted(want.fetchall())
    with pytest.raises(AnalysisException):
        entry.queries()[name](spark, "/no/such/folder").collect()
