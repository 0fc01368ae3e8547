"""The registry and a few queries against their SQL at the smallest scale."""

import math
import numbers

import duckdb
import numpy as np
import pandas as pd
import pytest

import __spark_entry__ as entry
from rippletide import workloads
from rippletide.sources.tables import TABLES

SF = "/root/testdata/sf0.001"
# Simulations take many jobs each; these two stand for them here, and the rest have tests of their own.
SIMULATED = ("cascade_", "effective_", "expected_spread", "activation_", "opinion_spread", "spread_stderr", "marginal_", "set_decomposition", "lt_equals", "reach_bits", "brute_force", "rr_", "stream_", "score_greedy_k3_majority", "submodularity", "set_cover")
NAMES = sorted(n for n in workloads.oracles() if "mc_greedy" not in n and n not in ("lazy_greedy_k2", "oc_greedy_k2") and not n.startswith(SIMULATED) or n in ("cascade_oi_ic", "cascade_oi_lt", "stream_topic_state", "stream_sessions"))


def test_every_oracle_has_a_query():
    assert set(entry.oracle_sql()) <= set(entry.queries())


def clean(x):
    """Numbers by value whatever their type, nulls as None."""
    if x is None or x is pd.NaT or (isinstance(x, numbers.Number) and math.isnan(x)):
        return None
    return round(float(x), 5) if isinstance(x, numbers.Number) and not isinstance(x, bool) else str(x)


def rows(df):
    df = df[sorted(df.columns)]
    return sorted((tuple(clean(x) for x in r) for r in df.itertuples(index=False)), key=str)


def test_clean_takes_numbers_of_any_kind_and_keeps_nulls():
    assert clean(np.int64(3)) == clean(3) == clean(3.0) == clean(np.float32(3)) == 3.0
    assert clean(None) is clean(float("nan")) is clean(np.float64("nan")) is None
    assert clean("3") == "3" and clean(np.int64(0)) is not None


@pytest.mark.parametrize("name", NAMES)
def test_query_equals_sql(spark, name):
    con = duckdb.connect()
    for t in TABLES:
        con.execute(f"CREATE VIEW {t} AS SELECT * FROM '{SF}/{t}.parquet'")
    assert rows(entry.queries()[name](spark, SF).toPandas()) == rows(con.execute(entry.oracle_sql()[name]).df())


def test_entry(spark):
    assert entry.entry(spark).count() == 10
