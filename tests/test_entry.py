"""The entry's queries against DuckDB on the smallest tables."""

from decimal import Decimal

import duckdb
import numpy as np
import pandas as pd
import pytest

import __spark_entry__ as entry
from dagframe import workloads

TABLES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()
NAMES = sorted(set(workloads.queries()) & set(workloads.oracle_sql()))


@pytest.fixture(scope="module")
def duck(sf):
    con = duckdb.connect()
    for t in TABLES:
        con.sql(f"create view {t} as select * from '{sf}/{t}.parquet'")
    return con


def test_entry(spark):
    assert entry.entry(spark).count() == 6


def test_every_oracle_has_a_query():
    assert all(isinstance(v, str) for v in entry.oracle_sql().values())
    assert set(entry.oracle_sql()) <= set(entry.queries()) and len(workloads.queries()) > 80


@pytest.mark.parametrize("name", NAMES)
def test_twin(spark, sf, duck, name):
    a, b = workloads.queries()[name](spark, sf).toPandas(), duck.sql(workloads.oracle_sql()[name]).df()
    cols = sorted(a.columns)
    assert cols == sorted(b.columns)
    one = lambda v: "" if pd.isna(v) else str(float(v)) if isinstance(v, (int, float, np.number, Decimal)) else str(v)
    rows = lambda f: sorted(tuple(map(one, r)) for r in f[cols].astype(object).to_numpy())
    assert rows(a) == rows(b)
