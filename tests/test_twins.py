"""Queries against their SQL twins on the smallest tables."""

import duckdb
import pandas as pd
import pytest

import __spark_entry__ as entry
from headcount.plans import catalogue

TABLES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()
NAMES = sorted(catalogue.oracle_sql())


@pytest.fixture(scope="module")
def con(tiny):
    c = duckdb.connect()
    for t in TABLES:
        c.execute(f"CREATE VIEW {t} AS SELECT * FROM '{tiny}/{t}.parquet'")
    return c


def rows(df):
    cols = sorted(df.columns)
    clean = lambda v: "null" if pd.isna(v) else (str(v)[:-2] if str(v).endswith(".0") else str(v))
    return sorted(tuple(clean(v) for v in r) for r in df[cols].astype(object).values.tolist())


@pytest.mark.parametrize("name", NAMES)
def test_twin(spark, tiny, con, name):
    a = catalogue.queries()[name](spark, tiny).toPandas()
    b = con.execute(catalogue.oracle_sql()[name]).df()
    assert sorted(a.columns) == sorted(b.columns)
    assert rows(a) == rows(b)


def test_every_twin_has_a_query():
    assert set(entry.oracle_sql()) <= set(entry.queries())


def test_entry(spark):
    assert entry.entry(spark).count() == 1
