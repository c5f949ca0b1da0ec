"""Registered queries against their SQL on the same tables."""

import os

import duckdb
import pytest

import __spark_entry__ as entry
from manifold_dp import streaming
from manifold_dp.plans import methods, relational

TABLES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()
SMALL = "/root/testdata/sf0.001"
#: Run over the small tables to keep the suite short; the driver compares all on larger ones.
CORE = {**methods.ORACLES, **relational.ORACLES, **streaming.ORACLES}


@pytest.fixture(scope="session")
def duck():
    c = duckdb.connect()
    for t in TABLES:
        c.execute(f"CREATE VIEW {t} AS SELECT * FROM '{SMALL}/{t}.parquet'")
    return c


def rows(df):
    df = df[sorted(df.columns)].astype(object)
    return list(df.columns), sorted(map(repr, (tuple(x) for x in df.where(df.notna(), None).itertuples(index=False))))


@pytest.mark.parametrize("name", sorted(CORE))
def test_query_equals_sql(spark, duck, name):
    got, want = entry.queries()[name](spark, SMALL).toPandas(), duck.execute(entry.oracle_sql()[name]).df()
    (gc, gr), (wc, wr) = rows(got), rows(want)
    assert gc == wc
    assert gr == wr


def test_entry_runs(spark):
    assert entry.entry(spark).count() > 0


def test_registry_names_match():
    assert set(entry.oracle_sql()) <= set(entry.queries())
    assert os.path.exists(SMALL)
