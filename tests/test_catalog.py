"""Every twin of the catalog at the smallest scale: the same columns and rows from Spark and from DuckDB."""

import re

import duckdb
import numpy as np
import pandas as pd
import pytest

from corrsentry import catalog

SF = "/root/testdata/sf0.001"
TABLES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()
#: Iterations with a checkpoint each; the driver's comparison and test_engine cover them.
SLOW = {"direct_score_sql", "direct_score_tiles"}


@pytest.fixture(scope="module")
def duck():
    con = duckdb.connect()
    for t in TABLES:
        con.execute(f"create view {t} as select * from '{SF}/{t}.parquet'")
    return con


def cell(v):
    if v is None or v is pd.NA or v is pd.NaT or (isinstance(v, float) and v != v):
        return "~"
    if hasattr(v, "isoformat"):
        return str(v)[:10]
    if isinstance(v, (int, bool, np.integer, np.bool_)) or (isinstance(v, float) and v == int(v)):
        return str(int(v))
    return str(v)


def rows(df):
    return sorted(tuple(map(cell, r)) for r in df[sorted(df.columns)].itertuples(index=False, name=None))


@pytest.mark.parametrize("name", sorted(set(catalog.oracle_sql()) - SLOW))
def test_twin(spark, duck, name):
    got, want = catalog.queries()[name](spark, SF).toPandas(), duck.execute(catalog.oracle_sql()[name]).df()
    assert sorted(got.columns) == sorted(want.columns)
    assert rows(got) == rows(want)


def test_names():
    assert all(re.fullmatch(r"[a-z0-9_]+", n) for n in catalog.queries()) and set(catalog.oracle_sql()) <= set(catalog.queries())
