"""One Spark session for all tests, and the comparison of a query with its SQL twin."""

from __future__ import annotations

import os
import sys
from pathlib import Path

import duckdb
import pandas as pd
import pytest

sys.path.insert(0, str(Path(__file__).resolve().parents[1]))

DATA = os.environ.get("TEST_SF_DIR", "/root/testdata/sf0.001")
TABLES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()


@pytest.fixture(scope="session")
def spark():
    from fedlake.session import local_session

    session = local_session(4, "6g", "tests")
    session.conf.set("spark.sql.streaming.stateStore.providerClass", "org.apache.spark.sql.execution.streaming.state.RocksDBStateStoreProvider")
    yield session
    session.stop()


@pytest.fixture(scope="session")
def folder():
    return DATA


@pytest.fixture(scope="session")
def duck():
    c = duckdb.connect()
    for t in TABLES:
        c.execute(f"CREATE VIEW {t} AS SELECT * FROM '{DATA}/{t}.parquet'")
    return c


def same_rows(a: pd.DataFrame, b: pd.DataFrame) -> None:
    """Equal column names and, in any order, equal rows."""
    assert sorted(a.columns) == sorted(b.columns)
    assert len(a) == len(b)
    names = sorted(a.columns)
    a, b = (x[names].sort_values(names).reset_index(drop=True) for x in (a, b))
    for c in names:
        equal = (a[c] == b[c]) | (a[c].isna() & b[c].isna())
        assert equal.all(), f"{c}: {a[c][~equal].head(3).tolist()} is not {b[c][~equal].head(3).tolist()}"


@pytest.fixture(scope="session")
def compare():
    return same_rows
