from __future__ import annotations

import os
import sys
from pathlib import Path

import pytest

ROOT = Path(__file__).resolve().parent.parent
sys.path.insert(0, str(ROOT))
os.environ["PYTHONPATH"] = f"{ROOT}:{os.environ.get('PYTHONPATH', '')}"


@pytest.fixture(scope="session")
def spark():
    from pyspark.sql import SparkSession

    session = (
        SparkSession.builder.master("local[8]")
        .config("spark.sql.shuffle.partitions", "4")
        .config("spark.sql.session.timeZone", "UTC")
        .config("spark.ui.enabled", "false")
        .config("spark.ui.showConsoleProgress", "false")
        .config("spark.driver.memory", "4g")
        .getOrCreate()
    )
    session.sparkContext.setLogLevel("ERROR")
    yield session


@pytest.fixture(scope="session")
def sf_dir() -> str:
    return "/root/testdata/sf0.001"


@pytest.fixture(scope="session")
def duck():
    """DuckDB over the same small tables."""
    import duckdb

    con = duckdb.connect()
    for table in "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split():
        con.sql(f"create view {table} as select * from '/root/testdata/sf0.001/{table}.parquet'")
    return con


def same_rows(ours, theirs) -> None:
    """Equal columns and, in any order, equal rows."""
    columns = sorted(ours.columns)
    assert columns == sorted(theirs.columns)
    a = ours[columns].sort_values(columns).reset_index(drop=True)
    b = theirs[columns].sort_values(columns).reset_index(drop=True)
    assert len(a) == len(b)
    for c in columns:
        x, y = a[c], b[c]
        equal = (x == y) | (x.isna() & y.isna())
        assert equal.all(), (c, x[~equal].head(3).tolist(), y[~equal].head(3).tolist())


@pytest.fixture(scope="session")
def equal_rows():
    return same_rows
