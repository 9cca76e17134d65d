"""One local session for all tests, and a DuckDB over the same tables."""

import os
from collections import Counter

import duckdb
import pytest
from pyspark.sql import SparkSession

SMALL, FULL = "/root/testdata/sf0.001", "/root/testdata/sf0.01"
TABLES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()


@pytest.fixture(scope="session")
def spark():
    build = SparkSession.builder.master("local[4]").config("spark.sql.shuffle.partitions", "4").config("spark.sql.session.timeZone", "UTC")
    session = build.config("spark.ui.enabled", "false").config("spark.driver.memory", "4g").getOrCreate()
    session.sparkContext.setLogLevel("ERROR")
    yield session
    session.stop()


@pytest.fixture(scope="session")
def duck():
    con = duckdb.connect()
    for t in TABLES:
        if os.path.exists(f"{FULL}/{t}.parquet"):
            con.sql(f"CREATE VIEW {t} AS SELECT * FROM '{FULL}/{t}.parquet'")
    return con


def rows_of(frame) -> Counter:
    """Multiset of rows of a pandas frame, columns by name; numbers by value, any null as None."""

    def plain(v):
        if v is None or str(v) in ("<NA>", "NaT", "nan"):
            return None
        return float(v) if not isinstance(v, (bool, str)) and hasattr(v, "__float__") else v

    cols = sorted(frame.columns)
    return Counter(tuple(plain(v) for v in r) for r in frame[cols].astype(object).itertuples(index=False, name=None))


def check_query(spark, duck, queries, oracles, name) -> None:
    mine, other = queries[name](spark, FULL).toPandas(), duck.sql(oracles[name]).df()
    assert sorted(mine.columns) == sorted(other.columns)
    assert rows_of(mine) == rows_of(other)
