"""One local session for all tests, and a DuckDB connection over the smallest tables."""

import os
import sys

import pytest

sys.path.insert(0, os.path.dirname(os.path.dirname(os.path.abspath(__file__))))
SF = os.environ.get("TEST_SF_DIR", "/root/testdata/sf0.001")


@pytest.fixture(scope="session")
def spark():
    from pyspark.sql import SparkSession

    session = (
        SparkSession.builder.master("local[4]")
        .config("spark.sql.shuffle.partitions", "4")
        .config("spark.driver.memory", "4g")
        .config("spark.ui.enabled", "false")
        .config("spark.ui.showConsoleProgress", "false")
        .config("spark.sql.session.timeZone", "UTC")
        .getOrCreate()
    )
    session.sparkContext.setLogLevel("ERROR")
    yield session
    session.stop()


@pytest.fixture(scope="session")
def duck():
    import duckdb

    con = duckdb.connect()
    for name in "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split():
        con.sql(f"create view {name} as select * from '{SF}/{name}.parquet'")
    return con


@pytest.fixture(scope="session")
def same(spark, duck):
    """Compare a query with its SQL as bags of rows, columns by name."""
    from collections import Counter

    def check(query, sql):
        df = query(spark, SF)
        cols = sorted(df.columns)
        found = duck.sql(sql)
        assert sorted(found.columns) == cols
        at = [found.columns.index(c) for c in cols]
        ours = Counter(tuple(str(r[c]) if isinstance(r[c], list) else r[c] for c in cols) for r in df.collect())
        theirs = Counter(tuple(str(r[i]) if isinstance(r[i], list) else r[i] for i in at) for r in found.fetchall())
        assert ours == theirs

    return check
