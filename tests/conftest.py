import os
import sys

import pytest

sys.path.insert(0, os.path.dirname(os.path.dirname(os.path.abspath(__file__))))
DATA = "/root/testdata"


@pytest.fixture(scope="session")
def spark():
    from pyspark.sql import SparkSession

    s = SparkSession.builder.master("local[8]").config("spark.sql.shuffle.partitions", "8").config("spark.ui.enabled", "false").config("spark.sql.session.timeZone", "UTC").config("spark.driver.memory", "8g").getOrCreate()
    s.sparkContext.setLogLevel("ERROR")
    return s


@pytest.fixture(scope="session")
def duck():
    """Rows of a query on the tables of a scale, as (columns, rows)."""
    import duckdb

    def run(sql, sf="sf0.001"):
        con = duckdb.connect()
        for name in os.listdir(f"{DATA}/{sf}"):
            con.sql(f"CREATE VIEW {name.removesuffix('.parquet')} AS SELECT * FROM read_parquet('{DATA}/{sf}/{name}')")
        r = con.sql(sql)
        return r.columns, r.fetchall()

    return run


@pytest.fixture(scope="session")
def same(duck):
    """Assert that a DataFrame has the rows of a query."""

    def check(df, sql, sf="sf0.001"):
        cols, rows = duck(sql, sf)
        names = sorted(df.columns)
        assert names == sorted(cols)
        key = lambda v: f"{v:.9g}" if isinstance(v, float) else repr(v)
        at = [cols.index(c) for c in names]
        assert sorted(tuple(key(r[c]) for c in names) for r in df.collect()) == sorted(tuple(key(r[i]) for i in at) for r in rows)

    return check
