import os
import sys

import pytest

sys.path.insert(0, os.path.dirname(os.path.dirname(os.path.abspath(__file__))))

SMALL = "/root/testdata/sf0.001"
TABLES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()


@pytest.fixture(scope="session")
def spark():
    from pyspark.sql import SparkSession

    session = (
        SparkSession.builder.master("local[4]").config("spark.sql.shuffle.partitions", "4").config("spark.ui.enabled", "false").config("spark.ui.showConsoleProgress", "false").config("spark.driver.memory", "4g").getOrCreate()
    )
    session.sparkContext.setLogLevel("OFF")
    yield session
    from phrasework.shared import remove_all

    remove_all()
    session.stop()


@pytest.fixture(scope="session")
def small():
    return SMALL


@pytest.fixture(scope="session")
def duck():
    import duckdb

    con = duckdb.connect()
    for t in TABLES:
        path = f"{SMALL}/{t}.parquet"
        con.execute(f"CREATE VIEW {t} AS FROM '{path}/*.parquet'" if os.path.isdir(path) else f"CREATE VIEW {t} AS FROM '{path}'")
    return con


def rows_of(frame, columns):
    """Rows as comparable text, nulls alike for both engines, in no order."""
    plain = frame[columns].astype(object)
    return sorted(map(repr, plain.where(plain.notna(), None).itertuples(index=False, name=None)))


@pytest.fixture(scope="session")
def same(spark, small, duck):
    """Compare a query with its SQL on the small tables."""

    def check(query, sql):
        got, want = query(spark, small).toPandas(), duck.sql(sql).df()
        columns = sorted(got.columns)
        assert columns == sorted(want.columns)
        assert rows_of(got, columns) == rows_of(want, columns)

    return check
