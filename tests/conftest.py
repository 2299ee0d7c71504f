import os
import sys

import pytest

sys.path.insert(0, os.path.dirname(os.path.dirname(os.path.abspath(__file__))))
SMALL, MIDDLE = "/root/testdata/sf0.001", "/root/testdata/sf0.01"


@pytest.fixture(scope="session")
def spark():
    from pyspark.sql import SparkSession

    session = (
        SparkSession.builder.master("local[8]").appName("tests")
        .config("spark.sql.shuffle.partitions", "8").config("spark.ui.enabled", "false").config("spark.driver.host", "127.0.0.1")
        .config("spark.driver.memory", "6g").config("spark.sql.session.timeZone", "UTC")
        .getOrCreate()
    )
    session.sparkContext.setLogLevel("ERROR")
    yield session
    session.stop()


@pytest.fixture(scope="session")
def duck():
    import duckdb

    con = duckdb.connect()
    for t in "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split():
        con.sql(f"create view {t} as select * from '{MIDDLE}/{t}.parquet'")
    return con


def same(frame, relation):
    """Whether a DataFrame and a DuckDB relation have the same columns and rows, in any order."""
    columns = sorted(frame.columns)
    assert columns == sorted(relation.columns)
    norm = lambda v: round(v, 9) if isinstance(v, float) else tuple(map(norm, v)) if isinstance(v, (list, tuple)) else v
    at = [relation.columns.index(c) for c in columns]
    got = sorted((tuple(norm(r[c]) for c in columns) for r in frame.collect()), key=repr)
    expected = sorted((tuple(norm(r[i]) for i in at) for r in relation.fetchall()), key=repr)
    return got == expected
