from __future__ import annotations

import os
import sys

import pytest

sys.path.insert(0, os.path.dirname(os.path.dirname(os.path.abspath(__file__))))

SMALL = "/root/testdata/sf0.001"
MIDDLE = "/root/testdata/sf0.01"
TABLES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()


@pytest.fixture(scope="session")
def spark():
    from pyspark.sql import SparkSession

    s = (
        SparkSession.builder.master("local[8]").config("spark.sql.shuffle.partitions", "8").config("spark.ui.enabled", "false")
        .config("spark.sql.session.timeZone", "UTC").config("spark.driver.memory", "6g").getOrCreate()
    )
    s.sparkContext.setLogLevel("ERROR")
    yield s
    s.stop()


@pytest.fixture(scope="session")
def duck():
    import duckdb

    c = duckdb.connect()
    c.execute("SET TimeZone = 'UTC'")
    for n in TABLES:
        c.execute(f"CREATE VIEW {n} AS SELECT * FROM '{MIDDLE}/{n}.parquet'")
    return c


def _plain(v):
    import decimal
    import math

    if isinstance(v, decimal.Decimal):
        return float(v) if v % 1 else int(v)
    if isinstance(v, float):
        return None if math.isnan(v) else round(v, 9)
    return v if isinstance(v, (int, str, bool, type(None))) else str(v)


def same_rows(df, cursor) -> None:
    names = [x[0] for x in cursor.description]
    assert sorted(df.columns) == sorted(names)
    order = sorted(names)
    mine = sorted((tuple(_plain(r[c]) for c in order) for r in df.collect()), key=str)
    theirs = sorted((tuple(_plain(r[names.index(c)]) for c in order) for r in cursor.fetchall()), key=str)
    assert len(mine) == len(theirs)
    assert mine == theirs
