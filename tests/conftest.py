import os
import sys

import pytest

sys.path.insert(0, os.path.dirname(os.path.dirname(os.path.abspath(__file__))))
TABLES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()
TINY, SMALL = "/root/testdata/sf0.001", "/root/testdata/sf0.01"


@pytest.fixture(scope="session")
def spark():
    from pyspark.sql import SparkSession

    s = (
        SparkSession.builder.master("local[8]")
        .config("spark.sql.shuffle.partitions", "8")
        .config("spark.ui.enabled", "false")
        .config("spark.driver.memory", "6g")
        .config("spark.sql.session.timeZone", "UTC")
        .getOrCreate()
    )
    s.sparkContext.setLogLevel("ERROR")
    return s


def duck(sf: str):
    import duckdb

    c = duckdb.connect()
    c.sql("SET TimeZone = 'UTC'")
    for t in TABLES:
        c.sql(f"CREATE VIEW {t} AS SELECT * FROM '{sf}/{t}.parquet'")
    return c


def rows(df) -> list[tuple]:
    """Rows with columns in order of name, as comparable text, sorted."""
    df = df[sorted(df.columns)]
    say = lambda v: "NULL" if v is None or v != v or str(v) in ("NaT", "<NA>") else v.hex() if isinstance(v, float) else str(v)
    return sorted(tuple(say(v) for v in r) for r in df.itertuples(index=False, name=None))


def agree(spark, name: str, query, sql: str, sf: str) -> None:
    got, want = query(spark, sf).toPandas(), duck(sf).sql(sql).df()
    assert sorted(got.columns) == sorted(want.columns), name
    assert rows(got) == rows(want), name
