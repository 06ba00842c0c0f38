import os
import sys

import pytest

ROOT = os.path.dirname(os.path.dirname(os.path.abspath(__file__)))
sys.path.insert(0, ROOT)
os.environ.setdefault("PYTHONPATH", ROOT)
SF = "/root/testdata/sf0.001"
TABLES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()


@pytest.fixture(scope="session")
def spark():
    from pyspark.sql import SparkSession

    s = (
        SparkSession.builder.master("local[4]")
        .config("spark.sql.shuffle.partitions", "4")
        .config("spark.ui.enabled", "false")
        .config("spark.driver.memory", "4g")
        .config("spark.sql.session.timeZone", "UTC")
        .config("spark.sql.streaming.stateStore.providerClass", "org.apache.spark.sql.execution.streaming.state.RocksDBStateStoreProvider")
        .getOrCreate()
    )
    s.sparkContext.setLogLevel("OFF")
    return s


@pytest.fixture(scope="session")
def duck():
    import duckdb

    c = duckdb.connect()
    for t in TABLES:
        c.execute(f"CREATE VIEW {t} AS SELECT * FROM '{SF}/{t}.parquet'")
    return c


def same_rows(df, rel) -> None:
    """Equal columns, and equal rows in any order."""
    assert sorted(df.columns) == sorted(rel.columns)
    cols = sorted(df.columns)

    def key(names, row):
        at = {n: v for n, v in zip(names, row)}
        return tuple("NULL" if at[c] is None or at[c] != at[c] else repr(float(at[c])) if isinstance(at[c], (int, float)) and not isinstance(at[c], bool) else str(at[c]) for c in cols)

    assert sorted(key(df.columns, r) for r in df.collect()) == sorted(key(rel.columns, r) for r in rel.fetchall())
