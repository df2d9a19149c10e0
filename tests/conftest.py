import os
import sys

import pytest

sys.path.insert(0, os.path.dirname(os.path.dirname(os.path.abspath(__file__))))
SF = "/root/testdata/sf0.001"


@pytest.fixture(scope="session")
def spark():
    from pyspark.sql import SparkSession

    s = (
        SparkSession.builder.master("local[4]").config("spark.sql.shuffle.partitions", "4").config("spark.ui.enabled", "false").config("spark.sql.session.timeZone", "UTC")
        .config("spark.driver.memory", "6g").config("spark.sql.streaming.stateStore.providerClass", "org.apache.spark.sql.execution.streaming.state.RocksDBStateStoreProvider").getOrCreate()
    )
    s.sparkContext.setLogLevel("ERROR")
    yield s
    s.stop()


@pytest.fixture(scope="session")
def sf():
    return SF


@pytest.fixture(scope="session")
def duck():
    import duckdb

    con = duckdb.connect()
    for t in "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split():
        con.sql(f"CREATE VIEW {t} AS SELECT * FROM '{SF}/{t}.parquet'")
    return con


def rows_match(df, relation):
    """Rows of a Spark frame and of a DuckDB relation, columns by name, in any order."""
    cols = sorted(df.columns)
    assert cols == sorted(relation.columns)

    def key(v):
        return "" if v is None else repr(float(v)) if type(v).__name__ in ("float", "Decimal") else str(v)

    mine = sorted(tuple(key(r[c]) for c in cols) for r in df.collect())
    at = [list(relation.columns).index(c) for c in cols]
    theirs = sorted(tuple(key(r[i]) for i in at) for r in relation.fetchall())
    assert mine == theirs
