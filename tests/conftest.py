import os
import sys
from pathlib import Path

import pytest
from pyspark.sql import SparkSession

sys.path.insert(0, str(Path(__file__).resolve().parents[1]))
DATA = os.environ.get("TEST_SF_DIR", "/root/testdata/sf0.001")


@pytest.fixture(scope="session")
def spark():
    s = (
        SparkSession.builder.master("local[4]").config("spark.sql.shuffle.partitions", "4").config("spark.ui.enabled", "false").config("spark.driver.memory", "4g")
        .config("spark.sql.session.timeZone", "UTC").config("spark.ui.showConsoleProgress", "false").getOrCreate()
    )
    s.sparkContext.setLogLevel("ERROR")
    yield s
    s.stop()


@pytest.fixture(scope="session")
def data():
    return DATA


@pytest.fixture(scope="session")
def duck(data):
    import duckdb

    con = duckdb.connect()
    for p in Path(data).glob("*.parquet"):
        con.execute(f"CREATE VIEW {p.stem} AS SELECT * FROM '{p if p.is_file() else str(p) + '/*.parquet'}'")
    return con


@pytest.fixture(scope="session")
def same(spark, duck, data):
    """Compares a query with its SQL: columns, rows and values."""

    def check(run, sql):
        a, b = run(spark, data).toPandas(), duck.execute(sql).df()
        cols = sorted(b.columns)
        assert cols == sorted(a.columns)
        a, b = (x[cols].sort_values(cols).reset_index(drop=True).astype(str) for x in (a, b))
        assert len(a) == len(b)
        assert (a == b).all().all(), [(c, a[c][a[c] != b[c]].head(3).tolist(), b[c][a[c] != b[c]].head(3).tolist()) for c in cols if (a[c] != b[c]).any()]

    return check
