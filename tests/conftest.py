import os
import sys

import duckdb
import pytest
from pyspark.sql import SparkSession

sys.path.insert(0, os.path.dirname(os.path.dirname(os.path.abspath(__file__))))
DATA = os.environ.get("CHARTREL_TESTDATA", "/root/testdata")


@pytest.fixture(scope="session")
def spark():
    s = (
        SparkSession.builder.master("local[4]").config("spark.sql.shuffle.partitions", "4").config("spark.ui.enabled", "false")
        .config("spark.sql.session.timeZone", "UTC").config("spark.driver.memory", "4g").config("spark.ui.showConsoleProgress", "false").getOrCreate()
    )
    s.sparkContext.setLogLevel("ERROR")
    yield s
    s.stop()


@pytest.fixture(scope="session")
def small():
    return f"{DATA}/sf0.001"


@pytest.fixture(scope="session")
def duck(small):
    c = duckdb.connect()
    for t in "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split():
        c.sql(f"create view {t} as select * from read_parquet('{small}/{t}.parquet')")
    return c


def rows_of(df):
    """Columns and sorted rows as text, doubles to six places."""
    cols = sorted(df.columns)
    text = lambda v: f"{v:.6f}" if isinstance(v, float) else str(v)
    return cols, sorted(tuple(text(x) for x in r) for r in df.select(*cols).collect())


def duck_rows(con, sql):
    r = con.sql(sql)
    names = r.columns
    cols = sorted(names)
    text = lambda v: f"{v:.6f}" if isinstance(v, float) else str(v)
    at = [names.index(c) for c in cols]
    return cols, sorted(tuple(text(row[i]) for i in at) for row in r.fetchall())
