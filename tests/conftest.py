import os
import sys

import duckdb
import pytest
from pyspark.sql import SparkSession

ROOT = os.path.dirname(os.path.dirname(os.path.abspath(__file__)))
sys.path.insert(0, ROOT)
SMALL = os.environ.get("SIGRES_TEST_DIR", "/root/testdata/sf0.001")


@pytest.fixture(scope="session")
def spark():
    s = (SparkSession.builder.master("local[4]").config("spark.sql.shuffle.partitions", "4").config("spark.ui.enabled", "false")
         .config("spark.ui.showConsoleProgress", "false").config("spark.sql.session.timeZone", "UTC").getOrCreate())
    s.sparkContext.setLogLevel("ERROR")
    yield s


@pytest.fixture(scope="session")
def small():
    if not os.path.isdir(SMALL):
        pytest.skip("the given tables are not here")
    return SMALL


@pytest.fixture(scope="session")
def duck(small):
    c = duckdb.connect()
    for name in os.listdir(small):
        if name.endswith(".parquet"):
            path = f"{small}/{name}"
            c.execute(f"CREATE VIEW {name[:-8]} AS SELECT * FROM '{path + '/*.parquet' if os.path.isdir(path) else path}'")
    return c


def canonical(columns, rows):
    order = sorted(range(len(columns)), key=lambda i: columns[i])
    text = lambda v: f"{v:.6f}" if isinstance(v, float) else str(v)
    return sorted(columns), sorted(tuple(text(r[i]) for i in order) for r in rows)


@pytest.fixture(scope="session")
def agrees(spark, duck, small):
    def check(query, oracle):
        df = query(spark, small)
        got = canonical(df.columns, [tuple(r) for r in df.collect()])
        r = duck.execute(oracle)
        assert got == canonical([x[0] for x in r.description], r.fetchall())
    return check
