import os
import sys

import pytest

ROOT = os.path.dirname(os.path.dirname(os.path.abspath(__file__)))
sys.path.insert(0, ROOT)
os.environ.setdefault("PYSPARK_PYTHON", sys.executable)
DATA = "/root/testdata"


@pytest.fixture(scope="session")
def spark():
    from pyspark.sql import SparkSession

    s = (
        SparkSession.builder.master("local[*]").appName("orthant-tests").config("spark.sql.shuffle.partitions", "8").config("spark.ui.enabled", "false")
        .config("spark.driver.memory", "6g").config("spark.sql.session.timeZone", "UTC").config("spark.ui.showConsoleProgress", "false").getOrCreate()
    )
    s.sparkContext.setLogLevel("ERROR")
    yield s
    s.stop()


@pytest.fixture(scope="session")
def sf():
    return f"{DATA}/sf0.001"


def duck(sql, sf_dir):
    """The SQL's rows over the tables of sf_dir."""
    import glob

    import duckdb

    con = duckdb.connect()
    con.execute("SET TimeZone = 'UTC'")
    for f in glob.glob(f"{sf_dir}/*.parquet"):
        con.execute(f"CREATE VIEW {os.path.basename(f)[:-8]} AS SELECT * FROM '{f}'")
    cur = con.execute(sql)
    return [c[0] for c in cur.description], cur.fetchall()


def same_rows(df, sql, sf_dir):
    """Whether a DataFrame and the SQL give the same rows, exactly, columns taken by name."""
    names, rows = duck(sql, sf_dir)
    assert sorted(names) == sorted(df.columns)
    key = sorted(names)
    at = [names.index(c) for c in key]
    text = lambda v: repr(float(v)) if isinstance(v, float) else str(v)
    got = sorted(tuple(text(r[c]) for c in key) for r in df.collect())
    want = sorted(tuple(text(r[i]) for i in at) for r in rows)
    return got == want
