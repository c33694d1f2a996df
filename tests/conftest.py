import os
import sys

import pytest

sys.path.insert(0, os.path.dirname(os.path.dirname(os.path.abspath(__file__))))
os.environ["PYTHONPATH"] = os.pathsep.join(x for x in (sys.path[0], os.environ.get("PYTHONPATH")) if x)

SF = "/root/testdata/sf0.001"


@pytest.fixture(scope="session")
def spark():
    from pyspark.sql import SparkSession

    s = SparkSession.builder.master("local[4]").config("spark.sql.shuffle.partitions", "4").config("spark.driver.memory", "4g").config("spark.ui.enabled", "false").config("spark.ui.showConsoleProgress", "false").config("spark.sql.session.timeZone", "UTC").getOrCreate()
    s.sparkContext.setLogLevel("ERROR")
    yield s
    s.stop()


@pytest.fixture(scope="session")
def sf():
    return SF


@pytest.fixture(scope="session")
def duck():
    import duckdb

    c = duckdb.connect()
    for t in "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split():
        c.execute(f"create view {t} as select * from read_parquet('{SF}/{t}.parquet')")
    return c


def plain(v):
    """Values of both engines in one form; floats to nine digits, with no negative zero."""
    if isinstance(v, float):
        return f"{round(v, 9) + 0.0:.9f}"
    if hasattr(v, "isoformat"):
        return v.isoformat()
    return str(v)


def same_rows(df, duck, sql):
    got = df.collect()
    r = duck.execute(sql)
    names = [x[0] for x in r.description]
    want = r.fetchall()
    assert sorted(names) == sorted(df.columns)
    order = sorted(names)
    a = sorted(tuple(plain(x[c]) for c in order) for x in got)
    b = sorted(tuple(plain(x[names.index(c)]) for c in order) for x in want)
    assert a == b
    return len(a)
