import os
import sys

import pytest

sys.path.insert(0, os.path.dirname(os.path.dirname(os.path.abspath(__file__))))
os.environ["PYTHONPATH"] = sys.path[0] + os.pathsep + os.environ.get("PYTHONPATH", "")

SF = "/root/testdata/sf0.001"


@pytest.fixture(scope="session")
def spark():
    from pyspark.sql import SparkSession

    s = SparkSession.builder.master("local[4]").config("spark.sql.shuffle.partitions", "4").config("spark.ui.enabled", "false").config("spark.sql.session.timeZone", "UTC").config("spark.ui.showConsoleProgress", "false").getOrCreate()
    s.sparkContext.setLogLevel("ERROR")
    yield s


def duck(sql, sf=SF):
    import duckdb

    con = duckdb.connect()
    for name in os.listdir(sf):
        con.execute(f"CREATE VIEW {name.split('.')[0]} AS SELECT * FROM '{sf}/{name}'")
    rel = con.execute(sql)
    names = [c[0] for c in rel.description]
    return names, rel.fetchall()


def plain(v):
    return round(v, 5) if isinstance(v, float) else v


def same(df, sql, sf=SF):
    """Whether a Spark result and the SQL over the same tables hold the same rows."""
    names, rows = duck(sql, sf)
    got = df.select(*names).collect()
    key = lambda r: tuple(str(plain(v)) for v in r)
    assert sorted(df.columns) == sorted(names)
    assert sorted(map(key, got)) == sorted(map(key, rows))
