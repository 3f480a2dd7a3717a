import os
import sys

import pytest

ROOT = os.path.dirname(os.path.dirname(os.path.abspath(__file__)))
sys.path.insert(0, ROOT)
os.environ["PYTHONPATH"] = os.pathsep.join([ROOT, os.environ.get("PYTHONPATH", "")])
SF = "/root/testdata/sf0.001"


@pytest.fixture(scope="session")
def spark():
    from pyspark.sql import SparkSession

    s = (
        SparkSession.builder.master("local[8]").config("spark.sql.shuffle.partitions", "8").config("spark.driver.memory", "4g").config("spark.ui.enabled", "false")
        .config("spark.ui.showConsoleProgress", "false").config("spark.sql.session.timeZone", "UTC").getOrCreate()
    )
    s.sparkContext.setLogLevel("ERROR")
    return s


@pytest.fixture(scope="session")
def duck():
    import duckdb

    con = duckdb.connect()
    for t in "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split():
        con.execute(f"create view {t} as select * from '{SF}/{t}.parquet'")
    return con


def _plain(v):
    if v is None or (isinstance(v, float) and v != v):
        return None
    if isinstance(v, float):
        return float(f"{v:.6g}")
    return v


@pytest.fixture(scope="session")
def same(spark, duck):
    """Compares a query's rows with its SQL twin's."""

    def check(query, sql):
        df = query(spark, SF)
        cols = sorted(df.columns)
        got = sorted(([_plain(v) for v in r] for r in df.select(*(f"`{c}`" for c in cols)).collect()), key=repr)
        rel = duck.sql(sql)
        assert cols == sorted(rel.columns)
        want = sorted(([_plain(v) for v in r] for r in rel.select(*(f'"{c}"' for c in cols)).fetchall()), key=repr)
        assert got == want

    return check
