import os
import sys

import pytest

sys.path.insert(0, os.path.dirname(os.path.dirname(os.path.abspath(__file__))))
os.environ["PYTHONPATH"] = os.pathsep.join([sys.path[0], os.environ.get("PYTHONPATH", "")])


@pytest.fixture(scope="session")
def spark(tmp_path_factory):
    from pyspark.sql import SparkSession

    s = (
        SparkSession.builder.master("local[4]").config("spark.sql.shuffle.partitions", "4").config("spark.ui.enabled", "false").config("spark.sql.session.timeZone", "UTC")
        .config("spark.checkpoint.dir", str(tmp_path_factory.mktemp("shared"))).config("spark.driver.memory", "4g").config("spark.ui.showConsoleProgress", "false").getOrCreate()
    )
    s.sparkContext.setLogLevel("ERROR")
    yield s
    s.stop()


@pytest.fixture(scope="session")
def sf():
    return "/root/testdata/sf0.001"


@pytest.fixture(scope="session")
def duck(sf):
    import glob

    import duckdb

    con = duckdb.connect()
    for p in glob.glob(f"{sf}/*.parquet"):
        con.execute(f"create view {os.path.basename(p)[:-8]} as select * from '{p}'")
    return con


def plain(df):
    """Rows of a pandas frame as comparable tuples, columns by name."""
    import math

    def one(v):
        if v is None or (isinstance(v, float) and math.isnan(v)) or str(v) in ("NaT", "<NA>"):
            return None
        if isinstance(v, float) or getattr(getattr(v, "dtype", None), "kind", "") == "f":
            return str(int(v)) if float(v).is_integer() else f"{float(v):.6f}"
        return str(v)

    columns = sorted(df.columns)
    return columns, sorted((tuple(one(v) for v in r) for r in df[columns].itertuples(index=False)), key=str)


@pytest.fixture(scope="session")
def same_rows():
    def check(a, b):
        (ca, ra), (cb, rb) = plain(a), plain(b)
        assert ca == cb
        assert ra == rb

    return check
