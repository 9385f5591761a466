import os
import sys

import pytest

ROOT = os.path.dirname(os.path.dirname(os.path.abspath(__file__)))
sys.path.insert(0, ROOT)
os.environ["PYTHONPATH"] = ROOT + os.pathsep + os.environ.get("PYTHONPATH", "")


@pytest.fixture(scope="session")
def spark():
    from pyspark.sql import SparkSession

    s = SparkSession.builder.master("local[4]").config("spark.sql.shuffle.partitions", "4").config("spark.ui.enabled", "false").config("spark.sql.session.timeZone", "UTC").config("spark.driver.memory", "4g").config("spark.ui.showConsoleProgress", "false").getOrCreate()
    s.sparkContext.setLogLevel("ERROR")
    yield s
    s.stop()


SF = "/root/testdata/sf0.001"
TABLES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()


@pytest.fixture(scope="session")
def duck():
    import duckdb

    con = duckdb.connect()
    con.execute("set TimeZone = 'UTC'")
    for t in TABLES:
        con.execute(f"create view {t} as select * from '{SF}/{t}.parquet'")
    return con


def rows_of(frame):
    """Sorted rows of a pandas frame with columns by name; floats to six places."""
    import pandas as pd

    def norm(x):
        if isinstance(x, float):
            return None if x != x else round(x, 6) + 0.0
        if x is None or x is pd.NA or x is pd.NaT:
            return None
        return x.item() if hasattr(x, "item") else x

    cols = sorted(frame.columns)
    return cols, sorted(repr([(int(v) if isinstance(v, float) and v.is_integer() else v) for v in map(norm, r)]) for r in frame[cols].itertuples(index=False, name=None))
