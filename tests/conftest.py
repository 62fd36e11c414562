import os
import sys

import pytest

ROOT = os.path.dirname(os.path.dirname(os.path.abspath(__file__)))
sys.path.insert(0, ROOT)
os.environ["PYTHONPATH"] = f"{ROOT}:{os.environ.get('PYTHONPATH', '')}"  # Python workers import the package too
SF = "/root/testdata/sf0.001"


@pytest.fixture(scope="session")
def spark(tmp_path_factory):
    from pyspark.sql import SparkSession

    shared = tmp_path_factory.mktemp("shared")
    s = (SparkSession.builder.master("local[4]").config("spark.sql.shuffle.partitions", "4").config("spark.ui.enabled", "false").config("spark.ui.showConsoleProgress", "false")
         .config("spark.sql.session.timeZone", "UTC").config("spark.driver.memory", "4g").config("spark.checkpoint.dir", str(shared)).config("spark.sql.warehouse.dir", str(shared / "wh")).getOrCreate())
    s.sparkContext.setLogLevel("OFF")
    yield s
    s.stop()


@pytest.fixture(scope="session")
def oracle():
    """Run oracle SQL over the smallest tables."""
    import glob

    import duckdb

    def run(sql: str, sf: str = SF):
        c = duckdb.connect()
        for p in glob.glob(f"{sf}/*.parquet"):
            c.execute(f"CREATE VIEW {os.path.basename(p)[:-8]} AS SELECT * FROM '{p}'")
        r = c.execute(sql)
        return [d[0] for d in r.description], r.fetchall()

    return run


def rows_of(df, cols=None):
    cols = cols or df.columns
    key = lambda r: tuple((x is None, str(x)) for x in r)
    return sorted((tuple(r[c] for c in cols) for r in df.collect()), key=key)
