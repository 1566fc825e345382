import os
import sys

import pytest

ROOT = os.path.dirname(os.path.dirname(os.path.abspath(__file__)))
sys.path.insert(0, ROOT)
os.environ["PYTHONPATH"] = ROOT + os.pathsep + os.environ.get("PYTHONPATH", "")


@pytest.fixture(scope="session")
def spark():
    from pyspark.sql import SparkSession

    session = (
        SparkSession.builder.master("local[8]").config("spark.sql.shuffle.partitions", "8").config("spark.ui.enabled", "false").config("spark.driver.memory", "6g")
        .config("spark.sql.session.timeZone", "UTC").config("spark.ui.showConsoleProgress", "false").config("spark.sql.sources.parallelPartitionDiscovery.parallelism", "8").getOrCreate()
    )
    session.sparkContext.setLogLevel("ERROR")
    yield session
    session.stop()


@pytest.fixture(scope="session")
def compare(spark):
    """Runs a query and its SQL over a folder of tables, and asserts that they have the same rows."""
    import decimal
    import math

    import duckdb

    def plain(v):
        if isinstance(v, float):
            return round(v, 6) if math.isfinite(v) else v
        if isinstance(v, decimal.Decimal):
            return int(v) if v == int(v) else float(v)
        return str(v) if isinstance(v, (list, dict)) else v

    def check(query, sql, folder):
        df = query(spark, folder)
        cols = sorted(df.columns)
        got = sorted((tuple(plain(r[c]) for c in cols) for r in df.collect()), key=str)
        con = duckdb.connect()
        for t in "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split():
            if os.path.exists(f"{folder}/{t}.parquet"):
                source = f"{folder}/{t}.parquet"
                con.execute(f"CREATE VIEW {t} AS SELECT * FROM '{source + '/*.parquet' if os.path.isdir(source) else source}'")
        res = con.execute(sql)
        names = [x[0] for x in res.description]
        assert sorted(names) == cols
        want = sorted((tuple(plain(r[names.index(c)]) for c in cols) for r in res.fetchall()), key=str)
        assert got == want

    return check
