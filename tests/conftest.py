import os
import sys
from pathlib import Path

import pytest

ROOT = Path(__file__).resolve().parent.parent
sys.path.insert(0, str(ROOT))
os.environ["PYTHONPATH"] = f"{ROOT}:{os.environ.get('PYTHONPATH', '')}"
os.environ.setdefault("OMP_NUM_THREADS", "1")
DATA = "/root/testdata"
TABLES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()


@pytest.fixture(scope="session")
def spark():
    from pyspark.sql import SparkSession

    s = (
        SparkSession.builder.master("local[8]").config("spark.sql.shuffle.partitions", "8").config("spark.driver.memory", "6g")
        .config("spark.ui.enabled", "false").config("spark.ui.showConsoleProgress", "false").config("spark.sql.session.timeZone", "UTC").getOrCreate()
    )
    s.sparkContext.setLogLevel("ERROR")
    yield s
    s.stop()


@pytest.fixture(scope="session")
def duck():
    """A DuckDB connection with the tables of the smallest size as views."""
    import duckdb

    c = duckdb.connect()
    for t in TABLES:
        c.sql(f"CREATE VIEW {t} AS SELECT * FROM '{DATA}/sf0.001/{t}.parquet'")
    return c


def rows_of(cols, rows):
    """Rows with columns by name, floats rounded."""
    text = lambda v: repr(round(v, 9)) if isinstance(v, float) else str(v)
    return sorted(tuple(text(v) for _, v in sorted(zip(cols, r))) for r in rows)


@pytest.fixture(scope="session")
def same(spark, duck):
    """Whether a query gives what its SQL gives."""

    def check(query, sql, sf=f"{DATA}/sf0.001"):
        df = query(spark, sf)
        want = duck.sql(sql)
        assert sorted(df.columns) == sorted(want.columns)
        assert rows_of(df.columns, df.collect()) == rows_of(want.columns, want.fetchall())

    return check
