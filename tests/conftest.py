import os
import sys
from pathlib import Path

import pytest

ROOT = Path(__file__).resolve().parent.parent
sys.path.insert(0, str(ROOT))
os.environ.setdefault("PYSPARK_PYTHON", sys.executable)


@pytest.fixture(scope="session")
def spark():
    from pyspark.sql import SparkSession

    s = (
        SparkSession.builder.master("local[8]").config("spark.sql.shuffle.partitions", "8").config("spark.ui.enabled", "false").config("spark.driver.memory", "6g")
        .config("spark.ui.showConsoleProgress", "false").config("spark.sql.session.timeZone", "UTC").getOrCreate()
    )
    s.sparkContext.setLogLevel("ERROR")
    yield s


@pytest.fixture(scope="session")
def data():
    return "/root/testdata/sf0.001"


@pytest.fixture(scope="session")
def duck():
    """Runs SQL over the tables of a folder."""
    import duckdb

    def run(sql, folder):
        c = duckdb.connect()
        for p in Path(folder).glob("*.parquet"):
            c.execute(f"CREATE VIEW {p.stem} AS SELECT * FROM '{p}{'/*.parquet' if p.is_dir() else ''}'")
        return c.execute(sql).df()

    return run


def same(a, b):
    """Two pandas frames hold the same rows, in any order; doubles to nine digits."""
    assert sorted(a.columns) == sorted(b.columns)
    import pandas as pd

    def text(v):
        if v is None or v is pd.NA or v != v:
            return "null"
        try:
            return f"{float(v):.9g}" if not isinstance(v, bool | str) else str(v)
        except (TypeError, ValueError):
            return str(v)

    rows = lambda x: sorted(tuple(map(text, r)) for r in x[sorted(x.columns)].astype(object).itertuples(index=False, name=None))
    return rows(a) == rows(b)
