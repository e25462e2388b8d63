from __future__ import annotations

import sys
from pathlib import Path

import pytest

sys.path.insert(0, str(Path(__file__).resolve().parent.parent))


@pytest.fixture(scope="session")
def spark():
    from pyspark.sql import SparkSession

    session = (
        SparkSession.builder.master("local[4]")
        .config("spark.sql.shuffle.partitions", "4")
        .config("spark.ui.enabled", "false")
        .config("spark.ui.showConsoleProgress", "false")
        .config("spark.sql.session.timeZone", "UTC")
        .config("spark.driver.memory", "4g")
        .getOrCreate()
    )
    session.sparkContext.setLogLevel("ERROR")
    yield session
    session.stop()


@pytest.fixture(scope="session")
def duck():
    import duckdb

    con = duckdb.connect()
    for t in "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split():
        con.execute(f"CREATE VIEW {t} AS SELECT * FROM read_parquet('/root/testdata/sf0.001/{t}.parquet')")
    return con


@pytest.fixture(scope="session")
def same():
    import pandas as pd

    def compare(a, b):
        cols = sorted(a.columns)
        assert cols == sorted(b.columns)

        def rows(d):
            def text(v):
                if pd.isna(v):
                    return "null"
                return repr(float(v)) if isinstance(v, (int, float)) and not isinstance(v, bool) else str(v)

            return sorted(tuple(text(v) for v in r) for r in d[cols].astype(object).itertuples(index=False))

        assert rows(a) == rows(b)

    return compare
