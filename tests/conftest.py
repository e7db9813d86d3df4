from __future__ import annotations

import os
import sys
from pathlib import Path

import pytest

ROOT = Path(__file__).resolve().parent.parent
sys.path.insert(0, str(ROOT))
os.environ["PYTHONPATH"] = f"{ROOT}:{os.environ.get('PYTHONPATH', '')}"
SF = os.environ.get("TEST_SF_DIR", "/root/testdata/sf0.001")


@pytest.fixture(scope="session")
def spark():
    from pyspark.sql import SparkSession

    session = (
        SparkSession.builder.master("local[4]").appName("tests").config("spark.sql.shuffle.partitions", "4").config("spark.driver.memory", "4g").config("spark.sql.session.timeZone", "UTC")
        .config("spark.ui.enabled", "false").config("spark.ui.showConsoleProgress", "false").getOrCreate()
    )
    session.sparkContext.setLogLevel("ERROR")
    yield session
    session.stop()


@pytest.fixture(scope="session")
def sf() -> str:
    return SF


@pytest.fixture(scope="session")
def duck(sf):
    import duckdb

    con = duckdb.connect()
    for p in Path(sf).glob("*.parquet"):
        con.execute(f"CREATE VIEW {p.stem} AS SELECT * FROM '{p}'")
    return con


def rows(df) -> list[tuple]:
    """Rows as sorted tuples, columns by name."""
    names = sorted(df.columns)
    return sorted((tuple(str(r[c]) for c in names) for r in df.collect()))


def same(spark_df, con, sql: str) -> None:
    got = spark_df.toPandas()
    want = con.execute(sql).df()
    assert sorted(got.columns) == sorted(want.columns)
    assert len(got) == len(want)
    names = sorted(got.columns)

    def text(v) -> str:
        if v is None or v != v:
            return ""
        return repr(float(v)) if isinstance(v, float) else str(v)

    a, b = (sorted(tuple(text(v) for v in r) for r in x[names].itertuples(index=False)) for x in (got, want))
    assert a == b
