"""One small session for all tests."""

from __future__ import annotations

import sys
from pathlib import Path

import pytest

ROOT = Path(__file__).resolve().parents[1]
sys.path.insert(0, str(ROOT))
SF = "/root/testdata/sf0.001"


@pytest.fixture(scope="session")
def spark(tmp_path_factory):
    from pyspark.sql import SparkSession

    from subpopgrid.session import on_workers

    s = (
        SparkSession.builder.master("local[4]")
        .config("spark.sql.shuffle.partitions", "4")
        .config("spark.ui.enabled", "false")
        .config("spark.ui.showConsoleProgress", "false")
        .config("spark.sql.session.timeZone", "UTC")
        .config("spark.driver.memory", "4g")
        .config("spark.checkpoint.dir", f"file://{tmp_path_factory.mktemp('shared')}")
        .getOrCreate()
    )
    s.sparkContext.setLogLevel("OFF")
    on_workers(s)
    yield s
    s.stop()


@pytest.fixture(scope="session")
def duck():
    """DuckDB over the small given tables, for the SQL of the queries."""
    import duckdb

    con = duckdb.connect()
    for p in sorted(Path(SF).glob("*.parquet")):
        con.execute(f"CREATE VIEW {p.stem} AS SELECT * FROM '{p}'")
    return con


def same_rows(spark_df, duck_df) -> None:
    """Equal as multisets of rows, columns by name."""
    a = spark_df.toPandas()
    names = sorted(a.columns)
    assert sorted(duck_df.columns) == names
    key = lambda f: sorted(tuple(map(str, r)) for r in f[names].astype(object).where(f[names].notna(), None).itertuples(index=False))
    assert key(a) == key(duck_df)
