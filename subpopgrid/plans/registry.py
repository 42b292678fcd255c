"""The catalogue of named queries and their SQL."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .oracle import cast_list

QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {}
SQL: dict[str, str] = {}


def projected(df: DataFrame, cols: str) -> DataFrame:
    """A fixed column list: ``a:l b:d c:s d:b`` as BIGINT, DOUBLE rounded to 6 digits, STRING, BOOLEAN."""
    kinds = {"l": lambda c: F.col(c).cast("long"), "d": lambda c: F.round(F.col(c).cast("double"), 6) + F.lit(0.0), "s": lambda c: F.col(c).cast("string"), "b": lambda c: F.col(c).cast("boolean")}
    return df.select(*(kinds[k](c).alias(c) for c, k in (x.split(":") for x in cols.split())))


def query(name: str, cols: str, sql: str | None = None):
    """Registers ``f(spark, sf_dir)``; ``sql`` is ``WITH ...`` and a last ``SELECT``, split at ``@@``, or a plain FROM body."""

    def add(f: Callable[[SparkSession, str], DataFrame]):
        QUERIES[name] = lambda spark, sf_dir: projected(f(spark, sf_dir), cols)
        if sql is not None:
            head, _, body = sql.rpartition("@@")
            SQL[name] = (f"WITH {head} " if head.strip() else "") + f"SELECT {cast_list(cols)} FROM ({body})"
        return f

    return add
