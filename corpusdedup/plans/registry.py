"""A registry of queries, each beside the SQL it must agree with."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

Query = Callable[[SparkSession, str], DataFrame]
QUERIES: dict[str, Query] = {}
ORACLES: dict[str, str] = {}


def wide(df: DataFrame) -> DataFrame:
    """Integers as long and decimals as double, so that both engines name the same types."""
    small = (T.IntegerType, T.ShortType, T.ByteType)
    cols = [F.col(f"`{f.name}`").cast("long").alias(f.name) if isinstance(f.dataType, small) else F.col(f"`{f.name}`").cast("double").alias(f.name) if isinstance(f.dataType, T.DecimalType) else F.col(f"`{f.name}`") for f in df.schema.fields]
    return df.select(*cols)


def query(sql: str | None = None, name: str | None = None) -> Callable[[Query], Query]:
    """Register a query under its function's name, with its oracle if it has one."""

    def add(f: Query) -> Query:
        key = name or f.__name__
        QUERIES[key] = lambda spark, sf_dir: wide(f(spark, sf_dir))
        if sql is not None:
            ORACLES[key] = sql
        return f

    return add
