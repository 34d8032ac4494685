"""Registered queries by name, each with the equivalent SQL where there is one."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {}
ORACLES: dict[str, str] = {}


def wide(function):
    """Integers as bigint, as SQL engines widen them."""

    def run(spark: SparkSession, d: str) -> DataFrame:
        df = function(spark, d)
        narrow = {c for c, t in df.dtypes if t in ("int", "smallint", "tinyint")}
        return df.select(*(F.col(c).cast("bigint").alias(c) if c in narrow else F.col(c) for c in df.columns))

    run.__name__, run.__doc__ = function.__name__, function.__doc__
    return run


def register(name: str, function, sql: str | None = None) -> None:
    QUERIES[name] = wide(function)
    if sql:
        ORACLES[name] = sql


def query(sql: str | None = None):
    def add(function):
        register(function.__name__, function, sql)
        return function

    return add
