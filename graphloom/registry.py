"""Registered queries: a name, a function of (spark, sf_dir), and SQL that says the same."""

from __future__ import annotations

import re
from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession

TABLES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()
QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {}
ORACLES: dict[str, str] = {}


def load(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def query(name: str, sql: str | None = None):
    """Decorator: register fn(spark, sf_dir) under name."""

    def add(fn):
        if name in QUERIES:
            raise ValueError(f"{name} is registered twice")
        QUERIES[name] = fn
        if sql:
            ORACLES[name] = sql
        return fn

    return add


def sql_query(name: str, spark_sql: str, oracle: str | None = None) -> None:
    """Register a query written in SQL over {table} placeholders. oracle: where DuckDB's dialect differs."""
    used = [t for t in TABLES if f"{{{t}}}" in spark_sql]

    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        return spark.sql(spark_sql, **{t: load(spark, sf_dir, t) for t in used})

    query(name, re.sub(r"\{(\w+)\}", r"\1", oracle or spark_sql))(run)
