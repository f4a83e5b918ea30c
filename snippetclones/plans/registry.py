"""The registry of queries: a name, typed output columns, a Spark function and, where SQL can express it, DuckDB SQL.

Both sides are published alike: integers as BIGINT, doubles rounded to six
places, so that value hashes agree.
"""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..session import shared_dir, ship_package

QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {}
ORACLE: dict[str, str] = {}
_SPARK = {"l": "bigint", "d": "double", "s": "string", "b": "boolean"}
_DUCK = {"l": "BIGINT", "d": "DOUBLE", "s": "VARCHAR", "b": "BOOLEAN"}


def _columns(spec: str) -> list[tuple[str, str]]:
    return [tuple(x.split(":")) for x in spec.split()]


def publish(df: DataFrame, spec: str) -> DataFrame:
    out = []
    for name, kind in _columns(spec):
        c = F.col(name).cast(_SPARK[kind])
        out.append((F.round(c, 6) + F.lit(0.0) if kind == "d" else c).alias(name))
    return df.select(*out)


def publish_sql(sql: str, spec: str) -> str:
    out = []
    for name, kind in _columns(spec):
        c = f'CAST("{name}" AS {_DUCK[kind]})'
        out.append(f'{f"round({c}, 6) + 0.0" if kind == "d" else c} AS "{name}"')
    return f"SELECT {', '.join(out)} FROM (\n{sql}\n) AS published"


def query(spec: str, sql: str | None = None, name: str | None = None):
    """Register a function ``(spark, sf_dir)`` under its name, with its column types and its oracle."""

    def wrap(f):
        key = name or f.__name__

        def run(spark: SparkSession, sf_dir: str) -> DataFrame:
            ship_package(spark)
            shared_dir(spark)
            return publish(f(spark, sf_dir), spec)

        QUERIES[key] = run
        if sql:
            ORACLE[key] = publish_sql(sql, spec)
        return f

    return wrap
