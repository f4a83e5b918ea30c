"""Assertions on physical plans of hot paths."""

from __future__ import annotations

from pyspark.sql import DataFrame

FORBIDDEN = ("CartesianProduct", "BatchEvalPython", "Exchange SinglePartition", "BroadcastNestedLoopJoin")


def text(df: DataFrame) -> str:
    """The formatted physical plan."""
    return df._sc._jvm.PythonSQLUtils.explainString(df._jdf.queryExecution(), "formatted")


def check(df: DataFrame, allow: tuple[str, ...] = ()) -> str:
    """Fail where a plan holds a cross product, row-at-a-time Python or a single-partition exchange."""
    plan = text(df)
    found = [x for x in FORBIDDEN if x in plan and x not in allow]
    if found:
        raise AssertionError(f"plan holds {found}\n{plan}")
    return plan
