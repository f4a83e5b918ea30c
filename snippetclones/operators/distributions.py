"""Histograms, two-dimensional grids and box-plot numbers."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F


def hist(df: DataFrame, col: str, width: float | None = None, log2: bool = False, cap: int | None = None, drop_top: int = 0, weight: str | None = None) -> DataFrame:
    """``(bin, cnt)`` with zero bins absent. ``drop_top`` leaves the largest value out where it stands alone."""
    v = F.col(col)
    if drop_top:
        top = df.groupBy(v.alias("top_")).agg(F.count("*").alias("rows_")).orderBy(F.desc("top_")).limit(1).where("rows_ = 1")
        df = df.join(F.broadcast(top), v == F.col("top_"), "left_anti")  # at most one row
    b = F.floor(F.log2(v + 1)) if log2 else F.floor(v / width) if width else v
    b = F.least(b, F.lit(cap)) if cap is not None else b
    return df.groupBy(b.cast("long").alias("bin")).agg((F.sum(weight) if weight else F.count("*")).alias("cnt"))


def grid2d(df: DataFrame, x, y) -> DataFrame:
    return df.groupBy(x.alias("x"), y.alias("y")).agg(F.count("*").alias("cnt"))


def box(df: DataFrame, group: str, y: str) -> DataFrame:
    """Quartiles, whiskers (the outermost values within 1.5 interquartile ranges) and outliers of each group."""
    q = df.groupBy(group).agg(F.percentile(y, F.array(F.lit(0.25), F.lit(0.5), F.lit(0.75))).alias("q"))
    q = q.select(group, F.col("q")[0].alias("q1"), F.col("q")[1].alias("q2"), F.col("q")[2].alias("q3"))
    j = df.join(q, group)
    reach = 1.5 * (F.col("q3") - F.col("q1"))
    inside = F.col(y).between(F.col("q1") - reach, F.col("q3") + reach)
    return j.groupBy(group, "q1", "q2", "q3").agg(F.min(F.when(inside, F.col(y))).alias("low"), F.max(F.when(inside, F.col(y))).alias("high"), F.count_if(~inside).alias("outliers"))
