"""Descriptive statistics and rank tests over value histograms.

Ranks come from the histogram of values, never from a global sort of rows:
``mid_ranks`` turns (value, count) into F(v) - (c(v) - 1) / 2.  The running sum
runs over distinct values in range partitions with broadcast offsets when there
are many, and in one small window when there are few.
"""

from __future__ import annotations

import pandas as pd
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..functions import tails
from .components import cut

POINTS = (0.1, 0.25, 0.5, 0.75, 0.9)
NAMES = ("p10", "p25", "median", "p75", "p90")
#: Histograms up to this many distinct values are accumulated in one task.
FEW_VALUES = 1 << 20


def summary8(df: DataFrame, cols: list[str], weight: str | None = None) -> DataFrame:
    """min, p10, p25, median, mean, p75, p90, max of each column in long form; percentiles interpolate linearly.

    ``weight`` counts a row that often, without expanding it.
    """
    per = []
    for c in cols:
        q = F.percentile(c, F.array(*[F.lit(p) for p in POINTS]), *([F.col(weight)] if weight else []))
        mean = F.sum(F.col(c) * F.col(weight)) / F.sum(weight) if weight else F.avg(c)
        per.append(F.struct(F.lit(c).alias("measure"), F.min(c).cast("double").alias("min"), q.alias("q"), mean.cast("double").alias("mean"), F.max(c).cast("double").alias("max")))
    out = df.agg(F.array(*per).alias("a")).select(F.explode("a").alias("x")).select("x.*")
    return out.select("measure", "min", *[F.col("q")[i].alias(n) for i, n in enumerate(NAMES)], "mean", "max")


def skew_report(df: DataFrame, cols: list[str]) -> DataFrame:
    """Skewness and mean/median of each column."""
    per = [F.struct(F.lit(c).alias("measure"), F.skewness(c).alias("skewness"), F.try_divide(F.avg(c), F.percentile(c, 0.5)).alias("mean_to_median")) for c in cols]
    return df.agg(F.array(*per).alias("a")).select(F.explode("a").alias("x")).select("x.*")


def mid_ranks(hist: DataFrame, value: str = "v", count: str = "c", distributed: bool | None = None) -> DataFrame:
    """``hist`` with the mid-rank ``rank`` of each distinct value and the running count."""
    if distributed is None:
        hist = cut(hist)
        distributed = hist.count() > FEW_VALUES
    if not distributed:
        cum = F.sum(count).over(Window.orderBy(value))
        return hist.withColumn("upto", cum).withColumn("rank", F.col("upto") - (F.col(count) - 1) / 2)
    parts = hist.repartitionByRange(value).withColumn("__p", F.spark_partition_id()).checkpoint()
    totals = parts.groupBy("__p").agg(F.sum(count).alias("t"))  # one number a partition
    offset = totals.withColumn("offset", F.coalesce(F.sum("t").over(Window.orderBy("__p").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0))).select("__p", "offset")
    local = F.sum(count).over(Window.partitionBy("__p").orderBy(value))
    out = parts.join(F.broadcast(offset), "__p").withColumn("upto", local + F.col("offset"))
    return out.withColumn("rank", F.col("upto") - (F.col(count) - 1) / 2).drop("__p", "offset")


def histogram(df: DataFrame, col: str) -> DataFrame:
    return df.where(F.col(col).isNotNull()).groupBy(F.col(col).alias("v")).agg(F.count("*").alias("c"))


def _p(kind: str, statistic: float | None, df1: float = 0, df2: float = 0) -> tuple[float | None, float | None]:
    if statistic is None:
        return None, None
    return tails.p_value(kind, statistic, df1, df2), tails.log_p(kind, statistic, df1, df2) / 2.302585092994046


def _with_p(row_df: DataFrame, kind: str, df1: str | None = None, df2: str | None = None) -> DataFrame:
    """Append p and log10_p to a frame of a few test rows (Arrow, one batch)."""

    @F.pandas_udf("p double, log10_p double")
    def tail(stat: pd.Series, d1: pd.Series, d2: pd.Series) -> pd.DataFrame:
        rows = [_p(kind, None if pd.isna(s) else float(s), float(a), float(b)) for s, a, b in zip(stat, d1, d2, strict=True)]
        return pd.DataFrame(rows, columns=["p", "log10_p"], dtype=float)

    degrees = [F.col(n).cast("double") if n else F.lit(0.0) for n in (df1, df2)]
    return row_df.withColumn("__t", tail(F.col("statistic").cast("double"), *degrees)).select(*row_df.columns, "__t.p", "__t.log10_p")


def spearman(df: DataFrame, x: str, y: str) -> DataFrame:
    """Rank correlation with mid-ranks, t approximation and two-sided p: ``(n, rho, statistic, p, log10_p)``."""
    cells = df.where(F.col(x).isNotNull() & F.col(y).isNotNull()).groupBy(F.col(x).alias("x"), F.col(y).alias("y")).agg(F.count("*").alias("c"))
    rx = mid_ranks(cells.groupBy("x").agg(F.sum("c").alias("c")), "x").select("x", F.col("rank").alias("rx"))
    ry = mid_ranks(cells.groupBy("y").agg(F.sum("c").alias("c")), "y").select("y", F.col("rank").alias("ry"))
    j = cells.join(rx, "x").join(ry, "y")
    w = F.col("c").cast("double")
    s = j.agg(F.sum("c").alias("n"), *[F.sum(w * e).alias(k) for k, e in (("sx", F.col("rx")), ("sy", F.col("ry")), ("sxx", F.col("rx") ** 2), ("syy", F.col("ry") ** 2), ("sxy", F.col("rx") * F.col("ry")))])
    n = F.col("n")
    vx, vy = n * F.col("sxx") - F.col("sx") ** 2, n * F.col("syy") - F.col("sy") ** 2
    rho = F.when((vx > 0) & (vy > 0), (n * F.col("sxy") - F.col("sx") * F.col("sy")) / F.sqrt(vx * vy))
    s = s.select("n", rho.alias("rho")).withColumn("statistic", F.when(F.abs("rho") < 1, F.col("rho") * F.sqrt((n - 2) / (1 - F.col("rho") ** 2)))).withColumn("df", n - 2)
    return _with_p(s, "t", "df")


def _group_hist(df: DataFrame, group: str, y: str) -> DataFrame:
    return df.where(F.col(y).isNotNull() & F.col(group).isNotNull()).groupBy(F.col(group).alias("g"), F.col(y).alias("v")).agg(F.count("*").alias("c"))


def kruskal(df: DataFrame, group: str, y: str, exclude: tuple[str, ...] = ("UNDEFINED",)) -> DataFrame:
    """Kruskal-Wallis H with tie correction: ``(k, n, statistic, df, p, log10_p)``."""
    cells = cut(_group_hist(df, group, y).where(~F.col("g").isin(list(exclude))))
    values = mid_ranks(cells.groupBy("v").agg(F.sum("c").alias("t")), "v", "t").select("v", "t", "rank")
    ties = values.agg(F.sum((F.col("t").cast("double") ** 3) - F.col("t")).alias("ties"))
    per = cells.join(values.select("v", "rank"), "v").groupBy("g").agg(F.sum("c").alias("n"), F.sum(F.col("c") * F.col("rank")).alias("s"))
    one = per.agg(F.count("*").alias("k"), F.sum("n").alias("n"), F.sum(F.col("s") ** 2 / F.col("n")).alias("q")).crossJoin(F.broadcast(ties))
    n = F.col("n").cast("double")
    h = (12 / (n * (n + 1)) * F.col("q") - 3 * (n + 1)) / F.nullif(1 - F.col("ties") / (n**3 - n), F.lit(0.0))
    return _with_p(one.select("k", "n", F.when(F.col("k") > 1, h).alias("statistic"), (F.col("k") - 1).alias("df")), "chi2", "df")


def anova(df: DataFrame, group: str, y: str) -> DataFrame:
    """One-way analysis of variance: ``(k, n, statistic, df1, df2, p, log10_p)``."""
    g = df.where(F.col(group).isNotNull()).groupBy(group).agg(F.count(y).alias("n"), F.avg(y).alias("m"), F.var_pop(y).alias("v"))
    s = g.agg(F.count("*").alias("k"), F.sum("n").alias("n"), F.sum(F.col("n") * F.col("m")).alias("t"), F.sum(F.col("n") * F.col("m") ** 2).alias("q"), F.sum(F.col("n") * F.col("v")).alias("within"))
    s = s.withColumn("df1", F.col("k") - 1).withColumn("df2", F.col("n") - F.col("k"))
    between = F.col("q") - F.col("t") ** 2 / F.col("n")
    f = F.try_divide(F.try_divide(between, F.col("df1")), F.try_divide(F.col("within"), F.col("df2")))
    return _with_p(s.select("k", "n", f.alias("statistic"), "df1", "df2"), "f", "df1", "df2")


def residual_moments(df: DataFrame, group: str, y: str) -> DataFrame:
    """Skewness, excess kurtosis and Jarque-Bera of the residuals about group means."""
    m = df.where(F.col(group).isNotNull()).groupBy(group).agg(F.avg(y).alias("__m"))
    r = df.join(m, group).select((F.col(y) - F.col("__m")).alias("r"))
    s = r.agg(F.count("r").alias("n"), F.skewness("r").alias("skewness"), F.kurtosis("r").alias("kurtosis"))
    return s.withColumn("jarque_bera", F.col("n") / 6 * (F.col("skewness") ** 2 + F.col("kurtosis") ** 2 / 4))


def pairwise_ranksum(df: DataFrame, group: str, y: str, exclude: tuple[str, ...] = ("UNDEFINED",)) -> DataFrame:
    """Wilcoxon rank-sum of every pair of groups, with tie and continuity correction: ``(g1, g2, n1, n2, w, statistic, p, log10_p)``."""
    cells = _group_hist(df, group, y).where(~F.col("g").isin(list(exclude)))
    cells = cut(cells)
    groups = cells.select("g").distinct().agg(F.array_sort(F.collect_set("g")).alias("all"))  # a row; the result has one for each pair of groups anyway
    first = F.explode(F.transform("all", lambda x, i: F.struct(x.alias("g1"), F.slice("all", i + 2, F.size("all")).alias("later"))))
    pairs = groups.select(first.alias("e")).select("e.g1", F.explode("e.later").alias("g2"))
    ends = pairs.select(F.col("g1").alias("g"), "g1", "g2").union(pairs.select(F.col("g2").alias("g"), "g1", "g2"))
    both = cells.join(ends, "g")
    per = both.groupBy("g1", "g2", "v").agg(F.sum("c").alias("t"), F.sum(F.when(F.col("g") == F.col("g1"), F.col("c")).otherwise(0)).alias("x"))
    upto = F.sum("t").over(Window.partitionBy("g1", "g2").orderBy("v"))
    ranked = per.withColumn("rank", upto - (F.col("t") - 1) / 2)
    s = ranked.groupBy("g1", "g2").agg(F.sum("x").alias("n1"), F.sum(F.col("t") - F.col("x")).alias("n2"), F.sum(F.col("x") * F.col("rank")).alias("sx"), F.sum(F.col("t").cast("double") ** 3 - F.col("t")).alias("ties"))
    n1, n2 = F.col("n1").cast("double"), F.col("n2").cast("double")
    n = n1 + n2
    w = F.col("sx") - n1 * (n1 + 1) / 2
    off = w - n1 * n2 / 2
    sigma = F.sqrt(n1 * n2 / 12 * (n + 1 - F.col("ties") / (n * (n - 1))))
    z = F.try_divide(off - F.signum(off) * 0.5, F.nullif(sigma, F.lit(0.0)))
    return _with_p(s.select("g1", "g2", "n1", "n2", w.alias("w"), z.alias("statistic")), "normal")


def signed_rank(df: DataFrame, x: str, y: str) -> DataFrame:
    """Wilcoxon signed rank of x - y: zero differences drop out; ``(n, v, statistic, p, log10_p)``."""
    d = F.col(x) - F.col(y)
    h = df.select(d.cast("double").alias("d")).where("d <> 0").groupBy(F.round(F.abs("d"), 9).alias("v")).agg(F.count("*").alias("c"), F.count_if(F.col("d") > 0).alias("plus"))
    s = mid_ranks(h).agg(F.coalesce(F.sum("c"), F.lit(0)).alias("n"), F.sum(F.col("plus") * F.col("rank")).alias("v"), F.sum(F.col("c").cast("double") ** 3 - F.col("c")).alias("ties"))
    n = F.col("n").cast("double")
    off = F.col("v") - n * (n + 1) / 4
    sigma = F.sqrt(n * (n + 1) * (2 * n + 1) / 24 - F.col("ties") / 48)
    return _with_p(s.select("n", "v", F.try_divide(off - F.signum(off) * 0.5, F.nullif(sigma, F.lit(0.0))).alias("statistic")), "normal")


def adjust(tests: DataFrame, method: str = "hochberg", p: str = "p") -> DataFrame:
    """Family-wise adjustment of a few p-values: step-up, or times the family's size."""
    m = F.count(p).over(Window.partitionBy())
    if method == "bonferroni":
        return tests.withColumn("adjusted", F.least(F.lit(1.0), F.col(p) * m))
    place = F.row_number().over(Window.orderBy(F.desc(p)))
    out = tests.withColumn("__i", place)
    return out.withColumn("adjusted", F.least(F.lit(1.0), F.min(F.col(p) * F.col("__i")).over(Window.orderBy("__i").rowsBetween(Window.unboundedPreceding, 0)))).drop("__i")


def grade(tests: DataFrame, p: str = "adjusted") -> DataFrame:
    return tests.withColumn("grade", F.when(F.col(p) < 0.001, "***").when(F.col(p) < 0.01, "**").when(F.col(p) < 0.05, "*").otherwise(""))
