"""Copy-modulo-white-space clones: fingerprints, groups, flags, cloned notebooks.

``counts(nb_id, repo, h, n)`` is the workhorse: cells collapsed per notebook before
any join, so that a giant group (the empty cell, one import line) is summed map-side.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..functions import normalize as N


def hashed(cells: DataFrame, algo: str = "md5", unicode_ws: bool = False) -> DataFrame:
    """Cells plus the normal form ``n`` and the fingerprint ``h``."""
    c = cells.withColumn("n", N.strip_ws(F.col("code"), unicode_ws))
    return c.withColumn("h", {"md5": lambda: F.md5("n"), "sha2": lambda: F.sha2("n", 256), "xxhash64": lambda: F.concat_ws(":", F.xxhash64("n"), F.length("n"))}[algo]())


def non_empty(cells: DataFrame) -> DataFrame:
    """Hashed cells that hold something besides white space; the test runs before hashing."""
    return hashed(cells.where(F.col("code").rlike(r"[^ \t\n\r\f\x0B]")))


def groups(ne: DataFrame) -> DataFrame:
    """``(h, size, n_nb, n_repo, median_loc, sample)`` of every fingerprint.

    Three partial aggregations instead of one multi-distinct: by (h, loc), (h, nb) and (h, repo)
    the rows shrink before the final step on h, so one hot fingerprint never fills a task.
    """
    by_loc = ne.groupBy("h", "loc").agg(F.count("*").alias("c"), F.min("code").alias("sample"))
    by_loc = by_loc.groupBy("h").agg(F.sum("c").alias("size"), F.floor(F.percentile("loc", 0.5, F.col("c"))).cast("int").alias("median_loc"), F.min("sample").alias("sample"))
    spread = ne.select("h", "nb_id", "repo").distinct()
    spread = spread.groupBy("h", "repo").agg(F.count("*").alias("nb")).groupBy("h").agg(F.sum("nb").alias("n_nb"), F.count("*").alias("n_repo"))
    return by_loc.join(spread, "h").select("h", "size", "n_nb", "n_repo", "median_loc", "sample")


def counts(ne: DataFrame) -> DataFrame:
    return ne.groupBy("nb_id", "repo", "h").agg(F.count("*").alias("n"))


def flags(ne: DataFrame, strategy: str = "agg_join") -> DataFrame:
    """Each non-empty cell with its group ``size`` and ``is_clone``; the window form is the reference for small data."""
    if strategy == "window":
        out = ne.withColumn("size", F.count("*").over(Window.partitionBy("h")))
    else:
        out = ne.join(ne.groupBy("h").agg(F.count("*").alias("size")), "h")
    return out.withColumn("is_clone", F.col("size") >= 2)


def totals(ne: DataFrame) -> DataFrame:
    """Clones, clone groups, unique snippets and the clone ratio."""
    s = ne.groupBy("h").agg(F.count("*").alias("s"))
    out = s.agg(F.coalesce(F.sum(F.when(F.col("s") > 1, F.col("s"))), F.lit(0)).alias("clones"), F.count_if(F.col("s") > 1).alias("groups"), F.count_if(F.col("s") == 1).alias("uniques"))
    return out.withColumn("ratio", F.try_divide(F.col("clones"), F.col("clones") + F.col("uniques")))


def self_clones(ne: DataFrame) -> DataFrame:
    """Notebooks that hold some non-empty snippet twice."""
    return counts(ne).where("n >= 2").select("nb_id").distinct()


def notebook_fingerprints(cells: DataFrame, keep_empty: bool = True, min_cells: int = 1) -> DataFrame:
    """Ordered fingerprint of each notebook's cells (ties of pos by fingerprint)."""
    h = hashed(cells) if keep_empty else non_empty(cells)
    lists = h.groupBy("nb_id").agg(F.array_sort(F.collect_list(F.struct("pos", "h"))).alias("hs"))
    return lists.where(F.size("hs") >= min_cells).select("nb_id", F.md5(F.array_join(F.transform("hs", lambda x: x["h"]), ",")).alias("fp"), F.size("hs").alias("n_cells"))


def notebook_clones(fingerprints: DataFrame) -> DataFrame:
    """Groups of cloned notebooks: ``(fp, size, first_nb)``."""
    return fingerprints.groupBy("fp").agg(F.count("*").alias("size"), F.min("nb_id").alias("first_nb")).where("size >= 2")
