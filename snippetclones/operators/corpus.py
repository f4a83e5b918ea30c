"""Acquisition funnel, exclusion, reload, sizes, sampling and selection bias."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import cmw


def canonical_url(url):
    """Lower-case scheme and host, no www./m., default port, fragment or trailing slash."""
    u = F.regexp_replace(F.trim(url), r"#.*$", "")
    host = F.lower(F.regexp_extract(u, r"^([A-Za-z]+://[^/?]*)", 1))
    rest = F.regexp_replace(F.regexp_replace(u, r"^[A-Za-z]+://[^/?]*", ""), r"/+$", "")
    host = F.regexp_replace(F.regexp_replace(host, r"^https?://(www\.|m\.)?", "https://"), r":(80|443)$", "")
    return F.concat(host, rest)


def exclude_forks(notebooks: DataFrame, forks: DataFrame) -> DataFrame:
    """Anti-join with the flagged projects; the planner broadcasts them only where they are small."""
    return notebooks.join(forks.select("repo").distinct(), "repo", "left_anti")


def reload(base: DataFrame, damaged: DataFrame, refetch: DataFrame) -> DataFrame:
    """Damaged records take their second copy where there is one: ``(nb_id, body, state)``."""
    b = base.join(damaged.select("nb_id", F.lit(True).alias("bad")), "nb_id", "left").join(refetch.select("nb_id", F.col("body").alias("again")), "nb_id", "left")
    state = F.when(F.col("bad").isNull(), "intact").when(F.col("again").isNotNull(), "obtained").otherwise("lost")
    return b.select("nb_id", F.when(F.col("bad").isNull(), F.col("body")).otherwise(F.col("again")).alias("body"), state.alias("state"))


def sizes(notebooks: DataFrame, cells: DataFrame) -> DataFrame:
    """``(nb_id, bytes, n_cells, loc_nb, loc_all)`` of each notebook, cells of newline-separated code; 0 without cells."""
    code = F.col("code")
    per = cells.groupBy("nb_id").agg(F.sum(F.octet_length(code)).alias("bytes"), F.count("*").alias("n_cells"), F.sum(F.size(F.filter(F.split(code, "\n"), lambda x: F.regexp_replace(x, r"[ \t\r\f\x0B]+", "") != ""))).alias("loc_nb"), F.sum(F.size(F.split(code, "\n"))).alias("loc_all"))
    return notebooks.select("nb_id").join(per, "nb_id", "left").na.fill(0)


def totals(sizes_df: DataFrame) -> DataFrame:
    return sizes_df.agg(F.count("*").alias("notebooks"), F.sum("n_cells").alias("cells"), F.sum("loc_nb").alias("loc_nb"), F.sum("loc_all").alias("loc_all"), F.sum("bytes").alias("bytes"))


def sample_repositories(notebooks: DataFrame, n_repo: int, per_repo: int, seed: str = "7") -> DataFrame:
    """Random repositories, then random notebooks in each, both by seeded MD5 so that reruns and SQL agree."""
    from pyspark.sql import Window

    key = lambda *c: F.md5(F.concat_ws("|", F.lit(seed), *c))
    repos = notebooks.select("repo").distinct().orderBy(key("repo")).limit(n_repo)
    inside = notebooks.join(F.broadcast(repos), "repo")  # n_repo rows
    place = F.row_number().over(Window.partitionBy("repo").orderBy(key(F.col("nb_id").cast("string"))))
    return inside.withColumn("k", place).where(F.col("k") <= per_repo).drop("k")


def selection_bias(cells: DataFrame, subsets: dict[str, DataFrame]) -> DataFrame:
    """Clone ratio within each criterion's notebooks (a frame of nb_id), one row a criterion."""
    out = None
    for name, chosen in subsets.items():
        part = cmw.totals(cmw.non_empty(cells.join(chosen.select("nb_id").distinct(), "nb_id", "left_semi"))).select(F.lit(name).alias("criterion"), "clones", "uniques", "ratio")
        out = part if out is None else out.union(part)
    return out
