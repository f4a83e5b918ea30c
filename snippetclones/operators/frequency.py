"""Clone frequency of notebooks and its extremes."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F


def per_notebook(notebooks: DataFrame, flags: DataFrame, empty: str = "zero") -> DataFrame:
    """``(nb_id, repo, lang, cells, cloned, freq)``; notebooks without snippets get 0 or null."""
    agg = flags.groupBy("nb_id").agg(F.count("*").alias("cells"), F.count_if("is_clone").alias("cloned"))
    out = notebooks.join(agg, "nb_id", "left").na.fill(0, ["cells", "cloned"])
    freq = F.try_divide(F.col("cloned"), F.col("cells"))
    return out.withColumn("freq", F.coalesce(freq, F.lit(0.0)) if empty == "zero" else freq)


def extremes(freq: DataFrame) -> DataFrame:
    """Notebooks with only cloned and with only unique snippets, and their shares of all notebooks."""
    return freq.agg(F.count("*").alias("notebooks"), F.count_if((F.col("cells") > 0) & (F.col("cloned") == F.col("cells"))).alias("all_cloned"), F.count_if((F.col("cells") > 0) & (F.col("cloned") == 0)).alias("all_unique")).withColumn("cloned_share", F.col("all_cloned") / F.col("notebooks")).withColumn("unique_share", F.col("all_unique") / F.col("notebooks"))
