"""Connected components of an edge table by alternating large-star and small-star steps.

Each step sends every node's neighbours to the smallest one it knows; in
O(log n) rounds the edges become stars around the smallest node.  Nothing is
collected but two sums a round; lineage is cut by reliable checkpoints.  Edges
that do not settle within ``ROUNDS`` raise an error.
"""

from __future__ import annotations

import contextlib
import uuid

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..session import shared_dir

ROUNDS = 60
#: Spark's setting to remove an execution's shuffle files at its end, not when the driver next collects garbage.
FREE_SHUFFLES = "spark.sql.classic.shuffleDependency.fileCleanup.enabled"


def cut(df: DataFrame) -> DataFrame:
    """Cut the lineage: an eager reliable checkpoint in the shared folder."""
    shared_dir(df.sparkSession)
    return df.checkpoint(eager=True)


@contextlib.contextmanager
def shuffles_freed(spark: SparkSession):
    """What is shuffled for an execution in here leaves the disk at the execution's end."""
    before = spark.conf.get(FREE_SHUFFLES, "false")
    spark.conf.set(FREE_SHUFFLES, "true")
    try:
        yield
    finally:
        spark.conf.set(FREE_SHUFFLES, before)


def folder_for(spark: SparkSession, label: str) -> str:
    """A fresh place in the shared folder."""
    return f"{shared_dir(spark).rstrip('/')}/{label}_{uuid.uuid4().hex}"


def written(df: DataFrame, label: str, path: str | None = None, by: str | None = None) -> DataFrame:
    """A cut in Parquet: compressed, and readers take the columns they need. What was shuffled for it leaves the disk when it is written.

    ``by``: a last column whose values get a folder each.
    """
    spark, path = df.sparkSession, path or folder_for(df.sparkSession, label)
    with shuffles_freed(spark):
        df.write.option("compression", "zstd").option("parquet.dictionary.page.size", 8 << 20).parquet(path, partitionBy=by)
    return spark.read.schema(df.schema).parquet(path)


def sums(df: DataFrame, *columns) -> list[int]:
    """Sums of integer columns (0 for no rows)."""
    with shuffles_freed(df.sparkSession):
        return list(df.agg(*[F.coalesce(F.sum(c), F.lit(0)) for c in columns]).first())


def delete(spark: SparkSession, path: str) -> None:
    folder = spark._jvm.org.apache.hadoop.fs.Path(path)
    folder.getFileSystem(spark._jsc.hadoopConfiguration()).delete(folder, True)


def release(*frames: DataFrame) -> None:
    """Delete the folders of ``written`` frames (and unions of such) that nothing reads any more."""
    for df in frames:
        for folder in {file.rsplit("/", 1)[0] for file in df.inputFiles()}:
            delete(df.sparkSession, folder)


def _least(pairs: DataFrame) -> DataFrame:
    """For each ``u`` the least of itself and its neighbours, beside every neighbour (aggregate, then join: hot nodes can be split)."""
    least = pairs.groupBy("u").agg(F.least(F.min("v"), F.col("u")).alias("m"))
    return pairs.join(least, "u")


def _large_star(edges: DataFrame) -> DataFrame:
    both = edges.select("u", "v").union(edges.select(F.col("v").alias("u"), F.col("u").alias("v")))
    return _least(both).where("v > u").select(F.col("v").alias("u"), F.col("m").alias("v"))


def _small_star(edges: DataFrame) -> DataFrame:
    down = edges.select(F.greatest("u", "v").alias("u"), F.least("u", "v").alias("v"))
    linked = _least(down)
    return linked.select(F.col("v").alias("u"), F.col("m").alias("v")).union(linked.select("u", F.col("m").alias("v"))).where("u <> v").distinct()


def components(edges: DataFrame, a: str = "a", b: str = "b") -> DataFrame:
    """``(node, root)`` for every node of an edge; ``root`` is the component's smallest node."""
    now = cut(edges.where(F.col(a) != F.col(b)).select(F.greatest(a, b).alias("u"), F.least(a, b).alias("v")).distinct())
    seen = None
    for _ in range(ROUNDS):
        now = cut(_small_star(_large_star(now)))
        state = tuple(now.agg(F.count("*"), F.sum(F.xxhash64("u", "v").cast("decimal(38,0)"))).first())
        if state == seen:
            break
        seen = state
    else:
        raise RuntimeError(f"components did not settle in {ROUNDS} rounds")
    stars = now.select(F.col("u").alias("node"), F.col("v").alias("root"))
    return stars.union(stars.select(F.col("root").alias("node"), "root").distinct())
