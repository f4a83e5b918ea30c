"""Connections between notebooks, by counting - the pair graph is never built.

For a notebook with n cells of a group of size s, of which r lie in its own
repository: edges n(s-n) + n(n-1)/2 (or endpoints n(s-1)), within the
repository the same with r for s, to other repositories n(s-r).
"""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .components import written


def _with_sizes(counts: DataFrame) -> DataFrame:
    by_repo = counts.groupBy("h", "repo").agg(F.sum("n").alias("r"))
    sizes = by_repo.groupBy("h").agg(F.sum("r").alias("s"))
    return counts.join(by_repo, ["h", "repo"]).join(sizes, "h")


def per_notebook(notebooks: DataFrame, counts: DataFrame, self_loop: str = "edge") -> DataFrame:
    """``(nb_id, repo, cells, edge, norm, c0, sc)``; notebooks without snippets get zeros."""
    n, s, r = F.col("n"), F.col("s"), F.col("r")
    loops = n * (n - 1)
    own = F.floor(loops / 2).cast("long") if self_loop == "edge" else loops
    agg = _with_sizes(counts).groupBy("nb_id").agg(F.sum(n).alias("cells"), F.sum(n * (s - n) + own).alias("edge"), F.sum(n * (r - n) + own).alias("c0"), F.sum(n * (s - r)).alias("sc"))
    out = notebooks.select("nb_id", "repo").join(agg, "nb_id", "left").na.fill(0, ["cells", "edge", "c0", "sc"])
    return out.withColumn("norm", F.coalesce(F.try_divide(F.col("edge"), F.col("cells")), F.lit(0.0)))


def per_repository(counts: DataFrame) -> DataFrame:
    """``(nb_id, repo, other, c)``: connections of each notebook to each repository it is connected with (own loops as edges).

    The result itself has a row for each notebook and partner; ``partners`` counts them without it.
    """
    by_repo = counts.groupBy("h", "repo").agg(F.sum("n").alias("r")).withColumnRenamed("repo", "other")
    joined = counts.join(by_repo, "h")
    n, r = F.col("n"), F.col("r")
    c = F.when(F.col("repo") == F.col("other"), n * (r - n) + F.floor(n * (n - 1) / 2)).otherwise(n * r)
    return joined.groupBy("nb_id", "repo", "other").agg(F.sum(c).cast("long").alias("c")).where("c > 0")


#: Repositories of a fingerprint that are listed one by one; more are kept as bitmaps.
LISTED = 64


def partners(counts: DataFrame, holders: DataFrame | None = None) -> DataFrame:
    """``(nb_id, m)``: the number of other repositories that each notebook is connected with, exactly.

    ``holders(h, other)``: the repositories behind each fingerprint, the notebook's own included; by default those that hold it.
    Repositories get dense numbers.  A fingerprint of few repositories lists them; one of many holds a bitmap
    (one bit a repository), and notebooks unite bitmaps, so a hot fingerprint costs each of its notebooks a
    bitmap and not a row for each repository.
    """
    if holders is None:
        holders = counts.select("h", F.col("repo").alias("other")).distinct()
    numbers = holders.select("other").distinct().select("other", F.row_number().over(Window.orderBy("other")).cast("long").alias("id"))  # as many rows as repositories
    known = holders.join(numbers, "other").select("h", "id")
    known = known.join(known.groupBy("h").agg(F.count("*").alias("k")), "h")
    few = known.where(F.col("k") <= LISTED).groupBy("h").agg(F.collect_list("id").alias("ids"))
    place, bit = F.bitmap_bucket_number("id"), F.bitmap_bit_position("id")
    many = known.where(F.col("k") > LISTED).groupBy("h", place.alias("bucket")).agg(F.bitmap_construct_agg(bit).alias("bits"))
    wide = counts.select("nb_id", "h").join(many, "h").select("nb_id", "bucket", "bits")
    hot = wide.select("nb_id").distinct().withColumn("hot", F.lit(True))
    listed = counts.select("nb_id", "h").join(few, "h").select("nb_id", F.explode("ids").alias("id")).distinct().join(hot, "nb_id", "left")
    plain = listed.where("hot IS NULL").groupBy("nb_id").agg((F.count("*") - 1).alias("m"))
    bits = listed.where("hot").groupBy("nb_id", place.alias("bucket")).agg(F.bitmap_construct_agg(bit).alias("bits")).union(wide)
    united = bits.groupBy("nb_id", "bucket").agg(F.bitmap_or_agg("bits").alias("bits")).groupBy("nb_id").agg((F.sum(F.bitmap_count("bits")) - 1).alias("m"))
    return plain.union(united)


def inter_mean(conn: DataFrame, partners: DataFrame) -> DataFrame:
    """``conn`` plus ``m``, the number of other repositories connected, and ``ic`` = sc / m (0 without any)."""
    return conn.join(partners, "nb_id", "left").na.fill(0, ["m"]).withColumn("ic", F.coalesce(F.try_divide(F.col("sc"), F.col("m")), F.lit(0.0)))


def inter_mean_sketched(conn: DataFrame, counts: DataFrame) -> DataFrame:
    """The same with a sketch of repositories per fingerprint united per notebook: no notebook-by-repository table."""
    sketch = counts.groupBy("h").agg(F.hll_sketch_agg("repo").alias("k"))
    m = counts.join(sketch, "h").groupBy("nb_id").agg(F.hll_sketch_estimate(F.hll_union_agg("k")).alias("repos"))
    out = conn.join(m, "nb_id", "left").withColumn("m", F.greatest(F.coalesce("repos", F.lit(1)) - 1, F.lit(0)))
    return out.withColumn("ic", F.when(F.col("m") > 0, F.col("sc") / F.col("m")).otherwise(0.0)).drop("repos")


def strongest(vector: DataFrame) -> DataFrame:
    """Each notebook's single strongest partner repository and whether it is its own."""
    top = F.row_number().over(Window.partitionBy("nb_id").orderBy(F.desc("c"), "other"))
    return vector.withColumn("k", top).where("k = 1").select("nb_id", "repo", "other", "c", (F.col("repo") == F.col("other")).alias("is_own"))


def explain(counts: DataFrame, top_notebook: DataFrame) -> DataFrame:
    """The groups that make the edges of one notebook (a one-row frame)."""
    n, s = F.col("n"), F.col("s")
    mine = _with_sizes(counts).join(F.broadcast(top_notebook.select("nb_id")), "nb_id")
    return mine.select("nb_id", "h", "n", "s", (n * (s - n) + F.floor(n * (n - 1) / 2)).cast("long").alias("edges"))


def edge_list(ne: DataFrame) -> DataFrame:
    """Reference for small data: every clone pair of cells as an edge between notebooks."""
    k = ne.select("h", "nb_id", "repo", F.struct("nb_id", "pos").alias("cell"))
    a, b = k.alias("a"), k.alias("b")
    return a.join(b, (F.col("a.h") == F.col("b.h")) & (F.col("a.cell") < F.col("b.cell"))).select(F.col("a.nb_id").alias("x"), F.col("b.nb_id").alias("y"), F.col("a.repo").alias("rx"), F.col("b.repo").alias("ry"))


def around(pairs: DataFrame, bag_counts: DataFrame) -> DataFrame:
    """``(bag_id, repo, r)``: cells of each repository that hold a bag or a neighbour of it.

    Sums over neighbours are made once a bag and repository, not once for each notebook that holds the bag.
    """
    repo = bag_counts.groupBy("bag_id", "repo").agg(F.sum("n").alias("r"))
    ends = pairs.select("a", "b").union(pairs.select("b", "a"))
    return ends.join(repo.toDF("b", "repo", "r"), "b").select(F.col("a").alias("bag_id"), "repo", "r").union(repo).groupBy("bag_id", "repo").agg(F.sum("r").alias("r"))


def links_inside(pairs: DataFrame, bag_counts: DataFrame) -> DataFrame:
    """``(nb_id, n, m)``: pairs with both bags in a notebook, and their cells there; the notebooks of a pair's rarer bag are looked through."""
    held = bag_counts.groupBy("bag_id").agg(F.count("*").alias("k"))
    known = pairs.select("a", "b").join(held.toDF("a", "ka"), "a").join(held.toDF("b", "kb"), "b")
    rare = F.col("ka") <= F.col("kb")
    ends = known.select(F.when(rare, F.col("a")).otherwise(F.col("b")).alias("a"), F.when(rare, F.col("b")).otherwise(F.col("a")).alias("b"))
    mine = bag_counts.select("nb_id", F.col("bag_id").alias("b"), F.col("n").alias("m"))
    return ends.join(bag_counts.select("nb_id", F.col("bag_id").alias("a"), "n"), "a").join(mine, ["nb_id", "b"]).select("nb_id", "n", "m")


def near_miss(pairs: DataFrame, bag_counts: DataFrame, near: DataFrame) -> DataFrame:
    """Connections over near-miss edges from adjacency and bag counts: ``(nb_id, repo, cells, edge, c0, sc)``.

    ``near``: ``around`` of both.  With a(b) = b and its neighbours: endpoints P = sum over own bags of n_b times the sum over a(b)
    of S, minus own cells; W is the same inside the notebook, and edges are P - W/2.
    """
    full = bag_counts.join(near.groupBy("bag_id").agg(F.sum("r").alias("s")), "bag_id").join(near, ["bag_id", "repo"], "left")
    inside = written(links_inside(pairs, bag_counts).groupBy("nb_id").agg((2 * F.sum(F.col("n") * F.col("m"))).alias("linked")), "inside")
    z = lambda c: F.coalesce(F.col(c), F.lit(0))
    cells = bag_counts.groupBy("nb_id").agg(F.sum("n").alias("cells"), F.sum(F.col("n") * F.col("n")).alias("same"))
    p = full.groupBy("nb_id", "repo").agg(F.sum(F.col("n") * F.col("s")).alias("p"), F.sum(F.col("n") * z("r")).alias("p0"))
    p = p.join(inside, "nb_id", "left").withColumn("linked", z("linked"))
    p = p.join(cells, "nb_id").withColumn("w", F.col("same") + F.col("linked"))
    half = F.floor((F.col("w") - F.col("cells")) / 2)
    return p.select("nb_id", "repo", "cells", (F.col("p") - F.col("cells") - half).cast("long").alias("edge"), (F.col("p0") - F.col("cells") - half).cast("long").alias("c0"), (F.col("p") - F.col("p0")).cast("long").alias("sc"))
