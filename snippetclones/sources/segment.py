"""Segmenters: how each table becomes canonical cells ``(nb_id, repo, lang, pos, code, loc)``."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..functions import normalize as N

CELL = ["nb_id", "repo", "lang", "pos", "code", "loc"]


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def notebooks(spark: SparkSession, sf_dir: str) -> DataFrame:
    return table(spark, sf_dir, "documents").select(F.col("doc_id").alias("nb_id"), F.col("source").alias("repo"), "lang")


def doc_lines(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Every line of a document is a cell; its size is its number of sentences."""
    d = table(spark, sf_dir, "documents")
    return d.select(F.col("doc_id").alias("nb_id"), F.col("source").alias("repo"), "lang", F.posexplode(F.split("text", "\n")).alias("pos", "code")).withColumn("loc", N.sentences(F.col("code")))


def doc_blocks(spark: SparkSession, sf_dir: str, k: int = 3) -> DataFrame:
    """Cells of k consecutive lines, in one narrow projection."""
    d = table(spark, sf_dir, "documents").withColumn("s", F.split("text", "\n"))
    blocks = F.transform(F.sequence(F.lit(0), F.floor((F.size("s") - 1) / k).cast("int")), lambda b: F.array_join(F.slice("s", b * k + 1, k), "\n"))
    return d.select(F.col("doc_id").alias("nb_id"), F.col("source").alias("repo"), "lang", F.posexplode(blocks).alias("pos", "code")).withColumn("loc", N.newline_loc(F.col("code")))


def doc_whole(spark: SparkSession, sf_dir: str) -> DataFrame:
    d = table(spark, sf_dir, "documents")
    return d.select(F.col("doc_id").alias("nb_id"), F.col("source").alias("repo"), "lang", F.lit(0).alias("pos"), F.col("text").alias("code")).withColumn("loc", N.newline_loc(F.col("code")))


def turns(spark: SparkSession, sf_dir: str) -> DataFrame:
    c = table(spark, sf_dir, "conversations")
    return c.select(F.col("conv_id").alias("nb_id"), F.concat(F.lit("r"), (F.col("conv_id") % 10).cast("string")).alias("repo"), F.lit("chat").alias("lang"), F.col("turn").cast("int").alias("pos"), F.col("text").alias("code")).withColumn("loc", N.newline_loc(F.col("code")))


def page_host(url):
    """Host without a leading www. or m."""
    return F.regexp_replace(F.regexp_extract(F.lower(url), r"^[a-z]+://([^/?#:]+)", 1), r"^(www|m)\.", "")


def page_blocks(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Paragraph, list-item and heading bodies in page order."""
    p = table(spark, sf_dir, "pages")
    bodies = F.regexp_extract_all("html", F.lit(r"<(?:p|li|h1)[^>]*>([^<]*)<"), F.lit(1))
    return p.select(F.col("page_id").alias("nb_id"), page_host(F.col("url")).alias("repo"), F.regexp_extract("html", r'<html[^>]*lang="([a-z]+)', 1).alias("lang"), F.posexplode(bodies).alias("pos", "code")).withColumn("loc", F.lit(1))


def page_notebooks(spark: SparkSession, sf_dir: str) -> DataFrame:
    return table(spark, sf_dir, "pages").select(F.col("page_id").alias("nb_id"), page_host(F.col("url")).alias("repo"), F.regexp_extract("html", r'<html[^>]*lang="([a-z]+)', 1).alias("lang"))


def order_notebooks(spark: SparkSession, sf_dir: str) -> DataFrame:
    o, c = table(spark, sf_dir, "orders"), table(spark, sf_dir, "customer")
    return o.join(c, o["o_custkey"] == c["c_custkey"]).select(F.col("o_orderkey").alias("nb_id"), F.col("o_custkey").cast("string").alias("repo"), F.col("c_mktsegment").alias("lang"))


def benchmark_lines(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Lines of the benchmark's passages as template cells; their notebooks have negative numbers."""
    b = table(spark, sf_dir, "benchmark")
    cells = b.select((-F.col("item_id") - 1).alias("nb_id"), F.lit("benchmark").alias("repo"), F.lit("en").alias("lang"), F.posexplode(F.split("text", "\n")).alias("pos", "code"))
    return cells.withColumn("loc", N.sentences(F.col("code")))


def order_lines(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Order lines as cells; line numbers repeat within an order, so the order has tie-breakers."""
    o, l, c = (table(spark, sf_dir, t) for t in ("orders", "lineitem", "customer"))
    own = o.join(c, o["o_custkey"] == c["c_custkey"]).select("o_orderkey", "o_custkey", "c_mktsegment")
    cells = l.select("l_orderkey", "l_linenumber", "l_partkey", "l_suppkey", "l_quantity", F.concat_ws("#", F.col("l_partkey").cast("string"), F.col("l_quantity").cast("long").cast("string")).alias("code"))
    rows = cells.join(own, cells["l_orderkey"] == own["o_orderkey"])
    return rows.select(F.col("l_orderkey").alias("nb_id"), F.col("o_custkey").cast("string").alias("repo"), F.col("c_mktsegment").alias("lang"), F.col("l_linenumber").alias("pos"), "code", F.lit(1).alias("loc"))


def event_sessions(spark: SparkSession, sf_dir: str, gap_minutes: int = 30) -> DataFrame:
    """Events of a user without a longer gap form a notebook."""
    e = table(spark, sf_dir, "events")
    w = Window.partitionBy("user_id").orderBy("ts", "event_id")
    fresh = F.coalesce((F.unix_micros(F.col("ts").cast("timestamp")) - F.lag(F.unix_micros(F.col("ts").cast("timestamp"))).over(w)) > gap_minutes * 60_000_000, F.lit(True))
    marked = e.withColumn("s", F.sum(fresh.cast("int")).over(w))
    inside = Window.partitionBy("user_id", "s").orderBy("ts", "event_id")
    return marked.select((F.col("user_id") * 1_000_000 + F.col("s")).alias("nb_id"), F.col("user_id").cast("string").alias("repo"), F.first("event_type").over(inside).alias("lang"), (F.row_number().over(inside) - 1).alias("pos"), F.concat_ws("#", "event_type", "props").alias("code"), F.lit(1).alias("loc"))
