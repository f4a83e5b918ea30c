"""JSON notebooks: a deterministic builder over documents, a permissive parser, and readers and sinks around them."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .segment import table

#: Explicit schema: inference would be one more pass over the corpus.
SCHEMA = "metadata STRUCT<language_info: STRUCT<name: STRING>, language: STRING, kernelspec: STRUCT<language: STRING>>, cells ARRAY<STRUCT<cell_type: STRING, language: STRING, source: STRING>>, damaged STRING"
NAMES = {"en": "python3", "fr": "julia", "de": "R", "es": "scala-2.12"}


def raw_notebooks(spark: SparkSession, sf_dir: str) -> DataFrame:
    """``(nb_id, repo, is_fork, url, body)``: documents as JSON notebooks; the language sits in one of four places by ``doc_id % 10``.

    Every 50th names none, every 97th another language; some conflict (``% 41``), some mix cell
    languages (``% 43``) and some bodies are cut short (``% 71``).
    """
    d = table(spark, sf_dir, "documents")
    i = F.col("doc_id")
    name = F.when(i % 97 == 0, "rust").otherwise(F.element_at(F.create_map(*[F.lit(x) for kv in NAMES.items() for x in kv]), F.col("lang")))
    name = F.when(i % 50 == 0, F.lit(None)).otherwise(name)
    place = F.when(i % 10 < 6, 1).when(i % 10 == 6, 2).when(i % 10 == 7, 3).otherwise(4)
    first = F.when(place == 1, name)
    second = F.when(i % 41 == 0, F.lit("Fortran")).when(place == 2, name)
    third = F.when(place == 3, name)
    cell = lambda x, p: F.struct(F.lit("code").alias("cell_type"), F.when(place == 4, F.when((i % 43 == 0) & (p % 2 == 1), F.lit("ruby")).otherwise(name)).alias("language"), x.alias("source"))
    meta = F.struct(F.struct(first.alias("name")).alias("language_info"), second.alias("language"), F.struct(third.alias("language")).alias("kernelspec"))
    body = F.to_json(F.struct(meta.alias("metadata"), F.transform(F.split("text", "\n"), cell).alias("cells")))
    body = F.when(i % 71 == 0, F.substring(body, 1, 20)).otherwise(body)
    return d.select(i.alias("nb_id"), F.col("source").alias("repo"), (F.col("source") == "src19").alias("is_fork"), F.concat(F.lit("https://host.example/"), "source", F.lit("/"), i.cast("string")).alias("url"), body.alias("body"))


def parse(raw: DataFrame, body: str = "body") -> DataFrame:
    """``raw`` plus parsed ``n`` and ``readable``; a damaged body isolates itself instead of failing the job."""
    return raw.withColumn("n", F.from_json(body, SCHEMA, {"mode": "PERMISSIVE", "columnNameOfCorruptRecord": "damaged"})).withColumn("readable", F.col("n.damaged").isNull() & F.col("n.cells").isNotNull())


def parsed_cells(parsed: DataFrame) -> DataFrame:
    """Code cells of readable notebooks: ``(nb_id, repo, pos, cell_lang, code)``; unreadable ones count as without cells."""
    return parsed.where("readable").select("nb_id", "repo", F.posexplode("n.cells").alias("pos", "c")).where("c.cell_type = 'code'").select("nb_id", "repo", "pos", F.col("c.language").alias("cell_lang"), F.col("c.source").alias("code"))


def read_pair_lines(spark: SparkSession, path: str) -> DataFrame:
    return spark.read.text(path)


def sink_partitioned(cells: DataFrame, path: str, by: str = "lang") -> None:
    """Write cells partitioned by language, so that a later restriction prunes folders."""
    cells.repartition(by).write.mode("overwrite").partitionBy(by).parquet(path)


def sink_bucketed(cells: DataFrame, name: str, buckets: int = 8, by: str = "h") -> None:
    """Write cells bucketed and sorted by fingerprint: later groupings by it need no exchange."""
    cells.write.mode("overwrite").bucketBy(buckets, by).sortBy(by).saveAsTable(name)
