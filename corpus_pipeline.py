"""A training-corpus pipeline in five stages, each one operator of ``snippetclones.llm`` over all that its predecessor kept.

``STAGES`` lists ``(name, function)``; a function takes ``(spark, docs, sf_dir)``
and returns a DataFrame, which is written as Parquet and read again as the next
one's ``docs``.  All stages but the last return the columns of ``documents``.

Edge cases, in every stage: null and empty texts stay documents (the classifier
rates them by its thresholds, one of them stays as near duplicate of the others,
and the mix takes no document without a word); ties go to the smaller doc_id, a
null doc_id counts as the largest; rows that repeat a doc_id are documents of
their own; an empty table gives an empty result with the same columns.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from snippetclones.llm import bpe_codec, line_dedup, mixing, quality, simhash
from snippetclones.llm.common import named, release, table, written
from snippetclones.llm.queries import tokenizer_path

#: Near duplicates: five-word shingles with a similarity of 0.8 or more, every such pair; those within 7 bits by fingerprints of distinct words, the rest by a prefix join.
NEAR = {"radius": 7, "segments": 4, "features": "distinct", "verify": (5, 0.8)}


def quality_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that the ordinal classifier rejects go."""
    grades = quality.graded(table(spark, sf_dir, "labels"))
    return quality.rate(docs, quality.fit(docs, grades)).where("keep").select(*map(named, docs.columns))


def line_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Later copies of repeated line runs are deleted from the texts; every document stays, and n_chars follows its text."""
    left = line_dedup.dedup_lines(docs)
    return left.select(*[F.coalesce(F.length("text"), F.lit(0)).cast(docs.schema[c].dataType).alias(c) if c == "n_chars" else named(c) for c in docs.columns])


def near_duplicate_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document of each near-duplicate group stays."""
    return simhash.drop_near_duplicates(docs, **NEAR)


def mixing_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Sources are brought to their target weights; a document appears as often as it is taken."""
    return mixing.mixed_documents(docs)


def encoding_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Each document's packed token ids (little-endian unsigned 32-bit) and their number."""
    coded = bpe_codec.encode_documents(docs.select("doc_id", "source", "lang", "text"), tokenizer_path("word_bpe_49k.json"))
    return coded.select("doc_id", "source", "lang", (F.length("ids_le") / 4).cast("long").alias("n_tokens"), "ids_le")


STAGES = [
    ("quality classifier", quality_stage),
    ("line dedup", line_stage),
    ("SimHash near-dedup", near_duplicate_stage),
    ("mixing sources to target weights", mixing_stage),
    ("BPE encoding and decoding", encoding_stage),
]

#: Fingerprints, fitted weights and the tokenizer can't be expressed in SQL; tests hold the stages against brute force.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    for at, (name, stage) in enumerate(STAGES[:-1]):
        before, docs = docs, written(stage(spark, docs, sf_dir), name)
        if at:
            release(before)  # the tables are the user's; a stage's output is read by the next stage only
    return STAGES[-1][1](spark, docs, sf_dir)
