"""The ten registered queries ``opN_*``: each applies its operator to its whole table and derives the digest columns."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import ann_tree, bpe_codec, exact_topk, language_id, line_dedup, mixing, pii, quality, simhash, token_counts, vectors
from .common import table

TOKENIZERS = None  # folder of the public vocabulary files; None: where the installed package keeps them


def tokenizer_path(name: str) -> str:
    if TOKENIZERS:
        return f"{TOKENIZERS}/{name}"
    import public_tokenizers

    return str(public_tokenizers.path(name))


def op1_bpe_codec(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents").select("doc_id", "text")
    coded = bpe_codec.encode_documents(docs, tokenizer_path("word_bpe_49k.json"))
    return coded.select("doc_id", (F.length("ids_le") / 4).cast("long").alias("n_tokens"), F.sha2("ids_le", 256).alias("ids_sha256"), F.sha2(F.encode("decoded", "UTF-8"), 256).alias("decoded_sha256"))


def op2_line_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents").select("doc_id", "text")
    return line_dedup.dedup_lines(docs).select("doc_id", "n_lines", "n_removed", "text")


def op3_exact_topk(spark: SparkSession, sf_dir: str) -> DataFrame:
    rows = vectors.usable(table(spark, sf_dir, "embeddings"))
    return exact_topk.exact_topk(rows, vectors.query_rows(rows, 50), k=5)


def op4_language_id(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents").select("doc_id", "text", "lang")
    held_out = F.coalesce(F.crc32(F.col("doc_id").cast("string")) % 3 == 1, F.lit(False))
    known = docs.where(F.crc32(F.col("doc_id").cast("string")) % 3 != 1)
    return language_id.predict(docs.select("doc_id", held_out.alias("held_out"), "text"), language_id.fit(known))


def op5_ann_tree(spark: SparkSession, sf_dir: str) -> DataFrame:
    rows = vectors.usable(table(spark, sf_dir, "embeddings")).where(F.exists("v", lambda x: x != 0))
    return ann_tree.nearest_neighbours(rows, vectors.query_rows(rows, 20), k=20)


def op6_token_counts(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents").select("doc_id", "text")
    return token_counts.count_tokens(docs, tokenizer_path("byte_bpe_50k.json"), limit=512)


def op7_simhash(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents").select("doc_id", "text")
    found, _, _ = simhash.near_duplicates(docs)
    return found.select("doc_id", F.lpad(F.lower(F.hex("fp")), 16, "0").alias("fingerprint"), "component_id")


def op8_source_mix(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents").select("doc_id", "source", "text")
    found, _, _ = mixing.mix(docs)
    return found.select("doc_id", "size", "source_size", "target", (F.col("size") * F.col("copies")).alias("taken"))


def op9_quality(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents").select("doc_id", "text")
    model = quality.fit(docs, quality.graded(table(spark, sf_dir, "labels")))
    return quality.rate(docs, model).select("doc_id", "expected_grade", "p_accept", "keep")


def op10_personal_data(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents").select("doc_id", "text")
    found = pii.find_personal_data(docs)
    line = lambda spans: F.array_join(F.transform(spans, lambda s: F.concat_ws(":", s["kind"], s["start"], s["end"])), ",")
    base = list(pii.KINDS[:4])
    of = lambda kind: F.filter("pii", lambda s: s["kind"] == kind)
    counts = [F.size(of(k)).cast("long").alias(f"n_{k}") for k in base]
    return found.select("doc_id", *counts, F.sha2(F.encode(line(F.filter("pii", lambda s: s["kind"].isin(base))), "UTF-8"), 256).alias("base_sha256"), line(F.col("pii")).alias("spans"), F.transform("pii", lambda s: s["score"]).alias("scores"))


QUERIES = {f.__name__: f for f in (op1_bpe_codec, op2_line_dedup, op3_exact_topk, op4_language_id, op5_ann_tree, op6_token_counts, op7_simhash, op8_source_mix, op9_quality, op10_personal_data)}

#: DuckDB SQL where it can express the operator.
ORACLE = {
    "op2_line_dedup": line_dedup.ORACLE,
    "op3_exact_topk": """
WITH v AS (SELECT vec_id, list_transform(embedding, lambda x: floor(256 * x::DOUBLE)::BIGINT) AS q FROM embeddings
           WHERE vec_id IS NOT NULL AND len(embedding) > 0 AND len(list_filter(embedding, lambda x: x IS NULL OR NOT isfinite(x))) = 0),
s AS (SELECT a.vec_id AS query_id, b.vec_id AS vec_id, list_sum(list_transform(list_zip(a.q, b.q), lambda p: p[1] * p[2]))::BIGINT AS score
      FROM v a JOIN v b ON a.vec_id % 50 = 0 AND a.vec_id <> b.vec_id)
SELECT query_id, rank::INTEGER AS rank, vec_id, score
FROM (SELECT *, row_number() OVER (PARTITION BY query_id ORDER BY score DESC, vec_id) AS rank FROM s) WHERE rank <= 5""",
}
