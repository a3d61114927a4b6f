"""The registered ``opN_`` queries and their SQL."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

import public_tokenizers
from overlapix.llm import byte_bpe, decontaminate, fm_quality, html_extract, lbl, nn_descent, pii, records, simhash, unigram_count

#: A text is predicted good at this score.
GOOD = 0.3


def _table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def op1_simhash_near_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Fingerprints and groups of ``documents``; null and empty texts have fingerprint zero and link like any other."""
    groups = simhash.near_duplicates(_table(spark, sf_dir, "documents"))
    return groups.select("doc_id", F.lower(F.lpad(F.hex("fp"), 16, "0")).alias("fingerprint"), "component_id")


def op2_html_extraction(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Main text of ``pages``; null html is empty and gives no text."""
    return html_extract.extract(_table(spark, sf_dir, "pages"))


def op3_token_counts(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Pieces of each text of ``documents``; null and empty texts have none."""
    return unigram_count.token_counts(_table(spark, sf_dir, "documents"), public_tokenizers.path("piece_bpe_32k.model"))


def op4_embedding_near_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Links and groups of ``embeddings``; vectors that are null, zero or not finite stay alone."""
    return nn_descent.near_duplicates(_table(spark, sf_dir, "embeddings"))


def op5_benchmark_decontamination(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Benchmark windows in ``documents``; null and empty texts have no words and are clean."""
    return decontaminate.contamination(_table(spark, sf_dir, "documents"), _table(spark, sf_dir, "benchmark"))


def op6_quality_classifier(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Quality scores of ``documents``; null and empty texts are scored too, null ids are not held out."""
    docs = _table(spark, sf_dir, "documents")
    model = fm_quality.train(docs, _table(spark, sf_dir, "labels"))
    held = F.coalesce(fm_quality.fold(F.col("doc_id"), 5) == 0, F.lit(False))
    return fm_quality.scored(docs, model).select("doc_id", held.alias("held_out"), "score", (F.col("score") >= GOOD).cast("int").alias("predicted"))


def op7_lm_scoring(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Model and base scores of ``documents``; null and empty texts are an end alone, null ids are learned from."""
    return lbl.language_model_scores(_table(spark, sf_dir, "documents"))


def op8_byte_bpe(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Token ids of ``documents`` and what they decode to; null and empty texts have none."""
    path, pattern = public_tokenizers.path("byte_bpe_multi_50k.tiktoken"), public_tokenizers.PATTERN
    done = byte_bpe.encode_and_decode(_table(spark, sf_dir, "documents"), path, pattern)
    return done.select("doc_id", (F.octet_length("ids") / 4).cast("bigint").alias("n_tokens"), F.sha2("ids", 256).alias("ids_sha256"), F.sha2("decoded", 256).alias("decoded_sha256"))


def op9_token_records(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Records of ``documents`` in id order, read back; null and empty texts are the end id alone."""
    manifest = records.write_records(_table(spark, sf_dir, "documents"), public_tokenizers.path("byte_bpe_50k.json"))
    return records.read_digests(manifest)


def op10_pii(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Personal data in ``documents``; null and empty texts have no span."""
    return pii.personal_data(_table(spark, sf_dir, "documents"))


QUERIES = {
    f.__name__: f
    for f in (
        op1_simhash_near_dedup, op2_html_extraction, op3_token_counts, op4_embedding_near_dedup, op5_benchmark_decontamination,
        op6_quality_classifier, op7_lm_scoring, op8_byte_bpe, op9_token_records, op10_pii,
    )
}

_OP5 = r"""
WITH iw AS (SELECT item_id, regexp_extract_all(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\x00-\x2F\x3A-\x60\x7B-\x7F]+') AS w FROM benchmark),
wins AS (SELECT DISTINCT item_id, least(len(w), 10) AS size, array_to_string(list_slice(w, s, s + least(len(w), 10) - 1), ' ') AS win
         FROM iw, LATERAL (SELECT unnest(generate_series(1, len(w) - least(len(w), 10) + 1)) AS s) WHERE len(w) > 0),
dw AS (SELECT doc_id, regexp_extract_all(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\x00-\x2F\x3A-\x60\x7B-\x7F]+') AS w FROM documents),
grams AS (SELECT doc_id, z.size, s, array_to_string(list_slice(w, s, s + z.size - 1), ' ') AS win
          FROM dw, (SELECT DISTINCT size FROM wins) z, LATERAL (SELECT unnest(generate_series(1, len(w) - z.size + 1)) AS s) WHERE len(w) >= z.size),
hits AS (SELECT doc_id, s, g.size, item_id FROM grams g JOIN wins USING (size, win)),
cover AS (SELECT doc_id, count(DISTINCT p) AS n_hit FROM (SELECT doc_id, unnest(generate_series(s, s + size - 1)) AS p FROM hits) GROUP BY doc_id),
names AS (SELECT doc_id, count(*) AS n_items, string_agg(i, ',' ORDER BY i) AS ids FROM (SELECT DISTINCT doc_id, CAST(item_id AS VARCHAR) AS i FROM hits) GROUP BY doc_id)
SELECT doc_id, CAST(len(w) AS BIGINT) AS n_words, CAST(coalesce(n_hit, 0) AS BIGINT) AS n_hit, CAST(coalesce(n_items, 0) AS BIGINT) AS n_items,
       sha256(coalesce(ids, '')) AS items_sha256, coalesce(n_hit, 0) > 0 AS contaminated
FROM dw LEFT JOIN cover USING (doc_id) LEFT JOIN names USING (doc_id)
"""

ORACLE_SQL = {"op5_benchmark_decontamination": _OP5}
