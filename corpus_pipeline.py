"""A training corpus from raw documents, in five stages.

Each stage takes what the one before kept, written as Parquet and read again.
"""

from __future__ import annotations

import public_tokenizers
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from overlapix.llm import byte_bpe, decontaminate, fm_quality, pii, simhash
from overlapix.llm.queries import GOOD
from overlapix.llm.storage import materialise

#: SQL has no factorisation machine, fingerprint hash, span classifier or tokenizer.
ORACLE_SQL = None


def _resized(before: DataFrame, after: DataFrame) -> DataFrame:
    """``after`` with the columns of ``before`` and ``n_chars`` of the texts as they are now."""
    if "n_chars" in before.columns:
        after = after.withColumn("n_chars", F.coalesce(F.length("text"), F.lit(0)).cast(before.schema["n_chars"].dataType))
    return after.select(*before.columns)


def quality(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that the factorisation machine scores as good.

    Null and empty texts are scored like any other; rows that repeat and null ids
    are judged row by row; an empty table stays empty.
    """
    model = fm_quality.train(docs, spark.read.parquet(f"{sf_dir}/labels.parquet"))
    return fm_quality.scored(docs, model, tuple(docs.columns), name="__score").where(F.col("__score") >= GOOD).select(*docs.columns)


def near_dedup(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document, that of the least id, of each group of near copies: sets of
    five-word shingles 0.8 alike, found by SimHash.

    Null and empty texts are copies of each other; of rows that repeat an id one
    stays; rows with a null id all stay; an empty table stays empty.
    """
    return simhash.keep_similar_groups(docs)


def decontamination(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Texts without benchmark windows; a text that was nothing else goes.

    Null and empty texts, null ids and rows that repeat stay as they are; an empty
    table or benchmark changes nothing.
    """
    cleaned = decontaminate.remove_spans(docs, spark.read.parquet(f"{sf_dir}/benchmark.parquet"))
    return _resized(docs, cleaned)


def personal_data(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Texts with marks in place of personal data, keys and tokens.

    Null and empty texts stay as they are, and so do null ids and rows that repeat;
    spans that overlap give one mark, that of the first.
    """
    return _resized(docs, pii.redact(docs))


def byte_level_bpe(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Token ids of each text, and whether decoding gives its bytes back.

    Null texts have no ids, like empty ones; null ids and rows that repeat stay.
    """
    path, pattern = public_tokenizers.path("byte_bpe_multi_50k.tiktoken"), public_tokenizers.PATTERN
    done = byte_bpe.encode_and_decode(docs, path, pattern, keep=("doc_id", "lang", "source"))
    return done.select("doc_id", "lang", "source", (F.octet_length("ids") / 4).cast("bigint").alias("n_tokens"), "ids", "round_trip")


STAGES = [("quality classifier", quality), ("SimHash near-dedup", near_dedup), ("benchmark decontamination", decontamination), ("PII", personal_data), ("byte-level BPE", byte_level_bpe)]


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All stages over ``documents``, each written and read again."""
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    for name, stage in STAGES:
        docs = stage(spark, docs, sf_dir)
        if name != STAGES[-1][0]:
            docs = materialise(docs, "stage")
    return docs
