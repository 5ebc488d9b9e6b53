"""Corpus pipeline: quality, language, near duplicates, secrets, packing; each stage works on what the last one kept.

Each stage function takes (spark, docs, sf_dir) and returns a DataFrame, which is written and read again as the
next one's docs. All but the last return the columns of documents. Empty tables pass through; rows with null
or empty texts are rejected by the first stage.
"""

from __future__ import annotations

import public_tokenizers
from pyspark.sql import DataFrame, SparkSession

from boxsum.llm import language_id, packing, quality, secret_scan, simhash
from boxsum.llm.queries import BPE_JSON, BPE_RANKS, held_out
from boxsum.llm.shared import remove, shared_path, table

COLUMNS = ["doc_id", "text", "lang", "source", "n_chars"]


def by_quality(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that the co-trained classifier keeps; it learns from the table of labels."""
    model = quality.train(docs, table(spark, sf_dir, "labels"))
    return quality.keep_good(docs.select(COLUMNS), model)


def by_language(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents whose text is in the learned languages: enough of its own n-grams must be known. Counts and floors are of all texts that may be learned from."""
    learned = docs.where(~held_out())
    model = language_id.with_floors(language_id.train(learned, per_language=None), learned, per_language=None)
    return language_id.keep_identified(docs.select(COLUMNS), model)


def by_fingerprint(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document of each group of near duplicates, the one with the least id: sets of five-word shingles, similarity 0.8."""
    return simhash.drop_similar(docs.select(COLUMNS))


def without_secrets(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """All documents, the secrets in their texts replaced and n_chars brought up to date."""
    return secret_scan.redact(docs.select(COLUMNS), length_col="n_chars")


def packed(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """The pieces of all documents in their sequences."""
    return packing.pack(docs, BPE_RANKS, public_tokenizers.PATTERN, added=packing.added_tokens(BPE_JSON))


STAGES = [("quality", by_quality), ("language", by_language), ("near_duplicates", by_fingerprint), ("secrets", without_secrets), ("packing", packed)]
#: The stages' models and fingerprints can't be told in SQL.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The last stage's rows. What a stage wrote goes when the next one's rows are on storage."""
    docs, before = table(spark, sf_dir, "documents"), None
    for name, stage in STAGES:
        path = shared_path(spark, f"stage-{name}")
        stage(spark, docs, sf_dir).write.parquet(path)
        docs = spark.read.parquet(path)
        if before:
            remove(spark, before)
        before = path
    return docs
