"""The corpus pipeline: language ID, near-dedup, repeated passages, decontamination, tokens.

Every stage takes (spark, docs, sf_dir) and works on all rows that the one before kept; ``run`` writes each stage's rows to the
shared folder and reads them again. The last stage returns token ids and digests, the others the columns of ``documents``.
"""

from __future__ import annotations

import public_tokenizers
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from setdiff.llm import bpe, decontaminate, langid, near_copies, suffix_dedup
from setdiff.llm.common import id_crc_mod, keep, stowed, table

RANKS = "byte_bpe_multi_50k.tiktoken"


def language_id(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Drops rows whose language can't be told: no letter, or two languages that fit about equally well."""
    model = langid.fit(docs, id_crc_mod("doc_id", 4) != 2)
    told = langid.identify(stowed(docs).withColumn("text", F.col("_row.text")), model)
    return told.where(f"lang_pred <> '{langid.UNDETERMINED}' and not lang_ambiguous").select("_row.*")


def simhash_near_dedup(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Keeps one row of each group of near copies (five-word shingles; candidates by SimHash, and by min-hash beyond its radius; similarity 0.8): the smallest doc_id, nulls last."""
    return near_copies.keep_one(docs, size=5, similarity=0.8)


def suffix_array_dedup(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Cuts out what repeats over 400 bytes or more or over more than 50 words; rows of which nothing is left go."""
    return suffix_dedup.clean_documents(docs, words=51)


def benchmark_decontamination(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Drops rows that hold a benchmark item (five-word shingles, similarity 0.8)."""
    return decontaminate.drop_leaks(docs, table(spark, sf_dir, "benchmark"), similarity=0.8)


def byte_bpe(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Token ids of every row, and the digests of ids and decoded bytes."""
    return bpe.encode_documents(docs, public_tokenizers.path(RANKS), public_tokenizers.PATTERN)


STAGES = [
    ("language_id", language_id),
    ("simhash_near_dedup", simhash_near_dedup),
    ("suffix_array_dedup", suffix_array_dedup),
    ("benchmark_decontamination", benchmark_decontamination),
    ("byte_bpe", byte_bpe),
]

#: Language models, fingerprints and merges are beyond SQL; tests hold each stage against brute force.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    for name, stage in STAGES:
        docs = keep(stage(spark, docs, sf_dir), name)
    return docs
