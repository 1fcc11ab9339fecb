"""Corpus pipeline: language, toxicity, near-duplicates, decontamination, tokens.

Each stage takes the rows its predecessor kept, as a written table, and drops what it rejects; all but
the last return the columns of documents.

Defined results: null texts and texts without a letter go with the first stage; a document of several
labels is toxic for the fit if one says so. Rows are judged by themselves: rows that repeat an id but not
a text, and rows without an id, each stay or go by their own text; of rows equal in id and text one stays.
Of each near-duplicate group the row of least id stays, then of least text hash.
An empty table gives an empty result. Texts are read whole at any length.
"""

from __future__ import annotations

import public_tokenizers
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from cellbalance.llm import bpe, fmindex, langid, neardup, toxicity
from cellbalance.llm.common import Work, fold, table


def language(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Drops documents in no known language: without text or without a letter."""
    return langid.in_known_language(docs, langid.fit(docs, fold(4) != 2))


def toxic(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Drops documents that the toxicity grammar, fitted on the labelled ones, scores 0.5 or more."""
    return toxicity.without_toxic(docs, toxicity.fit(docs, table(spark, sf_dir, "labels"), fold(5) != 0, work=Work(spark)))


def near_duplicates(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Keeps one document of each group: five-word shingles, similarity of 0.8 or more."""
    return neardup.one_of_each(docs, shingle=5, percent=80)


def decontamination(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Drops documents of which a twentieth of the words or more lies in benchmark windows."""
    return fmindex.decontaminated(docs, table(spark, sf_dir, "benchmark"))


def tokens(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Token ids of each document, and digests of the ids and of the decoded text."""
    path = public_tokenizers.path("byte_bpe_50k.json")
    both = bpe.round_trip(docs, path)
    return both.select("doc_id", "n_tokens", "ids", F.sha2("ids", 256).alias("ids_sha256"), F.sha2(F.col("decoded").cast("binary"), 256).alias("decoded_sha256"))


STAGES = [
    ("language", language),
    ("toxicity", toxic),
    ("near_duplicates", near_duplicates),
    ("decontamination", decontamination),
    ("tokens", tokens),
]

ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs, work = table(spark, sf_dir, "documents"), Work(spark)
    for name, stage in STAGES:
        docs = work.table(stage(spark, docs, sf_dir), name)
    return docs
