"""Registered queries of the training-data operators: whole tables, production parameters."""

from __future__ import annotations

from collections.abc import Callable

import public_tokenizers
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from cellbalance.llm import bpe, chat, fmindex, langid, licenses, oracles, quality, sharding, toxicity, warc
from cellbalance.llm.common import Work, fold, table
from cellbalance.llm.neardup import near_duplicates

ORACLES: dict[str, str] = {"op1_near_duplicates": oracles.NEAR_DUPLICATES, "op2_contamination": oracles.CONTAMINATION, "op9_tool_chat": oracles.TOOL_CHAT}


def op1_near_duplicates(spark: SparkSession, sf_dir: str) -> DataFrame:
    return near_duplicates(table(spark, sf_dir, "documents"), shingle=2, percent=80)


def op2_contamination(spark: SparkSession, sf_dir: str) -> DataFrame:
    found = fmindex.contamination(table(spark, sf_dir, "documents"), table(spark, sf_dir, "benchmark"))
    return found.select(
        "doc_id",
        "n_words",
        "n_hit",
        F.size("items").cast("long").alias("n_items"),
        F.size("spans").cast("long").alias("n_spans"),
        F.sha2(F.array_join("items", ",").cast("binary"), 256).alias("items_sha256"),
        F.expr("n_hit > 0 and 20 * n_hit >= n_words").alias("contaminated"),
    )


def op3_histogram_shards(spark: SparkSession, sf_dir: str) -> DataFrame:
    placed = sharding.document_shards(table(spark, sf_dir, "documents"), shards=16)
    return placed.select("doc_id", "size", "text_crc32", F.lit("bytes").alias("law"), "shard", "slot", F.lit(None).cast("int").alias("grown_shard"))


def op4_warc_derivatives(spark: SparkSession, sf_dir: str) -> DataFrame:
    records = warc.warc_members(warc.derivatives(warc.page_responses(table(spark, sf_dir, "pages")), "page_id"))
    member = (F.length("member").cast("long").alias("member_bytes"), F.sha2("member", 256).alias("member_sha256"))
    return records.select(*(F.col(c).cast("string").alias(c) if c == "block" else c for c in records.columns if c != "member"), *member)


def op5_toxicity(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs, labels = table(spark, sf_dir, "documents"), table(spark, sf_dir, "labels")
    model = toxicity.fit(docs, labels, fold(5) != 0, work=Work(spark))
    scored = toxicity.score(docs, model)
    return scored.select("doc_id", (fold(5) == 0).alias("held_out"), "score", (F.col("score") >= 0.5).cast("int").alias("predicted"))


def op6_bpe(spark: SparkSession, sf_dir: str) -> DataFrame:
    path = public_tokenizers.path("byte_bpe_50k.json")
    both = bpe.round_trip(table(spark, sf_dir, "documents"), path)
    return both.select("doc_id", "n_tokens", F.sha2("ids", 256).alias("ids_sha256"), F.sha2(F.col("decoded").cast("binary"), 256).alias("decoded_sha256"))


def op7_compression_bands(spark: SparkSession, sf_dir: str) -> DataFrame:
    found = quality.compression_bands(table(spark, sf_dir, "documents"))
    return found.select("doc_id", "n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", "base_failed", "kept", "in_band", "bad_chunks")


def op8_licenses(spark: SparkSession, sf_dir: str) -> DataFrame:
    found = licenses.scan(table(spark, sf_dir, "documents"))
    joined = (F.array_join(c, ",").alias(c) for c in ("base_labels", "labels"))
    return found.select("doc_id", "n_words", "n_base", "first_word", "last_word", *joined, "score")


def op9_tool_chat(spark: SparkSession, sf_dir: str) -> DataFrame:
    return chat.tool_chat(table(spark, sf_dir, "conversations"))


def op10_language(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    found = langid.identify(docs, langid.fit(docs, fold(4) != 2))
    return found.select("doc_id", (fold(4) == 2).alias("held_out"), "lang_pred", "score")


QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {
    "op1_near_duplicates": op1_near_duplicates,
    "op2_contamination": op2_contamination,
    "op3_histogram_shards": op3_histogram_shards,
    "op4_warc_derivatives": op4_warc_derivatives,
    "op5_toxicity": op5_toxicity,
    "op6_bpe": op6_bpe,
    "op7_compression_bands": op7_compression_bands,
    "op8_licenses": op8_licenses,
    "op9_tool_chat": op9_tool_chat,
    "op10_language": op10_language,
}
