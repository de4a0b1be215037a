"""Thin queries over whole tables, and their SQL counterparts where SQL can express them."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from pathtwin.llm import chat, quality_rules, vector_dedup
from pathtwin.sources.io import read_table


def _documents(spark: SparkSession, sf_dir: str) -> DataFrame:
    return read_table(spark, sf_dir, "documents")


def op1_quality_rules(spark: SparkSession, sf_dir: str) -> DataFrame:
    from pathtwin.llm.quality_rules import judge

    found = judge(read_table(spark, sf_dir, "documents", "doc_id", "source", "text"), keep_text=False)
    return found.select("doc_id", "n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", "base_failed", "kept")


def op2_chat_rotation(spark: SparkSession, sf_dir: str) -> DataFrame:
    from pathtwin.llm.chat import rotations

    return rotations(read_table(spark, sf_dir, "conversations"))


def op3_vector_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    from pathtwin.llm.vector_dedup import near_duplicates

    return near_duplicates(read_table(spark, sf_dir, "embeddings"))


def op4_simhash(spark: SparkSession, sf_dir: str) -> DataFrame:
    from pathtwin.llm.simhash import near_duplicates

    return near_duplicates(_documents(spark, sf_dir)).select("doc_id", "fingerprint", "component_id")


def op5_toxicity(spark: SparkSession, sf_dir: str) -> DataFrame:
    from pathtwin.llm.toxicity import toxicity_scores

    return toxicity_scores(_documents(spark, sf_dir), read_table(spark, sf_dir, "labels"))


def op6_language_id(spark: SparkSession, sf_dir: str) -> DataFrame:
    from pathtwin.llm.language_id import identify

    return identify(_documents(spark, sf_dir))


def op7_packing(spark: SparkSession, sf_dir: str) -> DataFrame:
    import public_tokenizers

    from pathtwin.llm.packing import pack_documents

    return pack_documents(_documents(spark, sf_dir), public_tokenizers.path("word_bpe_49k.json"))


def op8_suffix_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    from pathtwin.llm.suffix_dedup import dedup_digests

    return dedup_digests(_documents(spark, sf_dir))


def op9_byte_bpe(spark: SparkSession, sf_dir: str) -> DataFrame:
    import public_tokenizers

    from pathtwin.llm.byte_bpe import encode_documents

    ranks = public_tokenizers.path("byte_bpe_50k.tiktoken")
    return encode_documents(_documents(spark, sf_dir), ranks, public_tokenizers.PATTERN, ids=False)


def op10_rule_ensemble(spark: SparkSession, sf_dir: str) -> DataFrame:
    from pathtwin.llm.rule_ensemble import quality_scores

    found = quality_scores(_documents(spark, sf_dir), read_table(spark, sf_dir, "labels"))
    return found.select("doc_id", "held_out", "score", "predicted")


QUERIES = {"op1_quality_rules": op1_quality_rules, "op2_chat_rotation": op2_chat_rotation, "op3_vector_dedup": op3_vector_dedup, "op4_simhash": op4_simhash, "op5_toxicity": op5_toxicity, "op6_language_id": op6_language_id, "op7_packing": op7_packing, "op8_suffix_dedup": op8_suffix_dedup, "op9_byte_bpe": op9_byte_bpe, "op10_rule_ensemble": op10_rule_ensemble}

ORACLES: dict[str, str] = {"op1_quality_rules": quality_rules.ORACLE, "op2_chat_rotation": chat.ORACLE, "op3_vector_dedup": vector_dedup.ORACLE}
