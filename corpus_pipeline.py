"""Corpus pipeline: toxicity, quality rules, SimHash near-dedup, suffix-array dedup, packing.

Each stage takes all documents that its predecessor kept and, but for the last, returns the columns of
``documents``. Columns that it doesn't know are carried along, whatever their names. What a stage writes on
its way is deleted when its result is written. An empty table gives an empty result in every stage.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from pathtwin.plans.lineage import settled
from pathtwin.sources.io import read_table


def drop_toxic(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents with a toxicity score under one half. Null and empty texts have no evidence and stay; repeated rows fare alike."""
    from pathtwin.llm.toxicity import toxicity_scores

    scored = toxicity_scores(docs, read_table(spark, sf_dir, "labels"), keep_as="__toxicity")
    return scored.filter("__toxicity < 0.5").drop("__toxicity")


def apply_quality_rules(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that the base rules and their host's verdict keep. Null and empty texts go; without a source the base rules decide alone; repeated rows all stay."""
    from pathtwin.llm.quality_rules import ADDED, judge

    own = {c: f"__own_{c}" for c in docs.columns if c in ADDED}
    kept = judge(docs.withColumnsRenamed(own)).filter("kept").drop(*ADDED)
    return kept.withColumnsRenamed({v: k for k, v in own.items()}).select(*docs.columns)


def drop_near_copies(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document of each SimHash group. Null, empty and blank texts are one group; of repeated rows one stays; a null id is an id like any other."""
    from pathtwin.llm.simhash import one_of_each

    return one_of_each(docs).select(*docs.columns)


def drop_repeated_passages(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents without the bytes of repeated passages. Every row stays: null texts null, empty ones empty; repeated rows repeat each other."""
    from pathtwin.llm.suffix_dedup import without_repeats

    return without_repeats(docs)


def pack(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Token windows of what is left. Null and empty texts are their end id; repeated rows are packed as often as they occur."""
    import public_tokenizers

    from pathtwin.llm.packing import pack_documents

    return pack_documents(docs, public_tokenizers.path("word_bpe_49k.json"))


STAGES = [
    ("toxicity", drop_toxic),
    ("quality_rules", apply_quality_rules),
    ("simhash_near_dedup", drop_near_copies),
    ("suffix_array_dedup", drop_repeated_passages),
    ("packing", pack),
]


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All stages in turn, each written as Parquet and reread."""
    docs = read_table(spark, sf_dir, "documents")
    for _, stage in STAGES[:-1]:
        docs = settled(lambda stage=stage, docs=docs: stage(spark, docs, sf_dir))
    return STAGES[-1][1](spark, docs, sf_dir)


#: Viterbi decoding, learned scores, tokenizers and cut byte strings are beyond SQL; tests hold each stage against plain Python.
ORACLE_SQL = None
