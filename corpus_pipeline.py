"""A training-data pipeline over ``documents`` in five stages, each written before the next."""

from __future__ import annotations

import public_tokenizers
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from lexnorm.llm import decontaminate, quality, simhash_dedup, suffix_dedup, unigram, windows
from lexnorm.sources.store import materialise, table

COLUMNS = ("doc_id", "text", "lang", "source", "n_chars")
#: No stage but the last could be said in SQL, and that one can't either.
ORACLE_SQL = None


REST = COLUMNS[1:]


def quality_rules(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that the base rules and the isolation forest keep."""
    return quality.judge(docs, table(spark, sf_dir, "labels"), carry=REST).where("kept").select(*COLUMNS)


def simhash_near_dedup(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document of each group of near copies (five-word Jaccard 0.8 or more): the one with the smallest id.

    Rows without an id belong to no group and stay. Of rows that repeat an id, one stays.
    """
    groups = materialise(simhash_dedup.near_copies(docs), "groups")
    others = materialise(groups.where("doc_id != component_id").select("doc_id").distinct(), "others")
    if others.count() <= windows.BROADCAST_ROWS:
        others = F.broadcast(others)
    kept = docs.join(others, "doc_id", "left_anti").select(*COLUMNS)
    repeated = groups.where("doc_id is not null").groupBy("doc_id").count().where("count > 1")
    if repeated.limit(1).count() == 0:
        return kept
    return kept.where("doc_id is not null").dropDuplicates(["doc_id"]).unionByName(kept.where("doc_id is null"))


def suffix_array_dedup(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Texts without passages that a smaller document holds; documents that lose all their words go."""
    out = suffix_dedup.remove_repeats(docs, carry=REST).where("n_removed = 0 or n_removed < n_words")
    changed = F.col("n_removed") > 0
    return out.select(
        "doc_id",
        F.when(changed, F.col("kept_text")).otherwise(F.col("text")).alias("text"),
        "lang",
        "source",
        F.when(changed, F.length("kept_text").cast("long")).otherwise(F.col("n_chars")).alias("n_chars"),
    )


def benchmark_decontamination(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents without passages of the benchmark."""
    return decontaminate.scan(docs, table(spark, sf_dir, "benchmark"), carry=REST).where("not contaminated").select(*COLUMNS)


def unigram_encoding(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Token ids of each document, and whether they decode to its text."""
    return unigram.encode_documents(docs, public_tokenizers.path("piece_bpe_32k.model"), rank_scores=True)


STAGES = [
    ("quality_rules", quality_rules),
    ("simhash_near_dedup", simhash_near_dedup),
    ("suffix_array_dedup", suffix_array_dedup),
    ("benchmark_decontamination", benchmark_decontamination),
    ("unigram_encoding", unigram_encoding),
]


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All stages over ``documents``."""
    docs = table(spark, sf_dir, "documents")
    for name, stage in STAGES[:-1]:
        docs = materialise(stage(spark, docs, sf_dir), name)
    return STAGES[-1][1](spark, docs, sf_dir)
