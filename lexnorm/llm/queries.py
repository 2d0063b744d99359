"""Queries over the given tables, one for each operator of this subpackage."""

from __future__ import annotations

from collections.abc import Callable

import public_tokenizers
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from lexnorm.llm.decontaminate import scan
from lexnorm.llm.html_extract import extract
from lexnorm.llm.language_model import score
from lexnorm.llm.license_scan import scan as scan_licences
from lexnorm.llm.quality import judge
from lexnorm.llm.simhash_dedup import near_duplicates
from lexnorm.llm.substring_dedup import remove_repeats
from lexnorm.llm.suffix_dedup import remove_repeats as remove_suffix_repeats
from lexnorm.llm.token_file import round_trip
from lexnorm.llm.unigram import encode_documents
from lexnorm.sources.store import table


def op1_html_extract(spark: SparkSession, sf_dir: str) -> DataFrame:
    return extract(table(spark, sf_dir, "pages"))


def op2_language_model(spark: SparkSession, sf_dir: str) -> DataFrame:
    return score(table(spark, sf_dir, "documents"))


def op3_substring_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return remove_repeats(table(spark, sf_dir, "documents"), with_text=False).drop("kept_text")


def op4_quality_rules(spark: SparkSession, sf_dir: str) -> DataFrame:
    return judge(table(spark, sf_dir, "documents"), table(spark, sf_dir, "labels"))


def op5_unigram_encoding(spark: SparkSession, sf_dir: str) -> DataFrame:
    return encode_documents(table(spark, sf_dir, "documents"), public_tokenizers.path("piece_bpe_32k.model"), with_ids=False, rank_scores=True).drop("ids")


def op6_decontamination(spark: SparkSession, sf_dir: str) -> DataFrame:
    return scan(table(spark, sf_dir, "documents"), table(spark, sf_dir, "benchmark"))


def op7_simhash_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return near_duplicates(table(spark, sf_dir, "documents"))


def op8_suffix_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return remove_suffix_repeats(table(spark, sf_dir, "documents"), with_text=False).drop("kept_text")


def op9_token_file(spark: SparkSession, sf_dir: str) -> DataFrame:
    return round_trip(table(spark, sf_dir, "documents"), public_tokenizers.path("byte_bpe_50k.json"))


def op10_license_scan(spark: SparkSession, sf_dir: str) -> DataFrame:
    out = scan_licences(table(spark, sf_dir, "documents"))
    return out.select("doc_id", "n_licences", "n_unknown", F.array_join("families", ",").alias("families"))


def queries() -> dict[str, Callable[[SparkSession, str], DataFrame]]:
    return {f.__name__: f for f in (op1_html_extract, op2_language_model, op3_substring_dedup, op4_quality_rules, op5_unigram_encoding, op6_decontamination, op7_simhash_dedup, op8_suffix_dedup, op9_token_file, op10_license_scan)}


def oracle_sql() -> dict[str, str]:
    return {}
