"""From components to the normalization vocabulary."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F


def build(vocab: DataFrame, comps: DataFrame) -> DataFrame:
    """``word, freq, comp, rep_word, rep_freq, size``: the most frequent word of a component (the least of equals) stands for it.

    ``comps`` has ``node, comp``; a word without an edge is its own component.
    """
    labelled = vocab.join(comps.withColumnRenamed("node", "word"), "word", "left").select("word", "freq", F.coalesce("comp", "word").alias("comp"))
    # min_by over (-freq, word): partial aggregation, so a giant component is one row a task.
    best = labelled.groupBy("comp").agg(F.min(F.struct((-F.col("freq")).alias("order"), F.col("word").alias("w"))).alias("best"), F.count("*").alias("size"))
    rep = best.select("comp", F.col("best.w").alias("rep_word"), (-F.col("best.order")).alias("rep_freq"), "size")
    return labelled.join(rep, "comp").select("word", "freq", "comp", "rep_word", "rep_freq", "size")


def as_map(norm: DataFrame, changed_only: bool = True) -> DataFrame:
    """``word, rep_word``; words that stay are left out unless asked for."""
    out = norm.where("word != rep_word") if changed_only else norm
    return out.select("word", "rep_word")


def as_lists(norm: DataFrame, least: int = 2) -> DataFrame:
    """``rep_word, rep_freq, size, members``: members by frequency, then word."""
    grouped = norm.where(F.col("size") >= least).groupBy("rep_word", "rep_freq", "size")
    members = F.array_sort(F.collect_list(F.struct((-F.col("freq")).alias("order"), "word")))
    return grouped.agg(F.transform(members, lambda m: m["word"]).alias("members"))


def size_profile(norm: DataFrame) -> DataFrame:
    """How many components of each size: chaining shows as a giant one."""
    return norm.groupBy("comp").agg(F.count("*").alias("size")).groupBy("size").agg(F.count("*").alias("components"))
