"""Unseen words: attach each to the indexed word it collides with most often."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from lexnorm.functions import hashing
from lexnorm.operators import matching
from lexnorm.sources.store import materialise


def collisions(new: DataFrame, old: DataFrame, repetitions: int, min_weight: int, best: bool = False) -> DataFrame:
    """``word, indexed, weight`` of pairs (new, old) that collide ``min_weight`` times or more.

    A word's ``min_weight - 1`` most crowded buckets are skipped, as pairs of
    that weight meet in another one; weights are exact. With ``best``, pairs that are
    lighter than another one of their ``word`` may be left out.
    """
    found = matching.pairs(new.select("word", "sig"), repetitions, min_weight, old.select("word", "sig"), best=best)
    return found.select(F.col("src").alias("word"), F.col("dst").alias("indexed"), "weight")


def attach(words: DataFrame, index, inclusive: bool = False, targets: str = "all") -> DataFrame:
    """``word, matched, weight, rep_word, status`` for each distinct word.

    ``known``: in the index, looked up. ``attached``: takes the representative of
    the heaviest match (more frequent, then lesser word of equals) above the
    threshold, or at it if ``inclusive``. ``unmatched``: stays itself.
    ``targets='grouped'`` attaches to words in groups of two or more only.
    """
    p = index.params
    asked = words.select("word").where("word is not null").distinct()
    known = asked.join(index.norm, "word").select("word", F.col("word").alias("matched"), F.lit(None).cast("int").alias("weight"), "rep_word", F.lit("known").alias("status"))
    unseen = asked.join(index.norm.select("word"), "word", "left_anti")
    new = materialise(hashing.signatures(unseen, index.family), "sigs")
    old = index.sigs
    if targets == "grouped":
        old = old.join(index.norm.where("size > 1").select("word"), "word", "left_semi")
    weighed = collisions(new, old, p.repetitions, p.infer_min(inclusive), best=True)
    ranked = weighed.join(index.norm.select(F.col("word").alias("indexed"), "freq", "rep_word"), "indexed")
    best = ranked.groupBy("word").agg(F.min(F.struct((-F.col("weight")).alias("w"), (-F.col("freq")).alias("f"), F.col("indexed").alias("i"), F.col("rep_word").alias("r"))).alias("b"))
    found = unseen.join(best, "word", "left").select(
        "word",
        F.col("b.i").alias("matched"),
        (-F.col("b.w")).cast("int").alias("weight"),
        F.coalesce(F.col("b.r"), F.col("word")).alias("rep_word"),
        F.when(F.col("b").isNull(), "unmatched").otherwise("attached").alias("status"),
    )
    return known.unionByName(found)
