"""Buckets of words that share a signature in a repetition."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from lexnorm.sources.store import materialise

#: Rows of words and repetitions that are counted at once.
PASS_ROWS = 20_000_000


def explode(sigs: DataFrame) -> DataFrame:
    """``word, rep, sig``: one row for each repetition."""
    return sigs.select("word", F.posexplode("sig").alias("rep", "sig"))


def sizes(members: DataFrame, least: int = 2) -> DataFrame:
    """``rep, sig, size`` of buckets with ``least`` words or more; a bucket of one makes no edge."""
    return members.groupBy("rep", "sig").agg(F.count("*").alias("size")).where(F.col("size") >= least)


def profile(members: DataFrame) -> DataFrame:
    """Per repetition: buckets, words in them, mean and largest size, and pairs."""
    return sizes(members, 1).groupBy("rep").agg(
        F.count("*").alias("buckets"),
        F.sum("size").alias("words"),
        F.max("size").alias("largest"),
        F.sum((F.col("size") * (F.col("size") - 1) / 2).cast("long")).alias("pairs"),
    )


def profiles(sigs: DataFrame, repetitions: int) -> DataFrame:
    """:func:`profile` of all repetitions, a few at a time: what is on its way at once doesn't grow with their number."""
    step = min(repetitions, max(1, PASS_ROWS // max(1, sigs.count())))
    out = None
    for first in range(0, repetitions, step):
        some = sigs.select("word", F.posexplode(F.slice("sig", first + 1, step)).alias("rep", "sig"))
        one = materialise(profile(some.withColumn("rep", F.col("rep") + first)), "buckets")
        out = one if out is None else out.unionByName(one)
    return out


def sparse_members(members: DataFrame, min_weight: int) -> DataFrame:
    """Members without each word's ``min_weight - 1`` most crowded buckets.

    Two words that share ``min_weight`` buckets or more still share one of what
    is left: order all buckets by size; of the shared ones, at most
    ``min_weight - 1`` can be among either word's most crowded. Buckets of one
    word drop out first, so the order is that of buckets that can make edges.
    """
    crowded = members.join(sizes(members), ["rep", "sig"])
    if min_weight <= 1:
        return crowded
    order = Window.partitionBy("word").orderBy(F.desc("size"), "rep", "sig")
    return crowded.withColumn("rank", F.row_number().over(order)).where(F.col("rank") >= min_weight).drop("rank")
