"""The weighted word graph: candidate pairs, exact weights, pruning, ground truth."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from lexnorm.functions.shingles import gram_set
from lexnorm.operators import buckets, matching, similar

#: Pairs of blocks that a crowded bucket is cut into, so that no task enumerates it alone.
SALT_SIZE = 2_000
#: Representatives of groups that are sent to all executors; more are joined.
BROADCAST_HEADS = 1_000_000


def weight_of(a: Column, b: Column, repetitions: int) -> Column:
    """Repetitions in which two signature arrays agree; unrolled, so it stays in generated code."""
    out = F.lit(0)
    for r in range(repetitions):
        out = out + (F.get(a, F.lit(r)) == F.get(b, F.lit(r))).cast("int")
    return out


def _pairs(members: DataFrame, salt_size: int = SALT_SIZE) -> DataFrame:
    """``src, dst, rep`` for each two words of a bucket, once; crowded buckets are paired block by block."""
    n = F.greatest(F.lit(1), F.ceil(F.col("size") / salt_size)).cast("int")
    own = members.withColumn("blocks", n).withColumn("block", F.pmod(F.xxhash64("word"), F.col("blocks")).cast("int"))
    other = F.explode(F.sequence(F.lit(0), F.col("blocks") - 1))
    left = own.withColumn("with", other).select("rep", "sig", F.col("word").alias("src"), F.col("block").alias("b1"), F.col("with").alias("b2"))
    right = own.withColumn("with", other).select("rep", "sig", F.col("word").alias("dst"), F.col("with").alias("b1"), F.col("block").alias("b2"))
    return left.join(right, ["rep", "sig", "b1", "b2"]).where("src < dst").select("src", "dst", "rep")


def _sized(members: DataFrame) -> DataFrame:
    return members.join(buckets.sizes(members), ["rep", "sig"])


def edge_weights(sigs: DataFrame, repetitions: int, min_weight: int = 1, strategy: str = "prefix") -> DataFrame:
    """``src, dst, weight`` (src < dst) of pairs with ``min_weight`` or more.

    ``pairs`` counts collisions over all repetitions; ``prefix`` pairs words in
    sparse buckets only and weighs them there: the same result with far fewer
    pairs. ``union`` (weight one, connectivity only) ties each word to
    the least one of its group; ``intersect`` groups by the whole array.
    """
    members = buckets.explode(sigs)
    if strategy == "pairs" or strategy == "prefix" and repetitions > matching.MOST_REPETITIONS:
        return _pairs(_sized(members)).groupBy("src", "dst").agg(F.count("*").cast("int").alias("weight")).where(F.col("weight") >= min_weight)
    if strategy == "prefix":
        return matching.pairs(sigs, repetitions, min_weight)
    if strategy == "union":
        return matching.stars(sigs, repetitions)
    if strategy == "intersect":
        hubs = sigs.groupBy("sig").agg(F.min("word").alias("hub"), F.max("word").alias("last")).where("hub < last").drop("last")
        return sigs.join(hubs, "sig").where("word != hub").select(F.col("hub").alias("src"), F.col("word").alias("dst"), F.lit(repetitions).alias("weight"))
    raise ValueError(strategy)


def strategy_for(min_weight: int, repetitions: int) -> str:
    """The cheapest strategy that keeps the components."""
    if min_weight >= repetitions:
        return "intersect"
    return "union" if min_weight <= 1 else "prefix"


def prune(edges: DataFrame, min_weight: int) -> DataFrame:
    return edges.where(F.col("weight") >= min_weight)


def star_split(edges: DataFrame, norm_map: DataFrame) -> DataFrame:
    """Edges that tie a word straight to its representative; what chains through others is cut."""
    keyed = norm_map.select("word", "rep_word")
    both = edges.unionByName(edges.select(F.col("dst").alias("src"), F.col("src").alias("dst"), "weight"))
    # An edge ties to a representative only if one end is one, so few edges reach the join.
    heads = norm_map.where("size > 1 and word = rep_word").select(F.col("word").alias("dst"))
    if heads.count() <= BROADCAST_HEADS:
        heads = F.broadcast(heads)
    return both.join(heads, "dst", "left_semi").join(keyed, F.col("src") == keyed.word).where("dst = rep_word").select(F.least("src", "dst").alias("src"), F.greatest("src", "dst").alias("dst"), "weight").distinct()


def verified(edges: DataFrame, char_lens, least: float) -> DataFrame:
    """Edges whose words' exact substring similarity is ``least`` or more."""
    from lexnorm.functions.shingles import jaccard

    return edges.where(jaccard(gram_set(F.col("src"), char_lens), gram_set(F.col("dst"), char_lens)) >= least)


def exact_pairs(vocab: DataFrame, char_lens, least: float) -> DataFrame:
    """``src, dst, jaccard`` of all pairs with similarity ``least`` or more: the graph that signatures estimate.

    Pairs meet at the rarest substrings and are verified there (:mod:`lexnorm.operators.similar`):
    no candidates are shuffled or made distinct.
    """
    return similar.pairs(vocab, char_lens, least)
