"""Character substrings of words, and similarities of such sets."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F


def _runs(word: Column, k: int | Column) -> Column:
    n = F.length(word)
    k = F.lit(k) if isinstance(k, int) else k
    return F.when(n >= k, F.transform(F.sequence(F.lit(1), n - k + 1), lambda i: F.substring(word, i, k))).otherwise(F.array().cast("array<string>"))


def gram_set(word: Column, char_lens: tuple[int, ...] | str = (1, 3, 5)) -> Column:
    """Distinct substrings of the given lengths, or of all (``'all'``).

    A length beyond the word's adds nothing, so a short word may have an empty set.
    """
    if char_lens == "all":
        every = F.transform(F.sequence(F.lit(1), F.greatest(F.length(word), F.lit(1))), lambda k: _runs(word, k))
        return F.array_distinct(F.flatten(every))
    return F.array_distinct(F.concat(*(_runs(word, k) for k in char_lens)))


def jaccard(a: Column, b: Column) -> Column:
    """Shared over all elements of two sets; zero if both are empty."""
    every = F.size(F.array_union(a, b))
    return F.when(every > 0, F.size(F.array_intersect(a, b)) / every).otherwise(F.lit(0.0))


def same_prefix_groups(vocab: DataFrame, length: int = 4) -> DataFrame:
    """Stemming by truncation, for comparison: words that share their first ``length`` characters."""
    return vocab.where(F.length("word") >= length).groupBy(F.substring("word", 1, length).alias("stem")).agg(F.count("*").alias("words"), F.sum("freq").alias("freq"), F.max_by("word", F.struct(F.col("freq"))).alias("top"))


def collapse(vocab: DataFrame, char_lens: tuple[int, ...] | str) -> DataFrame:
    """Words with equal substring sets, which collide in every repetition, with the least of them as ``hub``."""
    keyed = vocab.select("word", F.array_sort(gram_set(F.col("word"), char_lens)).alias("grams")).where(F.size("grams") > 0)
    hubs = keyed.groupBy(F.md5(F.array_join("grams", "\x00")).alias("key")).agg(F.min("word").alias("hub"), F.count("*").alias("members"))
    return keyed.select("word", F.md5(F.array_join("grams", "\x00")).alias("key")).join(hubs, "key").select("word", "hub", "members")
