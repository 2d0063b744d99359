"""Error bounds, exact tails, cost model and collision curves."""

from __future__ import annotations

import math
from fractions import Fraction

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from lexnorm.functions.shingles import gram_set, jaccard
from lexnorm.operators import buckets


def _tail(T: int, p: float, lo: int, hi: int) -> float:
    return math.fsum(math.comb(T, k) * p**k * (1 - p) ** (T - k) for k in range(max(lo, 0), min(hi, T) + 1))


def fp_bound(c: int, T: int, q: float, alpha: str | float, form: str = "valid") -> float:
    """Chance that a word links to a foreign cluster of ``c`` words, each colliding with probability ``q``.

    ``printed`` divides by 3q, which holds for alpha up to 2q only; ``valid`` is
    the form for all alpha above q; ``exact`` sums the binomial tail. One where
    alpha does not exceed q.
    """
    a = float(Fraction(str(alpha)))
    if a <= q:
        return 1.0
    if form == "printed":
        return min(1.0, c * math.exp(-T * (q - a) ** 2 / (3 * q)))
    if form == "valid":
        d = a / q - 1
        return min(1.0, c * math.exp(-(d**2) * T * q / (2 + d)))
    if form == "exact":
        return min(1.0, c * _tail(T, q, math.ceil(Fraction(str(alpha)) * T), T))
    raise ValueError(form)


def fn_bound(c: int, T: int, p: float, alpha: str | float, form: str = "printed", strict: bool = True) -> float:
    """Chance that a word links to none of its own cluster, whose pairs collide with probability ``p``.

    ``printed`` counts all ``c`` members, the word included; ``peers`` the other
    ``c - 1``; ``exact`` is the binomial tail for the peers, weights below alpha T
    (``strict``) or up to it. One where alpha is not below p.
    """
    a = float(Fraction(str(alpha)))
    if form == "exact":
        t = Fraction(str(alpha)) * T
        return _tail(T, p, 0, math.ceil(t) - 1 if strict else math.floor(t)) ** max(c - 1, 0)
    if a >= p:
        return 1.0
    n = c if form == "printed" else c - 1
    return min(1.0, math.exp(-n * T * (p - a) ** 2 / (2 * p)))


def _sql_tail(T: Column, p: Column, lo: Column, hi: Column) -> Column:
    """Binomial probability of lo..hi, by a running product over the terms."""
    ln_choose = lambda k: F.aggregate(F.when(k > 0, F.sequence(F.lit(1), k)).otherwise(F.array().cast("array<int>")), F.lit(0.0), lambda s, i: s + F.log((T - i + 1).cast("double")) - F.log(i.cast("double")))
    ks = F.when(hi >= lo, F.sequence(lo, hi)).otherwise(F.array().cast("array<int>"))
    return F.aggregate(ks, F.lit(0.0), lambda s, k: s + F.exp(ln_choose(k) + k * F.log(p) + (T - k) * F.log(1 - p)))


def bounds(grid: DataFrame) -> DataFrame:
    """Add all forms of both bounds to rows ``c, t, p, q, alpha_num, alpha_den`` (alpha as a fraction)."""
    a = F.col("alpha_num") / F.col("alpha_den")
    t, c, p, q = F.col("t"), F.col("c"), F.col("p"), F.col("q")
    up = F.expr("cast(ceil(cast(alpha_num * t as decimal(18, 0)) / alpha_den) as int)")
    d = a / q - 1
    cap = lambda x: F.least(F.lit(1.0), x)
    fp = lambda x: F.when(a <= q, F.lit(1.0)).otherwise(cap(x))
    fn = lambda n: F.when(a >= p, F.lit(1.0)).otherwise(cap(F.exp(-n * t * (p - a) ** 2 / (2 * p))))
    return grid.select(
        "*",
        fp(c * F.exp(-t * (q - a) ** 2 / (3 * q))).alias("fp_printed"),
        fp(c * F.exp(-d * d * t * q / (2 + d))).alias("fp_valid"),
        fp(c * _sql_tail(t, q, up, t)).alias("fp_exact"),
        fn(c).alias("fn_printed"),
        fn(c - 1).alias("fn_peers"),
        F.pow(_sql_tail(t, p, F.lit(0), up - 1), c - 1).alias("fn_exact"),
    )


def collision_curve(sigs: DataFrame, pairs: DataFrame, repetitions: int, bins: int = 10) -> DataFrame:
    """Measured share of agreeing repetitions by similarity bin, for pairs ``src, dst, jaccard``."""
    from lexnorm.operators.graph import weight_of

    a = sigs.select(F.col("word").alias("src"), F.col("sig").alias("sig_a"))
    b = sigs.select(F.col("word").alias("dst"), F.col("sig").alias("sig_b"))
    rate = pairs.join(a, "src").join(b, "dst").select("jaccard", (weight_of(F.col("sig_a"), F.col("sig_b"), repetitions) / repetitions).alias("rate"))
    at = F.least(F.floor(F.col("jaccard") * bins), F.lit(bins - 1)).cast("int")
    return rate.groupBy(at.alias("bin")).agg(F.count("*").alias("pairs"), F.avg("jaccard").alias("jaccard"), F.avg("rate").alias("rate"))


def estimate_pq(edges: DataFrame, clusters: DataFrame, repetitions: int) -> DataFrame:
    """Least collision rate within clusters (p) and greatest between them (q), over weighed pairs ``src, dst, weight``."""
    a = clusters.select(F.col("word").alias("src"), F.col("cluster").alias("ca"))
    b = clusters.select(F.col("word").alias("dst"), F.col("cluster").alias("cb"))
    rate = edges.join(a, "src").join(b, "dst").select((F.col("weight") / repetitions).alias("rate"), (F.col("ca") == F.col("cb")).alias("inside"))
    return rate.groupBy("inside").agg(F.count("*").alias("pairs"), F.min("rate").alias("least"), F.max("rate").alias("greatest"), F.avg("rate").alias("mean"))


def cost(vocab: DataFrame, sigs: DataFrame, repetitions: int, alphabet: int = 36) -> DataFrame:
    """Terms of the cost model: hashing L N T, pairing M^2 B, pruning N, and enumeration L N X."""
    v = vocab.agg(F.count("*").alias("n"), F.avg(F.length("word")).alias("l"))
    b = buckets.profiles(sigs, repetitions).agg(F.coalesce(F.sum("buckets"), F.lit(0)).alias("b"), F.try_divide(F.sum("words"), F.sum("buckets")).alias("m"))
    row = v.crossJoin(F.broadcast(b))
    n, length, m, many = F.col("n"), F.col("l"), F.col("m"), F.col("b")
    return row.select(n.alias("words"), length.alias("mean_length"), many.alias("buckets"), m.alias("mean_bucket"), (length * n * repetitions).alias("hashing"), (m * m * many).alias("pairing"), n.cast("double").alias("pruning"), (length * n * alphabet).alias("enumeration"))


def similar(a: Column, b: Column, char_lens=(1, 3, 5)) -> Column:
    return jaccard(gram_set(a, char_lens), gram_set(b, char_lens))
