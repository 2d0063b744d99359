"""Accuracy and cost measures, each one aggregation."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

GOOD, NEUTRAL, BAD, UNSURE = "good", "neutral", "bad", "not sure"


def _ratio(a: Column, b: Column) -> Column:
    return F.when(b != 0, a / b).otherwise(F.lit(0.0))


def _count(cond: Column) -> Column:
    return F.coalesce(F.sum(F.when(cond, 1).otherwise(0)), F.lit(0))


def human_prf(judgements: DataFrame, needs: DataFrame, vote: str = "label") -> DataFrame:
    """``dataset, method, precision, recall, f1`` of reviewers' labels.

    Precision: good and neutral among labels of corrections (unsure ones left
    out). Recall: labels good on sentences that need fixing. With ``majority``
    each sentence counts once, by its most frequent label (good, then neutral,
    then bad among equals); with ``label`` every label counts.
    """
    votes = judgements.where(F.col("label") != UNSURE)
    if vote == "majority":
        order = F.when(F.col("label") == GOOD, 0).when(F.col("label") == NEUTRAL, 1).otherwise(2)
        counted = votes.groupBy("dataset", "method", "sentence_id", "label").agg(F.count("*").alias("n"), F.max("corrected").alias("corrected"))
        votes = counted.groupBy("dataset", "method", "sentence_id").agg(F.min(F.struct((-F.col("n")).alias("n"), order.alias("o"), "label")).alias("b"), F.max("corrected").alias("corrected")).select("dataset", "method", "sentence_id", F.col("b.label").alias("label"), "corrected")
    keyed = votes.join(needs, ["dataset", "sentence_id"], "left")
    need = F.coalesce(F.col("needs_fix"), F.lit(False))
    right = F.col("label").isin(GOOD, NEUTRAL)
    sums = keyed.groupBy("dataset", "method").agg(
        _count(F.col("corrected") & right).alias("right"), _count(F.col("corrected")).alias("judged"), _count(need & F.col("corrected") & (F.col("label") == GOOD)).alias("fixed"), _count(need).alias("needed")
    )
    p, r = _ratio(F.col("right"), F.col("judged")), _ratio(F.col("fixed"), F.col("needed"))
    return sums.select("dataset", "method", p.alias("precision"), r.alias("recall"), _ratio(2 * p * r, p + r).alias("f1"))


def vote_profile(judgements: DataFrame) -> DataFrame:
    """Labels by method and dataset, and the share of sentences on which all reviewers agree."""
    by = ["dataset", "method"]
    same = judgements.groupBy(*by, "sentence_id").agg((F.countDistinct("label") == 1).cast("int").alias("same"))
    labels = judgements.groupBy(*by).agg(*(_count(F.col("label") == x).alias(x.replace(" ", "_")) for x in (GOOD, NEUTRAL, BAD, UNSURE)))
    return labels.join(same.groupBy(*by).agg(F.avg("same").alias("agreement")), by)


def coverage(norm: DataFrame) -> DataFrame:
    """Four readings of coverage: words (or their occurrences) in groups of two or more, or changed."""
    grouped, changed, n = F.col("size") > 1, F.col("word") != F.col("rep_word"), F.col("freq")
    share = lambda cond, w: _ratio(F.sum(F.when(cond, w).otherwise(0)), F.sum(w))
    one = F.lit(1)
    return norm.agg(share(grouped, one).alias("grouped_words"), share(grouped, n).alias("grouped_occurrences"), share(changed, one).alias("changed_words"), share(changed, n).alias("changed_occurrences"))


def classification(predictions: DataFrame, by: list[str] | None = None) -> DataFrame:
    """``n, accuracy, precision, recall, f1, matthews`` of 0/1 columns ``y, yhat``; empty margins give zero."""
    y, h = F.col("y") == 1, F.col("yhat") == 1
    c = predictions.groupBy(*(by or [])).agg(F.count("*").alias("n"), _count(y & h).alias("tp"), _count(~y & h).alias("fp"), _count(y & ~h).alias("fn"), _count(~y & ~h).alias("tn"))
    tp, fp, fn, tn = (F.col(x).cast("double") for x in ("tp", "fp", "fn", "tn"))
    p, r = _ratio(tp, tp + fp), _ratio(tp, tp + fn)
    mcc = _ratio(tp * tn - fp * fn, F.sqrt(tp + fp) * F.sqrt(tp + fn) * F.sqrt(tn + fp) * F.sqrt(tn + fn))
    return c.select(*(by or []), "n", _ratio(tp + tn, F.col("n").cast("double")).alias("accuracy"), p.alias("precision"), r.alias("recall"), _ratio(2 * tp, 2 * tp + fp + fn).alias("f1"), mcc.alias("matthews"))


def correlations(pairs: DataFrame, by: list[str]) -> DataFrame:
    """Pearson and Spearman (average ranks) of ``gold, score``."""
    part = Window.partitionBy(*by)

    def rank(c: str) -> Column:
        return F.rank().over(part.orderBy(c)) + (F.count("*").over(Window.partitionBy(*by, c)) - 1) / 2

    ranked = pairs.select(*by, "gold", "score", rank("gold").alias("rg"), rank("score").alias("rs"))
    return ranked.groupBy(*by).agg(F.corr("gold", "score").alias("pearson"), F.corr("rg", "rs").alias("spearman"))


def gain(results: DataFrame, by: list[str], base: str = "none") -> DataFrame:
    """Each method's value over that of no correction."""
    zero = results.where(F.col("method") == base).select(*by, F.col("value").alias("base"))
    return results.join(zero, by).select(*by, "method", "value", (F.col("value") - F.col("base")).alias("gain"))


def restoration(tokens: DataFrame, by: list[str] | None = None) -> DataFrame:
    """Word-level precision, recall, F1 against the clean word, from ``clean_word, noisy_word, fixed_word``."""
    changed = F.col("fixed_word") != F.col("noisy_word")
    wrong = F.col("noisy_word") != F.col("clean_word")
    right = F.col("fixed_word") == F.col("clean_word")
    s = tokens.groupBy(*(by or [])).agg(F.count("*").alias("tokens"), _count(wrong).alias("noisy"), _count(changed).alias("changed"), _count(changed & right).alias("restored"))
    p, r = _ratio(F.col("restored").cast("double"), F.col("changed").cast("double")), _ratio(F.col("restored").cast("double"), F.col("noisy").cast("double"))
    return s.select("*", p.alias("precision"), r.alias("recall"), _ratio(2 * p * r, p + r).alias("f1"))


def edge_quality(edges: DataFrame, truth: DataFrame) -> DataFrame:
    """Precision and recall of edges against true pairs (both ``src, dst``)."""
    both = edges.select("src", "dst").distinct().withColumn("found", F.lit(True)).join(truth.select("src", "dst").distinct().withColumn("true", F.lit(True)), ["src", "dst"], "full")
    hit, found, true = _count(F.col("found") & F.col("true")), _count(F.col("found").isNotNull()), _count(F.col("true").isNotNull())
    return both.agg(found.alias("found"), true.alias("expected"), hit.alias("hit")).select("*", _ratio(F.col("hit").cast("double"), F.col("found").cast("double")).alias("precision"), _ratio(F.col("hit").cast("double"), F.col("expected").cast("double")).alias("recall"))


def component_edit_profile(norm: DataFrame) -> DataFrame:
    """Words of groups by their edit distance from the representative."""
    return norm.where("word != rep_word").groupBy(F.levenshtein("word", "rep_word").cast("long").alias("distance")).agg(F.count("*").alias("words"), F.sum("freq").alias("occurrences"))


def link_patterns(norm: DataFrame) -> DataFrame:
    """How links look: repeated letters, one letter added at an end, a final s, one letter changed (to its neighbour on a keyboard), letters beyond ASCII."""
    from lexnorm.baselines.edit import NEIGHBOURS

    w, r = F.col("word"), F.col("rep_word")
    squeeze = lambda x: F.regexp_replace(x, r"(.)\1+", "$1")
    long, short = F.when(F.length(w) > F.length(r), w).otherwise(r), F.when(F.length(w) > F.length(r), r).otherwise(w)
    flags = {
        "repeated_letters": squeeze(w) == squeeze(r),
        "one_letter_prefix": (F.length(long) == F.length(short) + 1) & (F.substring(long, F.lit(2), F.length(short)) == short),
        "one_letter_suffix": (F.length(long) == F.length(short) + 1) & F.startswith(long, short),
        "final_s": long == F.concat(short, F.lit("s")),
        "one_letter_changed": (F.length(w) == F.length(r)) & (F.levenshtein(w, r) == 1),
        "keyboard_neighbour": (F.length(w) == F.length(r)) & (F.levenshtein(w, r) == 1) & F.arrays_overlap(F.zip_with(F.split(w, ""), F.split(r, ""), lambda x, y: F.when(x != y, F.concat(x, y)).otherwise("")), F.array(*(F.lit(a + b) for a, b in sorted(NEIGHBOURS)))),
        "beyond_ascii": F.regexp_replace(w, r"[^\x00-\x7f]", "") == F.regexp_replace(r, r"[^\x00-\x7f]", ""),
    }
    return norm.where("word != rep_word").agg(F.count("*").alias("links"), *(_count(v).alias(k) for k, v in flags.items()))


def case_study(norm: DataFrame, k: int = 20) -> DataFrame:
    """The ``k`` groups with the most occurrences beside their representative's."""
    from lexnorm.operators.vocabulary import as_lists

    top = norm.where("size > 1").groupBy("rep_word").agg(F.sum(F.when(F.col("word") != F.col("rep_word"), F.col("freq")).otherwise(0)).alias("moved")).orderBy(F.desc("moved"), "rep_word").limit(k)
    return as_lists(norm.join(F.broadcast(top), "rep_word", "left_semi"))


def speedup(times: DataFrame, base: str) -> DataFrame:
    """Seconds of each method over those of ``base``, by phase."""
    b = times.where(F.col("method") == base).select("phase", F.col("seconds").alias("base"))
    return times.join(b, "phase").select("phase", "method", "seconds", (F.col("seconds") / F.col("base")).alias("ratio"))
