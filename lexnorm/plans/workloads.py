"""The experiment workloads over the given tables."""

from __future__ import annotations

import time
from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from lexnorm.baselines import cosine, edit
from lexnorm.config import HashParams
from lexnorm.functions import hashing, metrics, tokens
from lexnorm.operators import graph, infer, vocabulary
from lexnorm.operators.components import components
from lexnorm.plans import perturb
from lexnorm.plans.index import Index, build_index
from lexnorm.sources.store import materialise, table

RATES = (20, 40, 60)
#: Dictionary of accepted words: seen so often at least.
ACCEPTED = 3
#: Parameters for attaching structured spellings.
INFER = HashParams(bins=2, alpha="0.4")
METHODS = ("none", "hash_graph", "edit_index", "edit_enumerate", "word_vectors", "subword_vectors")


def sentences(spark: SparkSession, d: str, name: str) -> DataFrame:
    """``id, text`` of a table's texts."""
    t = table(spark, d, name)
    key = {"documents": F.col("doc_id"), "benchmark": F.col("item_id"), "conversations": F.col("conv_id") * 1000 + F.col("turn")}[name]
    return t.select(key.alias("id"), "text")


def dictionary(spark: SparkSession, d: str, least: int = ACCEPTED) -> DataFrame:
    """``word, score``."""
    return tokens.vocabulary(table(spark, d, "documents"), min_freq=least).withColumnRenamed("freq", "score")


def index_corpus(spark: SparkSession, d: str, name: str = "documents", params: HashParams = HashParams()) -> Index:
    return build_index(tokens.vocabulary(table(spark, d, name)), params)


def corrections(method: str, words: DataFrame, accepted: DataFrame, documents: DataFrame, params: HashParams = INFER, times_col: str | None = None) -> DataFrame:
    """``word, corrected`` of distinct words by one method, against the accepted words. A row of ``documents`` counts as ``times_col`` equal rows."""
    if method == "none":
        return edit.identity(words)
    if method == "hash_graph":
        index = build_index(accepted.select("word", F.col("score").alias("freq")), params, method="task", split_star=True)
        return infer.attach(words, index).select("word", F.when(F.col("status") == "known", F.col("word")).otherwise(F.col("rep_word")).alias("corrected"))
    if method == "edit_index":
        return edit.deletion_index(words, accepted, k=1).select("word", "corrected")
    if method == "edit_enumerate":
        return edit.enumerate_edits(words, accepted, k=1).select("word", "corrected")
    vectors = None
    if method == "word_vectors":
        vectors = cosine.word_vectors(documents, times_col=times_col, wanted=words.select("word").unionByName(accepted.select("word")).distinct())
    return cosine.correct(words, accepted, vectors=vectors).select("word", "corrected")


_swaps: dict[tuple, DataFrame] = {}


def swaps(spark: SparkSession, d: str, name: str, methods: tuple[str, ...] = METHODS, rates: tuple[int, ...] = RATES, seed: int = 13, among: DataFrame | None = None) -> DataFrame:
    """``method, noisy_word, corrected`` of all words of a table perturbed at any of the rates.

    Word vectors see the perturbed texts of all rows too, so that misspelt words have some. One table serves all tasks of an
    application. Where there is none yet, a task that reads the rows of the ids ``among`` only can have their words corrected.
    """
    key = (spark.sparkContext.applicationId, d, name, methods, rates, seed)
    if key in _swaps:
        return _swaps[key]
    # A text has the same changes at each rate that selects it: it is changed once and counts as often.
    rows = sentences(spark, d, name)
    once = lambda frame: perturb.noise(frame, "id", "text", max(rates), seed).withColumn("times", sum((perturb.selected(F.col("id"), r, seed).cast("int") for r in rates), F.lit(0)))
    asked = once(rows if among is None else rows.join(among.select("id").distinct(), "id", "left_semi"))
    kept = F.when(F.col("times") < len(rates), F.col("clean_words")).otherwise(F.array().cast("array<string>"))
    words = asked.select(F.explode(F.when(F.col("times") > 0, F.concat("noisy_words", kept)).otherwise(kept)).alias("word"))
    words = materialise(words.distinct(), "noisy_words")
    accepted = materialise(dictionary(spark, d), "accepted")
    texts = table(spark, d, "documents").select("text", F.lit(1).alias("times"))
    if "word_vectors" in methods:
        texts = texts.unionByName(materialise(once(rows).where("times > 0").select(F.col("noisy").alias("text"), "times"), "noisy_texts"))
    out = None
    for method in methods:
        one = corrections(method, words, accepted, texts, times_col="times").select(F.lit(method).alias("method"), F.col("word").alias("noisy_word"), "corrected")
        out = one if out is None else out.unionByName(one)
    out = materialise(out, "swaps")
    if among is None:
        _swaps[key] = out
    return out


def noisy_tokens(spark: SparkSession, d: str, name: str, rate: int, seed: int = 13, ops: tuple[str, ...] = ("delete", "replace")) -> DataFrame:
    return perturb.aligned(perturb.noise(sentences(spark, d, name), "id", "text", rate, seed, ops))


def restoration(spark: SparkSession, d: str, name: str = "benchmark", rates: tuple[int, ...] = RATES, methods: tuple[str, ...] = METHODS, ops: tuple[str, ...] = ("delete", "replace")) -> DataFrame:
    """``method, rate`` and word-level restoration against the known clean words."""
    accepted = materialise(dictionary(spark, d), "accepted")
    docs = table(spark, d, "documents")
    out = None
    for rate in rates:
        rows = materialise(noisy_tokens(spark, d, name, rate, ops=ops), "noisy")
        words = rows.select(F.col("noisy_word").alias("word")).distinct()
        for method in methods:
            fixed = corrections(method, words, accepted, docs).withColumnRenamed("word", "noisy_word")
            joined = rows.join(fixed, "noisy_word", "left").withColumn("fixed_word", F.coalesce("corrected", "noisy_word"))
            one = metrics.restoration(joined).select(F.lit(method).alias("method"), F.lit(rate).alias("rate"), "*")
            out = one if out is None else out.unionByName(one)
    return out


def coverage_by_alpha(spark: SparkSession, d: str, name: str = "documents", alphas: tuple[str, ...] = ("0", "0.05", "0.1", "0.15", "0.2", "0.3", "0.5", "1"), params: HashParams = HashParams()) -> DataFrame:
    """Four coverages, groups and the largest one for each threshold.

    One pass makes all edges of the lowest counted weight; higher thresholds
    filter it. Threshold one and below need connectivity only, so bucket stars do.
    """
    vocab = materialise(tokens.vocabulary(table(spark, d, name)), "vocab")
    sigs = materialise(hashing.signatures(vocab, hashing.Family.draw(params)), "sigs")
    weights = {a: HashParams(alpha=a, repetitions=params.repetitions).index_min for a in alphas}
    counted = [w for w in weights.values() if w > 1]
    edges = materialise(graph.edge_weights(sigs, params.repetitions, min(counted), "prefix"), "edges") if counted else None
    stars = materialise(graph.edge_weights(sigs, params.repetitions, 1, "union"), "edges") if len(counted) < len(weights) else None
    by_weight, out = {}, None
    for alpha, w in weights.items():
        if w not in by_weight:
            kept = stars if w <= 1 else graph.prune(edges, w)
            norm = materialise(vocabulary.build(vocab, components(kept)), "norm")
            sizes = norm.where("size > 1").agg(F.countDistinct("comp").alias("groups")), norm.agg(F.max("size").alias("largest"))
            by_weight[w] = metrics.coverage(norm).crossJoin(F.broadcast(sizes[0])).crossJoin(F.broadcast(sizes[1]))
        one = by_weight[w].select(F.lit(alpha).alias("alpha"), "*")
        out = one if out is None else out.unionByName(one)
    return out.select("alpha", *(F.round(c, 8).alias(c) for c in ("grouped_words", "grouped_occurrences", "changed_words", "changed_occurrences")), "groups", "largest")


def human_eval(spark: SparkSession, d: str, name: str, rate: int = 40, n: int = 100, raters: int = 5, seed: int = 13, methods: tuple[str, ...] = METHODS, vote: str = "label") -> DataFrame:
    """Simulated reviewers over a hundred sentences (the workload's own number): a correction is good if it
    brings the sentence nearer to the clean one, neutral if as near, bad if farther; five in a hundred labels flip, three are unsure."""
    picked = sentences(spark, d, name).where(F.length("text") > 0).withColumn("o", perturb.draw(F.lit(seed), F.col("id"), F.lit("pick"))).orderBy("o", "id").limit(n).drop("o")
    noised = materialise(perturb.noise(picked, "id", "text", rate, seed, ("delete", "replace", "elongate", "prefix", "accent")), "noised")
    accepted = materialise(dictionary(spark, d), "accepted")
    needs = noised.select(F.lit(name).alias("dataset"), F.col("id").alias("sentence_id"), F.col("selected").alias("needs_fix"))
    words = noised.select(F.explode("noisy_words").alias("word")).distinct()
    docs = table(spark, d, "documents")
    flat = perturb.aligned(noised)
    out = None
    for method in methods:
        fixed = flat.join(corrections(method, words, accepted, docs).withColumnRenamed("word", "noisy_word"), "noisy_word", "left").withColumn("fixed_word", F.coalesce("corrected", "noisy_word"))
        sums = fixed.groupBy("id").agg(F.sum(F.levenshtein("clean_word", "noisy_word")).alias("before"), F.sum(F.levenshtein("clean_word", "fixed_word")).alias("after"), F.max((F.col("fixed_word") != F.col("noisy_word")).cast("int")).alias("touched"))
        truth = F.when(F.col("after") < F.col("before"), 0).when(F.col("after") == F.col("before"), 1).otherwise(2)
        labels = F.array(F.lit(metrics.GOOD), F.lit(metrics.NEUTRAL), F.lit(metrics.BAD))
        voted = sums.select("*", F.explode(F.sequence(F.lit(1), F.lit(raters))).alias("reviewer"))
        key = [F.lit(seed), F.col("id"), F.col("reviewer")]
        flip = perturb.draw(*key, F.lit("flip")) % 100
        shifted = F.when(flip < 5, (truth + 1) % 3).otherwise(truth)
        label = F.when(perturb.draw(*key, F.lit("unsure")) % 100 < 3, F.lit(metrics.UNSURE)).otherwise(F.get(labels, shifted))
        judged = voted.select(F.lit(name).alias("dataset"), F.lit(method).alias("method"), F.col("id").alias("sentence_id"), "reviewer", (F.col("touched") == 1).alias("corrected"), label.alias("label"))
        out = judged if out is None else out.unionByName(judged)
    return metrics.human_prf(materialise(out, "judged"), needs, vote)


def classify(spark: SparkSession, d: str, target: str, methods: tuple[str, ...] = METHODS, rates: tuple[int, ...] = RATES, features: int = 1 << 16, seed: int = 13) -> DataFrame:
    """A linear bag-of-words classifier of ``labels.<target>``, trained on clean text, tested on noisy text after each correction.

    A trainable sum of word vectors before an affine map is such a classifier.
    """
    from pyspark.ml.classification import LogisticRegression
    from pyspark.ml.feature import HashingTF

    docs = table(spark, d, "documents")
    rows = docs.join(table(spark, d, "labels").where(F.col(target).isNotNull()), "doc_id").select(F.col("doc_id").alias("id"), "text", F.col(target).cast("double").alias("y"))
    part = perturb.draw(F.lit(seed), F.col("id"), F.lit("split")) % 10
    train = rows.where(part < 8).select(tokens.words(F.col("text")).alias("words"), "y")
    tf = HashingTF(numFeatures=features, inputCol="words", outputCol="x", binary=True)
    model = LogisticRegression(featuresCol="x", labelCol="y", maxIter=20, regParam=0.01).fit(tf.transform(train))
    test = rows.where(part == 9)
    flat = None
    for rate in rates:
        one = perturb.noise(test, "id", "text", rate, seed).select(F.lit(rate).alias("rate"), "id", F.explode("noisy_words").alias("noisy_word")).distinct()
        flat = one if flat is None else flat.unionByName(one)
    fixed = flat.join(swaps(spark, d, "documents", methods, rates, seed, among=test), "noisy_word").join(test.select("id", "y"), "id").groupBy("rate", "method", "id", "y").agg(F.collect_set("corrected").alias("words"))
    said = materialise(model.transform(tf.transform(fixed)).select("rate", "method", F.col("y").cast("int").alias("y"), F.col("prediction").cast("int").alias("yhat")), "said")
    return metrics.classification(said, ["rate", "method"]).select(F.lit(target).alias("task"), "rate", "method", "n", "accuracy", "f1", "matthews")


def sentiment(spark: SparkSession, d: str, target: str = "quality", methods: tuple[str, ...] = METHODS, dim: int = 256, seed: int = 13) -> DataFrame:
    """Validation and test accuracy after normalizing all text: a linear model over ``dim`` hashed word sums."""
    from pyspark.ml.classification import LogisticRegression
    from pyspark.ml.feature import HashingTF
    from pyspark.ml.functions import array_to_vector, vector_to_array

    docs = table(spark, d, "documents")
    accepted = materialise(dictionary(spark, d), "accepted")
    rows = docs.join(table(spark, d, "labels"), "doc_id").select(F.col("doc_id").alias("id"), tokens.words(F.col("text")).alias("words"), F.col(target).cast("double").alias("y"), (perturb.draw(F.lit(seed), F.col("doc_id"), F.lit("split")) % 10).alias("part"))
    flat = materialise(rows.select("id", "y", "part", F.explode("words").alias("word")), "flat")
    asked = materialise(flat.select("word").distinct(), "words")
    rare = asked.join(accepted.select("word"), "word", "left_anti").withColumn("rare", F.lit(True))
    # No method changes accepted words: they are joined and summed once, and each method adds the other words' sums.
    summed = lambda frame: HashingTF(numFeatures=dim, inputCol="words", outputCol="v").transform(frame).withColumn("v", vector_to_array("v"))
    parted = flat.join(rare, "word", "left").groupBy("id", "y", "part").agg(F.collect_list(F.when(F.col("rare").isNull(), F.col("word"))).alias("words"), F.collect_list(F.when(F.col("rare"), F.col("word"))).alias("rare"))
    base = materialise(summed(parted).select(F.monotonically_increasing_id().alias("row"), "y", "part", "v", "rare"), "base")
    found = base.select("row", F.explode("rare").alias("word"))
    out = None
    for method in methods:
        swap = corrections(method, asked, accepted, docs)
        more = summed(found.join(swap, "word", "left").groupBy("row").agg(F.collect_list(F.coalesce("corrected", "word")).alias("words"))).select("row", F.col("v").alias("more"))
        both = base.select("row", "y", "part", "v").join(more, "row", "left")
        fixed = materialise(both.select("y", "part", array_to_vector(F.coalesce(F.zip_with("v", "more", lambda m, n: m + n), F.col("v"))).alias("x")), "fixed")
        model = LogisticRegression(featuresCol="x", labelCol="y", maxIter=30).fit(fixed.where("part < 8"))
        said = model.transform(fixed.where("part >= 8")).select("part", (F.col("prediction") == F.col("y")).cast("int").alias("right"))
        one = said.agg(F.avg(F.when(F.col("part") == 8, F.col("right"))).alias("valid_accuracy"), F.avg(F.when(F.col("part") == 9, F.col("right"))).alias("test_accuracy")).select(F.lit(target).alias("target"), F.lit(method).alias("method"), "*")
        out = one if out is None else out.unionByName(one)
    return out


def _pairs(spark: SparkSession, d: str, least: float = 0.8) -> DataFrame:
    """Document pairs with exact word-set similarity: near copies, and neighbours in id order.

    Two sets of similarity ``least`` share one of their rarest words. Documents that
    share such a word are tried with the smallest of them only, so a group of copies
    of any size gives as many pairs as it has members.
    """
    sets = materialise(table(spark, d, "documents").select(F.col("doc_id").alias("id"), F.array_distinct(tokens.words(F.col("text"))).alias("words")), "sets")
    flat = sets.select("id", F.size("words").alias("n"), F.explode("words").alias("word"))
    counts = flat.groupBy("word").agg(F.count("*").alias("df"))
    ordered = flat.join(counts, "word").groupBy("id", "n").agg(F.array_sort(F.collect_list(F.struct("df", "word"))).alias("o"))
    rare = ordered.select("id", F.explode(F.slice("o", F.lit(1), F.col("n") - F.ceil(F.col("n") * least - 1e-6).cast("int") + 1)).alias("g")).select("id", F.col("g.word").alias("word"))
    heads = rare.groupBy("word").agg(F.min("id").alias("id1"), F.max("id").alias("last")).where("id1 < last").drop("last")
    near = rare.join(heads, "word").where("id1 < id").select("id1", F.col("id").alias("id2")).distinct()
    far = sets.select(F.col("id").alias("id1"), (F.col("id") + 1).alias("id2"))
    a, b = sets.select(F.col("id").alias("id1"), F.col("words").alias("wa")), sets.select(F.col("id").alias("id2"), F.col("words").alias("wb"))
    shared = F.size(F.array_intersect("wa", "wb"))
    every = F.size("wa") + F.size("wb") - shared
    gold = F.when(every > 0, shared / every).otherwise(0.0).alias("gold")
    scored = lambda pairs: pairs.join(a, "id1").join(b, "id2").select("id1", "id2", gold)
    return scored(near).where(F.col("gold") >= least).unionByName(scored(far)).distinct()


def pair_tasks(spark: SparkSession, d: str, methods: tuple[str, ...] = METHODS, rates: tuple[int, ...] = RATES, seed: int = 13) -> DataFrame:
    """Paraphrase (accuracy, F1 at similarity .5), similarity (Pearson, Spearman) and containment of benchmark passages (accuracy), by method and rate."""
    pairs = materialise(_pairs(spark, d), "pairs")
    clean = materialise(sentences(spark, d, "documents").select("id", tokens.words(F.col("text")).alias("words")), "clean")
    items = table(spark, d, "benchmark").select(tokens.words(F.col("text")).alias("w"))
    grams = lambda w: F.when(F.size(w) >= 8, F.transform(F.sequence(F.lit(1), F.size(w) - 7), lambda i: F.array_join(F.slice(w, i, 8), " "))).otherwise(F.array().cast("array<string>"))
    shingles = F.broadcast(items.select(F.explode(grams(F.col("w"))).alias("g")).distinct())
    holds = lambda frame: frame.select("id", F.explode(grams(F.col("words"))).alias("g")).join(shingles, "g", "left_semi").select("id").distinct()
    truth = materialise(holds(clean), "truth")
    noised = None
    for rate in rates:
        one = perturb.noise(sentences(spark, d, "documents"), "id", "text", rate, seed).select(F.lit(rate).alias("rate"), "id", F.posexplode_outer("noisy_words").alias("pos", "noisy_word"))
        noised = one if noised is None else noised.unionByName(one)
    swap = swaps(spark, d, "documents", methods, rates, seed)
    every = F.broadcast(swap.select("method").distinct())
    word = F.struct("pos", F.coalesce("corrected", "noisy_word").alias("w"))
    full = noised.crossJoin(every).join(swap, ["method", "noisy_word"], "left")
    by = ["rate", "method"]
    fixed = materialise(full.groupBy(*by, "id").agg(F.transform(F.array_sort(F.collect_list(F.when(F.col("pos").isNotNull(), word))), lambda x: x["w"]).alias("words")), "fixed")
    a = clean.select(F.col("id").alias("id1"), F.array_distinct("words").alias("wa"))
    b = fixed.select(*by, F.col("id").alias("id2"), F.array_distinct("words").alias("wb"))
    both = pairs.join(a, "id1").join(b, "id2")
    shared = F.size(F.array_intersect("wa", "wb"))
    score = F.when(F.size("wa") + F.size("wb") > 0, shared / (F.size("wa") + F.size("wb") - shared)).otherwise(0.0)
    scored = materialise(both.select(*by, "gold", score.alias("score")), "scored")
    c = metrics.classification(scored.select(*by, (F.col("gold") >= 0.5).cast("int").alias("y"), (F.col("score") >= 0.5).cast("int").alias("yhat")), by)
    corr = metrics.correlations(scored, by)
    grams_found = fixed.select(*by, "id", F.explode(grams(F.col("words"))).alias("g")).join(shingles, "g", "left_semi").select(*by, "id").distinct().withColumn("yhat", F.lit(1))
    judged = fixed.select(*by, "id").join(grams_found, [*by, "id"], "left").join(truth.withColumn("y", F.lit(1)), "id", "left")
    held = metrics.classification(judged.select(*by, F.coalesce("y", F.lit(0)).alias("y"), F.coalesce("yhat", F.lit(0)).alias("yhat")), by)
    row = lambda frame, task, names: frame.select(F.lit(task).alias("task"), *by, F.explode(F.array(*(F.struct(F.lit(n).alias("metric"), F.col(n).alias("value")) for n in names))).alias("m")).select("task", *by, "m.metric", "m.value")
    return row(c, "paraphrase", ("accuracy", "f1")).unionByName(row(corr, "similarity", ("pearson", "spearman"))).unionByName(row(held, "containment", ("accuracy",)))


def noise_grid(spark: SparkSession, d: str, methods: tuple[str, ...] = METHODS, rates: tuple[int, ...] = RATES) -> DataFrame:
    """All downstream tasks by rate and method, with the gain over no correction."""
    pairs = pair_tasks(spark, d, methods, rates)
    out = pairs
    for target, names in (("quality", ("matthews",)), ("toxic", ("accuracy",))):
        c = classify(spark, d, target, methods, rates)
        for n in names:
            out = out.unionByName(c.select("task", "rate", "method", F.lit(n).alias("metric"), F.col(n).alias("value")))
    return metrics.gain(materialise(out, "grid"), ["task", "rate", "metric"])


def search_recall(spark: SparkSession, d: str, rate: int = 60, k: int = 10, methods: tuple[str, ...] = METHODS, seed: int = 13) -> DataFrame:
    """Product search: noisy titles as queries for the titles they come from, before and after correction.

    Each part sold is a query; titles of equal words are one target, so a hit is a title with the query's word set among the best ``k``.
    """
    parts = table(spark, d, "part").join(table(spark, d, "lineitem").select(F.col("l_partkey").alias("p_partkey")).distinct(), "p_partkey", "left_semi")
    titles = parts.select(F.array_join(F.array_sort(F.array_distinct(tokens.words(F.col("p_name")))), " ").alias("title"), "p_partkey")
    targets = materialise(titles.groupBy("title").agg(F.min("p_partkey").alias("target"), F.count("*").alias("n")), "targets")
    posting = targets.select("target", F.explode(F.split("title", " ")).alias("word"), F.size(F.split("title", " ")).alias("size"))
    noised = materialise(perturb.noise(targets.select(F.col("target").alias("id"), F.col("title").alias("text")), "id", "text", rate, seed), "noised")
    accepted = materialise(posting.groupBy("word").agg(F.count("*").alias("score")), "accepted")
    flat = materialise(perturb.aligned(noised), "flat")
    words = flat.select(F.col("noisy_word").alias("word")).distinct()
    from pyspark.sql import Window

    out = None
    for method in methods:
        if method == "word_vectors":
            swap = edit.identity(words)  # no vectors are learnt from titles: unknown words have none
        else:
            swap = corrections(method, words, accepted, table(spark, d, "documents"))
        asked = flat.join(swap.withColumnRenamed("word", "noisy_word"), "noisy_word", "left").select("id", F.coalesce("corrected", "noisy_word").alias("word")).distinct()
        hits = asked.join(posting, "word").groupBy("id", "target").agg((F.count("*") / F.max("size")).alias("share"), F.count("*").alias("common"))
        top = hits.withColumn("r", F.row_number().over(Window.partitionBy("id").orderBy(F.desc("common"), F.desc("share"), "target"))).where(F.col("r") <= k)
        right = top.where("id = target").select("id").withColumn("hit", F.lit(1))
        one = noised.select("id").join(right, "id", "left").agg(F.count("*").alias("queries"), F.avg(F.coalesce("hit", F.lit(0))).alias("recall")).select(F.lit(method).alias("method"), "*")
        out = one if out is None else out.unionByName(one)
    return out


def timed(run: Callable[[], DataFrame]) -> float:
    """Seconds to compute a frame without keeping it."""
    start = time.time()
    run().write.format("noop").mode("overwrite").save()
    return time.time() - start


def time_phases(spark: SparkSession, d: str, params: HashParams = HashParams()) -> dict[str, float]:
    """Seconds of indexing (words are extracted beforehand) and of inference over the second corpus's words."""
    vocab = materialise(tokens.vocabulary(table(spark, d, "documents")), "vocab")
    start = time.time()
    index = build_index(vocab, params)
    took = time.time() - start
    asked = materialise(tokens.vocabulary(table(spark, d, "conversations")), "asked")
    return {"index": took, "inference": timed(lambda: infer.attach(asked, index))}


def scale_curve(spark: SparkSession, folders: list[str], params: HashParams = HashParams()) -> DataFrame:
    """Words and seconds of both phases at each scale."""
    rows = []
    for d in folders:
        t = time_phases(spark, d, params)
        rows.append((d, tokens.vocabulary(table(spark, d, "documents")).count(), t["index"], t["inference"]))
    return spark.createDataFrame(rows, "folder string, words long, index_seconds double, inference_seconds double")
