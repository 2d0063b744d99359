"""All queries of the engine by name, with DuckDB SQL where it can say the same."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from lexnorm.baselines import cosine, edit
from lexnorm.config import HashParams
from lexnorm.functions import hashing, metrics, shingles, theory, tokens
from lexnorm.operators import buckets, graph, infer, rewrite, vocabulary
from lexnorm.operators.components import components
from lexnorm.plans import oracle as sql
from lexnorm.plans import perturb, relational, sqlapi, workloads
from lexnorm.plans.index import Index, build_index
from lexnorm.sources.store import materialise, table
from lexnorm.streaming import jobs

P = HashParams()
FAMILY = hashing.Family.draw(P)
#: A stricter index for demonstrations on a dense vocabulary.
QUALITY = HashParams(alpha="0.4")
JACCARD = 0.7
#: Words of abuse that the given texts hold (fixed values).
TOXIC = ("idiot", "moron", "scum", "loser", "clown", "worthless", "pathetic")

_indexes: dict[tuple, Index] = {}


def index(spark: SparkSession, d: str, params: HashParams = P) -> Index:
    """The documents' index, built once for an application."""
    key = (spark.sparkContext.applicationId, d, params)
    if key not in _indexes:
        _indexes[key] = workloads.index_corpus(spark, d, "documents", params)
    return _indexes[key]


def _vocab(spark: SparkSession, d: str) -> DataFrame:
    return tokens.vocabulary(table(spark, d, "documents"))


def _unseen(spark: SparkSession, d: str, name: str) -> DataFrame:
    return tokens.vocabulary(table(spark, d, name)).select("word")


def gram_sets(spark, d):
    g = shingles.gram_set(F.col("word"), P.char_lens)
    return _vocab(spark, d).select("word", F.size(g).cast("long").alias("n"), F.array_join(F.array_sort(g), " ").alias("grams"))


def gram_sets_all(spark, d):
    g = shingles.gram_set(F.col("word"), "all")
    return _vocab(spark, d).select("word", F.size(g).cast("long").alias("n"))


def fingerprints(spark, d):
    g = _vocab(spark, d).select(F.explode(shingles.gram_set(F.col("word"), P.char_lens)).alias("gram")).distinct()
    return g.select("gram", hashing.fingerprint(F.col("gram")).alias("x"))


def bin_minima(spark, d):
    return hashing.bin_minima(_vocab(spark, d), FAMILY).select("word", F.col("rep").cast("long").alias("rep"), *(f"m{k}" for k in range(P.bins)))


UNIVERSE = HashParams(bin_space="universe")


def bin_minima_universe(spark, d):
    return hashing.bin_minima(_vocab(spark, d), hashing.Family.draw(UNIVERSE)).select("word", F.col("rep").cast("long").alias("rep"), *(f"m{k}" for k in range(P.bins)))


def densified(spark, d):
    return hashing.densified(hashing.bin_minima(_vocab(spark, d), FAMILY), FAMILY).select("word", F.col("rep").cast("long").alias("rep"), *(f"d{k}" for k in range(P.bins)))


def _joined_sigs(sigs):
    return sigs.select("word", F.array_join(F.col("sig").cast("array<string>"), ",").alias("sig"))


def signatures(spark, d):
    return _joined_sigs(hashing.signatures(_vocab(spark, d), FAMILY))


def signatures_relational(spark, d):
    return _joined_sigs(hashing.signatures(_vocab(spark, d), FAMILY, "relational"))


VARIANTS = {
    "signatures_single_bin": HashParams(bins=1),
    "signatures_left": HashParams(densify="left"),
    "signatures_right": HashParams(densify="right"),
    "signatures_offset": HashParams(densify="coin_offset"),
    "signatures_one_repetition": HashParams(repetitions=1),
    "signatures_bigrams": HashParams(char_lens=(2, 3)),
    "signatures_all_lengths": HashParams(char_lens="all", repetitions=5),
}


def _variant(params):
    return lambda spark, d: _joined_sigs(hashing.signatures(_vocab(spark, d), hashing.Family.draw(params)))


def signatures_permutations(spark, d):
    return _joined_sigs(hashing.signatures(_vocab(spark, d), hashing.Family.draw(HashParams(scheme="kperm"))))


def signatures_wide(spark, d):
    return _joined_sigs(hashing.signatures(_vocab(spark, d), hashing.Family.draw(HashParams(width=62))))


def bucket_stats(spark, d):
    return buckets.profiles(index(spark, d).sigs, P.repetitions).select(F.col("rep").cast("long").alias("rep"), "buckets", "words", "largest", "pairs")


def edge_weights(spark, d):
    return graph.edge_weights(index(spark, d).sigs, P.repetitions, P.index_min, "pairs").select("src", "dst", F.col("weight").cast("long").alias("weight"))


def edges_prefix(spark, d):
    return index(spark, d).edges.select("src", "dst", F.col("weight").cast("long").alias("weight"))


def edges_pruned(spark, d):
    # Pairs of the higher weight alone: pruning the edges of the lower one leaves the same.
    ix = index(spark, d)
    weighed = graph.edge_weights(ix.sigs, P.repetitions, QUALITY.index_min) if ix.made_edges is None else ix.edges
    return graph.prune(weighed, QUALITY.index_min).select("src", "dst", F.col("weight").cast("long").alias("weight"))


def edges_union_alpha0(spark, d):
    vocab = index(spark, d).vocab
    stars = graph.edge_weights(index(spark, d).sigs, P.repetitions, 1, "union")
    # Each group is one star around its least word: no rounds are needed.
    groups = vocab.select("word").join(stars.select("src", F.col("dst").alias("word")), "word", "left").select(F.coalesce("src", "word").alias("comp"))
    return groups.groupBy("comp").agg(F.count("*").alias("size"))


def edges_intersect_alpha1(spark, d):
    return graph.edge_weights(index(spark, d).sigs, P.repetitions, P.repetitions, "intersect").select("src", "dst", F.col("weight").cast("long").alias("weight"))


def components_star(spark, d):
    ix = index(spark, d)
    return components(ix.links, ix.vocab.select(F.col("word").alias("node")), "star")


def components_hash_min(spark, d):
    ix = index(spark, d)
    return components(ix.links, ix.vocab.select(F.col("word").alias("node")), "hash_min")


def components_driver(spark, d):
    ix = index(spark, d)
    return components(ix.links, ix.vocab.select(F.col("word").alias("node")), "driver")


def representatives(spark, d):
    return index(spark, d).norm.where("size > 1").select("comp", "rep_word", "rep_freq", "size").distinct()


def norm_map(spark, d):
    return index(spark, d).norm


def norm_lists(spark, d):
    return vocabulary.as_lists(index(spark, d, QUALITY).norm).select("rep_word", "rep_freq", "size", F.array_join("members", " ").alias("members"))


def component_sizes(spark, d):
    return vocabulary.size_profile(index(spark, d).norm)


def index_documents(spark, d):
    """The whole index from text, afresh: representatives and group sizes."""
    return workloads.index_corpus(spark, d).norm.select("word", "rep_word", "size")


def index_conversations(spark, d):
    return workloads.index_corpus(spark, d, "conversations").norm.select("word", "rep_word", "size")


def index_both(spark, d):
    """One index over both corpora."""
    both = table(spark, d, "documents").select("text").unionByName(table(spark, d, "conversations").select("text"))
    return build_index(tokens.vocabulary(both)).norm.select("word", "rep_word", "size")


def index_counters(spark, d):
    return index(spark, d).stats()


def index_verified(spark, d):
    """Edges that also have exact similarity 0.5, with their groups."""
    ix = index(spark, d)
    return graph.verified(ix.edges, P.char_lens, 0.5).select("src", "dst", F.col("weight").cast("long").alias("weight"))


def index_star_split(spark, d):
    ix = index(spark, d)
    return graph.star_split(ix.edges, ix.norm).select("src", "dst", F.col("weight").cast("long").alias("weight"))


def index_extended(spark, d):
    """Conversations' words added to the documents' index: the same groups as one index of both."""
    more = tokens.vocabulary(table(spark, d, "conversations"))
    return index(spark, d, QUALITY).extend(more).norm.select("word", "freq", "rep_word", "size")


def infer_known(spark, d):
    return infer.attach(_unseen(spark, d, "conversations"), index(spark, d)).where("status = 'known'").select("word", "rep_word")


def _attached(frame):
    return frame.select("word", "matched", F.col("weight").cast("long").alias("weight"), "rep_word", "status")


def infer_attach_strict(spark, d):
    return _attached(infer.attach(_unseen(spark, d, "conversations"), index(spark, d)))


def infer_attach_inclusive(spark, d):
    return _attached(infer.attach(_unseen(spark, d, "conversations"), index(spark, d), inclusive=True))


def infer_benchmark(spark, d):
    return _attached(infer.attach(_unseen(spark, d, "benchmark"), index(spark, d)))


def infer_unmatched(spark, d):
    return infer.attach(_unseen(spark, d, "conversations"), index(spark, d)).where("status = 'unmatched'").select("word")


def infer_grouped_targets(spark, d):
    return _attached(infer.attach(_unseen(spark, d, "conversations"), index(spark, d), targets="grouped")).groupBy("status").agg(F.count("*").alias("words"))


def _turns(spark, d):
    return workloads.sentences(spark, d, "conversations")


def _mapping(spark, d):
    return infer.attach(_unseen(spark, d, "conversations"), index(spark, d, QUALITY)).where("word != rep_word").select("word", "rep_word")


def rewrite_conversations(spark, d):
    out = rewrite.apply(_turns(spark, d), ["id"], "text", materialise(_mapping(spark, d), "mapping"))
    return out.select("id", "text", F.col("n_changed").cast("long").alias("n_changed"))


def rewrite_joined(spark, d):
    out = rewrite.apply(_turns(spark, d), ["id"], "text", materialise(_mapping(spark, d), "mapping"), "join")
    return out.select("id", "text", F.col("n_changed").cast("long").alias("n_changed"))


def rewrite_documents(spark, d):
    out = rewrite.apply(table(spark, d, "documents"), ["doc_id"], "text", vocabulary.as_map(index(spark, d, QUALITY).norm))
    return out.select("doc_id", "n_changed", F.md5("text").alias("text_md5"))


def dedup_after_norm(spark, d):
    """Groups of equal texts before and after rewriting."""
    docs = table(spark, d, "documents")
    new = rewrite.apply(docs, ["doc_id"], "text", vocabulary.as_map(index(spark, d, QUALITY).norm))
    groups = lambda frame, name, text: frame.groupBy(F.md5(text).alias("k")).count().where("count > 1").agg(F.count("*").alias("groups"), F.coalesce(F.sum("count"), F.lit(0)).alias("documents")).select(F.lit(name).alias("stage"), "groups", "documents")
    return groups(docs, "before", F.lower("text")).unionByName(groups(new, "after", F.col("text")))


def coverage_by_alpha(spark, d):
    return workloads.coverage_by_alpha(spark, d, "documents", HIGH)


def coverage_low_alpha(spark, d):
    """Thresholds at which one giant group holds nearly all words; SQL needs too much memory for these."""
    return workloads.coverage_by_alpha(spark, d, "documents", ("0", "0.05", "0.1"))


#: Thresholds that SQL can follow.
HIGH = ("0.15", "0.2", "0.3", "0.5", "1")


def coverage_conversations(spark, d):
    return workloads.coverage_by_alpha(spark, d, "conversations", ("0.1", "0.2", "0.3", "0.5"))


def case_components(spark, d):
    return metrics.case_study(index(spark, d, QUALITY).norm, 20).select("rep_word", "rep_freq", "size", F.array_join("members", " ").alias("members"))


def exact_jaccard_pairs(spark, d):
    return graph.exact_pairs(_vocab(spark, d), P.char_lens, JACCARD).select("src", "dst", F.round("jaccard", 8).alias("jaccard"))


def edge_quality(spark, d):
    truth = graph.exact_pairs(_vocab(spark, d), P.char_lens, JACCARD)
    return metrics.edge_quality(index(spark, d).edges, truth).select("found", "expected", "hit", F.round("precision", 8).alias("precision"), F.round("recall", 8).alias("recall"))


def collision_curve(spark, d):
    """Collision rates of all pairs of similar words; pairs below that similarity are too many to list."""
    pairs = graph.exact_pairs(_vocab(spark, d), P.char_lens, JACCARD)
    out = theory.collision_curve(index(spark, d).sigs, pairs, P.repetitions)
    return out.select(F.col("bin").cast("long").alias("bin"), "pairs", F.round("jaccard", 8).alias("jaccard"), F.round("rate", 8).alias("rate"))


def estimate_pq(spark, d):
    ix = index(spark, d)
    return theory.estimate_pq(ix.edges, index(spark, d, QUALITY).norm.select("word", F.col("comp").alias("cluster")), P.repetitions).select("inside", "pairs", F.round("least", 8).alias("least"), F.round("greatest", 8).alias("greatest"), F.round("mean", 8).alias("mean"))


_GRID = [(t, p, q, n, 100) for t in (5, 10, 20) for p, q in ((0.9, 0.01), (0.6, 0.02), (0.4, 0.05), (0.3, 0.1), (0.25, 0.15)) for n in (10, 20, 50)]
_FORMS = ("fp_printed", "fp_valid", "fp_exact", "fn_printed", "fn_peers", "fn_exact")


def error_bounds(spark, d):
    """Bounds for clusters as large as the groups of documents' words with the same first letters, by parameters."""
    sizes = shingles.same_prefix_groups(_vocab(spark, d)).select(F.col("words").cast("int").alias("c")).distinct()
    settings = spark.createDataFrame(_GRID, "t int, p double, q double, alpha_num int, alpha_den int")
    grid = sizes.crossJoin(F.broadcast(settings))
    return theory.bounds(grid).select(*(F.col(x).cast("long").alias(x) for x in ("c", "t", "alpha_num")), "p", "q", *(F.round(x, 9).alias(x) for x in _FORMS))


def cost_counters(spark, d):
    out = theory.cost(_vocab(spark, d), index(spark, d).sigs, P.repetitions)
    return out.select("words", "buckets", *(F.round(c, 4).alias(c) for c in ("mean_length", "mean_bucket", "hashing", "pairing", "enumeration")))


def component_edit_profile(spark, d):
    return metrics.component_edit_profile(index(spark, d, QUALITY).norm)


def link_patterns(spark, d):
    return metrics.link_patterns(index(spark, d, QUALITY).norm)


def sketch_counts(spark, d):
    """Count-min estimates beside true counts, by language: no estimate is below its count, and few are far above."""
    docs = table(spark, d, "documents")
    estimated = tokens.sketch_estimates(docs, tokens.sketch_counts(docs, by=["lang"]), ["lang"])
    over = F.col("estimate") - F.col("freq")
    return estimated.groupBy("lang").agg(F.count("*").alias("words"), F.min(over).alias("least_over"), F.max(over).alias("most_over"), F.avg(over).alias("mean_over"), (F.sum("freq") * 0.001).alias("bound"))


def same_prefix_groups(spark, d):
    out = shingles.same_prefix_groups(_vocab(spark, d))
    return out.select("stem", "words", "freq")


def collapsed_words(spark, d):
    return shingles.collapse(_vocab(spark, d), P.char_lens).where("members > 1").select("word", "hub", "members")


def _noised(rate):
    def run(spark, d):
        out = perturb.aligned(perturb.noise(_turns(spark, d), "id", "text", rate))
        return out.select("id", F.col("pos").cast("long").alias("pos"), "clean_word", "noisy_word")

    return run


def classification_metrics(spark, d):
    """Toxic documents told by a list of words: all scores of two-class prediction."""
    bad = F.array(*map(F.lit, TOXIC))
    rows = table(spark, d, "documents").join(table(spark, d, "labels"), "doc_id").select(F.col("toxic").alias("y"), F.arrays_overlap(tokens.words(F.col("text")), bad).cast("int").alias("yhat"))
    return metrics.classification(rows).select("n", *(F.round(c, 8).alias(c) for c in ("accuracy", "precision", "recall", "f1", "matthews")))


def rank_correlation(spark, d):
    """Pearson and Spearman of a part's price and size, by brand: ties take average ranks."""
    rows = table(spark, d, "part").select("p_brand", F.col("p_retailprice").alias("gold"), F.col("p_size").cast("double").alias("score"))
    return metrics.correlations(rows, ["p_brand"]).select("p_brand", F.round("pearson", 6).alias("pearson"), F.round("spearman", 6).alias("spearman"))


def _dictionary(spark, d):
    return workloads.dictionary(spark, d)


def _benchmark_words(spark, d):
    return _unseen(spark, d, "benchmark")


def _edit(frame):
    return frame.select("word", "corrected", F.col("distance").cast("long").alias("distance"))


def edit_deletion_index(spark, d):
    return _edit(edit.deletion_index(_benchmark_words(spark, d), _dictionary(spark, d), 2))


def edit_enumerate_k1(spark, d):
    return _edit(edit.enumerate_edits(_benchmark_words(spark, d), _dictionary(spark, d), 1))


def edit_enumerate_k2(spark, d):
    return _edit(edit.enumerate_edits(_benchmark_words(spark, d), _dictionary(spark, d), 2))


def edit_phonetic(spark, d):
    return _edit(edit.phonetic(_benchmark_words(spark, d), _dictionary(spark, d)))


def edit_distances(spark, d):
    """All distances between neighbours in the ordered list of words."""
    from pyspark.sql import Window

    words = _vocab(spark, d).withColumn("c", F.substring("word", 1, 1))
    pairs = words.withColumn("next", F.lead("word").over(Window.partitionBy("c").orderBy("word"))).where("next is not null").select("word", "next")
    kinds = {"lev": "lev", "dl": "damerau", "jw": "jaro_winkler"}
    return pairs.select("word", "next", *(F.round(edit.distance(F.col("word"), F.col("next"), k).cast("double"), 8).alias(n) for k, n in kinds.items()))


def edit_costs(spark, d):
    from pyspark.sql import Window

    words = _vocab(spark, d).withColumn("c", F.substring("word", 1, 1))
    pairs = words.withColumn("next", F.lead("word").over(Window.partitionBy("c").orderBy("word"))).where("next is not null")
    return pairs.select("word", "next", edit.distance(F.col("word"), F.col("next"), "keyboard").alias("keyboard"), edit.distance(F.col("word"), F.col("next"), "phonetic").alias("phonetic"))


def identity_correction(spark, d):
    return edit.identity(_unseen(spark, d, "benchmark"))


def _vectors(spark, d):
    e = table(spark, d, "embeddings").select(F.col("vec_id").alias("id"), F.col("embedding").alias("vec"))
    return e.where("id % 100 = 0"), e


def mips_exact(spark, d):
    out = cosine.search(*_vectors(spark, d), 10)
    return out.select("query_id", "id", F.round("score", 6).alias("score"), F.col("rank").cast("long").alias("rank"))


def mips_ivf(spark, d):
    return cosine.search(*_vectors(spark, d), 10, index="ivf")


def mips_recall(spark, d):
    q, e = _vectors(spark, d)
    return cosine.recall(cosine.search(q, e, 10, index="ivf"), cosine.search(q, e, 10))


def subword_vectors(spark, d):
    return cosine.subword_vectors(_unseen(spark, d, "benchmark"))


def subword_correction(spark, d):
    return cosine.correct(_benchmark_words(spark, d), _dictionary(spark, d))


def word_vector_correction(spark, d):
    texts = table(spark, d, "documents").select("text").unionByName(table(spark, d, "benchmark").select("text"))
    return cosine.correct(_benchmark_words(spark, d), _dictionary(spark, d), vectors=cosine.word_vectors(texts))


def restoration_scores(spark, d):
    return workloads.restoration(spark, d)


def restoration_structured(spark, d):
    """Elongated, prefixed and accented spellings, the kinds the graph is good at."""
    return workloads.restoration(spark, d, rates=(60,), ops=("elongate", "prefix", "accent"))


def human_eval_documents(spark, d):
    return workloads.human_eval(spark, d, "documents")


def human_eval_conversations(spark, d):
    return workloads.human_eval(spark, d, "conversations", vote="majority")


def pair_tasks(spark, d):
    return workloads.pair_tasks(spark, d)


def acceptability_quality(spark, d):
    return workloads.classify(spark, d, "quality")


def sentiment_toxic(spark, d):
    return workloads.sentiment(spark, d, "toxic")


def noise_grid(spark, d):
    return workloads.noise_grid(spark, d)


def search_recall(spark, d):
    return workloads.search_recall(spark, d)


_LOCAL = (
    gram_sets, gram_sets_all, fingerprints, bin_minima, bin_minima_universe, densified, signatures, signatures_relational, signatures_permutations, signatures_wide, bucket_stats, edge_weights,
    edges_prefix, edges_pruned, edges_union_alpha0, edges_intersect_alpha1, components_star, components_hash_min, components_driver, representatives, norm_map, norm_lists, component_sizes,
    index_documents, index_conversations, index_both, index_counters, index_verified, index_star_split, index_extended, infer_known, infer_attach_strict, infer_attach_inclusive, infer_benchmark, infer_unmatched,
    infer_grouped_targets, rewrite_conversations, rewrite_joined, rewrite_documents, dedup_after_norm, coverage_by_alpha, coverage_low_alpha, coverage_conversations, case_components, exact_jaccard_pairs, edge_quality,
    collision_curve, estimate_pq, error_bounds, cost_counters, component_edit_profile, link_patterns, sketch_counts, same_prefix_groups, collapsed_words, classification_metrics, rank_correlation,
    edit_deletion_index, edit_enumerate_k1, edit_enumerate_k2, edit_phonetic, edit_distances, edit_costs, identity_correction, mips_exact, mips_ivf, mips_recall, subword_vectors, subword_correction,
    word_vector_correction, restoration_scores, restoration_structured, human_eval_documents, human_eval_conversations, pair_tasks, acceptability_quality, sentiment_toxic, noise_grid, search_recall,
)

QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {f.__name__: f for f in _LOCAL}
QUERIES |= {name: _variant(p) for name, p in VARIANTS.items()}
QUERIES |= {f"perturb_{r}": _noised(r) for r in workloads.RATES}
QUERIES |= relational.QUERIES | jobs.QUERIES | sqlapi.QUERIES

_V = f"vocab AS MATERIALIZED ({sql.vocab()})"
_IX = f"WITH RECURSIVE {sql.index(P)}"
_QX = f"WITH RECURSIVE {sql.index(QUALITY)}"
_MS = ", ".join(f"m{k}" for k in range(P.bins))
_ASK = "SELECT DISTINCT word FROM ({})"
_ATTACHED = f"{_IX}, " + sql.attach(P, _ASK.format(sql.words_of("conversations")))
_COLS = "word, matched, weight::BIGINT AS weight, rep_word, status"
_GRAMS = f"SELECT word, {sql.gram_list('word', P.char_lens)} AS g FROM ({sql.vocab()})"


def _exact(least: float) -> str:
    """Pairs of exact similarity: two sets share one of their rarest substrings."""
    return (
        f"gw AS MATERIALIZED ({_GRAMS}), cg AS MATERIALIZED (SELECT word, len(g) AS n, unnest(g) AS g FROM gw), df AS (SELECT g, count(*) AS df FROM cg GROUP BY g), "
        "ranked AS (SELECT word, n, g, row_number() OVER (PARTITION BY word ORDER BY df, g) AS r FROM cg JOIN df USING (g)), "
        f"kept AS MATERIALIZED (SELECT word, n, g FROM ranked WHERE r <= n - ceil({least} * n - 0.000001) + 1), "
        f"cand AS (SELECT DISTINCT a.word AS src, b.word AS dst FROM kept a JOIN kept b ON a.g = b.g AND a.word < b.word AND least(a.n, b.n) >= {least} * greatest(a.n, b.n)), "
        "both_sets AS (SELECT src, dst, len(list_intersect(x.g, y.g)) AS s, len(x.g) + len(y.g) AS t FROM cand JOIN gw x ON x.word = src JOIN gw y ON y.word = dst), "
        f"truth AS MATERIALIZED (SELECT src, dst, s / (t - s) AS jaccard FROM both_sets WHERE s / (t - s) >= {least})"
    )


_COVER = "coalesce(sum(CASE WHEN {c} THEN {w} ELSE 0 END) / nullif(sum({w}), 0), 0)"
_COVERS = ", ".join(f"round({_COVER.format(c=c, w=w)}, 8) AS {n}" for c, w, n in (("size > 1", "1", "grouped_words"), ("size > 1", "freq", "grouped_occurrences"), ("word <> rep_word", "1", "changed_words"), ("word <> rep_word", "freq", "changed_occurrences")))


def _coverage(source: str, alphas: tuple[str, ...]) -> str:
    parts, ctes = [], [f"vocab AS MATERIALIZED ({sql.vocab(source)})", sql.sigs(P), "weighed AS MATERIALIZED (SELECT a.word AS src, b.word AS dst, count(*) AS weight FROM sigs a JOIN sigs b ON a.rep = b.rep AND a.sig = b.sig AND a.word < b.word GROUP BY ALL HAVING count(*) >= 2)"]
    weights = {a: HashParams(alpha=a).index_min for a in alphas}
    for w in sorted(set(weights.values())):
        ctes += [f"e{w} AS (SELECT src, dst FROM weighed WHERE weight >= {w})", sql.components(f"e{w}", f"cc{w}"), sql.norm().replace("norm AS MATERIALIZED", f"norm{w} AS MATERIALIZED").replace("JOIN cc ON", f"JOIN cc{w} ON")]
    for a, w in weights.items():
        parts.append(f"SELECT '{a}' AS alpha, {_COVERS}, count(DISTINCT comp) FILTER (size > 1) AS groups, max(size) AS largest FROM norm{w}")
    return "WITH RECURSIVE " + ", ".join(ctes) + " " + " UNION ALL ".join(parts)


def _corrected(k: int, measure: str) -> str:
    return (
        f"WITH dict AS (SELECT word, freq AS score FROM ({sql.vocab()}) WHERE freq >= {workloads.ACCEPTED}), asked AS (SELECT DISTINCT word FROM ({sql.words_of('benchmark')})), "
        f"pairs AS (SELECT a.word, d.word AS candidate, score, {measure}({sql.single("a.word")}, {sql.single("d.word")}) AS distance FROM asked a JOIN dict d ON abs(length(a.word) - length(d.word)) <= {k} WHERE a.word NOT IN (SELECT word FROM dict) AND {measure}({sql.single("a.word")}, {sql.single("d.word")}) <= {k}), "
        "best AS (SELECT * FROM pairs QUALIFY row_number() OVER (PARTITION BY word ORDER BY distance, score DESC, candidate) = 1) "
        "SELECT a.word, coalesce(b.candidate, a.word) AS corrected, CASE WHEN a.word IN (SELECT word FROM dict) THEN 0 ELSE b.distance END AS distance FROM asked a LEFT JOIN best b ON a.word = b.word"
    )


def _rewritten(source: str, key: str, mapping: str) -> str:
    """Texts with mapped words, and the words replaced, by position."""
    return (
        f"base AS (SELECT {key} AS id, regexp_extract_all(lower(text), '{sql.WORD}') AS ws, string_split_regex(lower(text), '{sql.WORD}') AS gs FROM {source}), "
        f"flat AS (SELECT id, unnest(ws) AS word, unnest(range(len(ws))) AS pos, unnest(gs[:len(ws)]) AS gap FROM base), map AS ({mapping}), "
        "swapped AS (SELECT id, string_agg(gap || coalesce(rep_word, word), '' ORDER BY pos) AS body, count(rep_word) AS n FROM flat LEFT JOIN map USING (word) GROUP BY id), "
        "rewritten AS (SELECT b.id, coalesce(body, '') || gs[-1] AS text, coalesce(n, 0) AS n_changed FROM base b LEFT JOIN swapped s ON b.id = s.id)"
    )


_MAP_Q = f"{_QX}, " + sql.attach(QUALITY, _ASK.format(sql.words_of("conversations")))
_REWRITE = f"{_MAP_Q}, " + _rewritten("conversations", "conv_id * 1000 + turn", "SELECT word, rep_word FROM attached WHERE word <> rep_word") + " SELECT id, text, n_changed FROM rewritten"
_REDOC = f"{_QX}, " + _rewritten("documents", "doc_id", "SELECT word, rep_word FROM norm WHERE word <> rep_word")


def _bounds_sql() -> str:
    rows = ", ".join(map(str, _GRID))
    a, ln = "(alpha_num / alpha_den)", "lgamma(t + 1) - lgamma(k + 1) - lgamma(t - k + 1)"
    up = "((alpha_num * t + alpha_den - 1) // alpha_den)"
    tail = lambda p, lo, hi: f"coalesce(list_sum(list_transform(range({lo}, {hi} + 1), lambda k: exp({ln} + k * ln({p}) + (t - k) * ln(1 - {p})))), 0)"
    fp = lambda x: f"round(CASE WHEN {a} <= q THEN 1 ELSE least(1, {x}) END, 9)"
    fn = lambda n: f"round(CASE WHEN {a} >= p THEN 1 ELSE least(1, exp(-{n} * t * (p - {a}) ** 2 / (2 * p))) END, 9)"
    d = f"({a} / q - 1)"
    forms = {"fp_printed": fp(f"c * exp(-t * (q - {a}) ** 2 / (3 * q))"), "fp_valid": fp(f"c * exp(-(({d}) ** 2) * t * q / (2 + {d}))"), "fp_exact": fp(f"c * {tail('q', up, 't')}"), "fn_printed": fn("c"), "fn_peers": fn("(c - 1)"), "fn_exact": f"round(({tail('p', '0', f'({up} - 1)')}) ** (c - 1), 9)"}
    return f"SELECT c, t, alpha_num, p, q, {', '.join(f'{v} AS {k}' for k, v in forms.items())} FROM (SELECT c, t, p::DOUBLE AS p, q::DOUBLE AS q, alpha_num, alpha_den FROM (VALUES {rows}) g(t, p, q, alpha_num, alpha_den), (SELECT DISTINCT words AS c FROM (SELECT count(*) AS words FROM ({sql.vocab()}) WHERE length(word) >= 4 GROUP BY left(word, 4))))"


def _sig_sql(params: HashParams) -> str:
    return f"WITH {_V}, {sql.sigs(params)} SELECT word, string_agg(sig, ',' ORDER BY rep) AS sig FROM sigs GROUP BY word"


ORACLES: dict[str, str] = {
    "gram_sets": f"WITH {_V} SELECT word, len(g) AS n, array_to_string(list_sort(g), ' ') AS grams FROM (SELECT word, {sql.gram_list('word', P.char_lens)} AS g FROM vocab)",
    "gram_sets_all": f"WITH {_V} SELECT word, len({sql.gram_list('word', 'all')}) AS n FROM vocab",
    "fingerprints": f"WITH {_V} SELECT gram, {sql.fingerprint('gram')} AS x FROM (SELECT DISTINCT unnest({sql.gram_list('word', P.char_lens)}) AS gram FROM vocab)",
    "bin_minima": f"WITH {_V}, {sql.minima(P)} SELECT word, rep, {_MS} FROM mins",
    "bin_minima_universe": f"WITH {_V}, {sql.minima(UNIVERSE)} SELECT word, rep, {_MS} FROM mins",
    "densified": f"WITH {_V}, {sql.minima(P)}, {sql.dense(P)} SELECT word, rep, {_MS.replace('m', 'd')} FROM dense",
    "signatures": _sig_sql(P),
    "signatures_relational": _sig_sql(P),
    **{name: _sig_sql(p) for name, p in VARIANTS.items()},
    "bucket_stats": f"WITH {_V}, {sql.sigs(P)} SELECT rep, count(*) AS buckets, sum(n)::BIGINT AS words, max(n) AS largest, sum(n * (n - 1) // 2)::BIGINT AS pairs FROM (SELECT rep, sig, count(*) AS n FROM sigs GROUP BY ALL) GROUP BY rep",
    "edge_weights": f"WITH {sql.edges(P)} SELECT * FROM edges",
    "edges_prefix": f"WITH {sql.edges(P)} SELECT * FROM edges",
    "edges_pruned": f"WITH {sql.edges(QUALITY)} SELECT * FROM edges",
    "edges_intersect_alpha1": f"WITH {_V}, {sql.sigs(P)}, w AS (SELECT word, string_agg(sig, ',' ORDER BY rep) AS s FROM sigs GROUP BY word) SELECT min(word) OVER (PARTITION BY s) AS src, word AS dst, {P.repetitions}::BIGINT AS weight FROM w QUALIFY src <> dst",
    **{f"components_{m}": f"WITH RECURSIVE {sql.edges(P)}, {sql.components()} SELECT node, comp FROM cc" for m in ("star", "hash_min", "driver")},
    "representatives": f"{_IX} SELECT DISTINCT comp, rep_word, rep_freq, size FROM norm WHERE size > 1",
    "norm_map": f"{_IX} SELECT * FROM norm",
    "norm_lists": f"{_QX} SELECT rep_word, rep_freq, size, string_agg(word, ' ' ORDER BY freq DESC, word) AS members FROM norm WHERE size > 1 GROUP BY ALL",
    "component_sizes": f"{_IX} SELECT size, count(*) AS components FROM (SELECT comp, count(*) AS size FROM norm GROUP BY comp) GROUP BY size",
    "index_documents": f"{_IX} SELECT word, rep_word, size FROM norm",
    "index_conversations": "WITH RECURSIVE " + sql.index(P).replace("FROM documents", "FROM conversations") + " SELECT word, rep_word, size FROM norm",
    "index_verified": f"WITH {sql.edges(P)}, g AS (SELECT word, {sql.gram_list('word', P.char_lens)} AS g FROM vocab) SELECT src, dst, weight FROM edges JOIN g a ON src = a.word JOIN g b ON dst = b.word WHERE len(list_intersect(a.g, b.g)) / (len(a.g) + len(b.g) - len(list_intersect(a.g, b.g))) >= 0.5",
    "index_star_split": f"{_IX} SELECT DISTINCT src, dst, weight FROM edges JOIN norm ON (src = word AND dst = rep_word) OR (dst = word AND src = rep_word)",
    "index_extended": "WITH RECURSIVE " + sql.index(QUALITY).replace(sql.vocab(), f"SELECT word, sum(freq)::BIGINT AS freq FROM ({sql.vocab()} UNION ALL {sql.vocab('conversations')}) GROUP BY word") + " SELECT word, freq, rep_word, size FROM norm",
    "infer_known": f"{_ATTACHED} SELECT word, rep_word FROM attached WHERE status = 'known'",
    "infer_attach_strict": f"{_ATTACHED} SELECT {_COLS} FROM attached",
    "infer_attach_inclusive": f"{_IX}, " + sql.attach(P, _ASK.format(sql.words_of("conversations")), True) + f" SELECT {_COLS} FROM attached",
    "infer_benchmark": f"{_IX}, " + sql.attach(P, _ASK.format(sql.words_of("benchmark"))) + f" SELECT {_COLS} FROM attached",
    "infer_grouped_targets": f"{_IX}, " + sql.attach(P, _ASK.format(sql.words_of("conversations")), grouped=True) + " SELECT status, count(*) AS words FROM attached GROUP BY status",
    "component_edit_profile": f"{_QX} SELECT levenshtein({sql.single('word')}, {sql.single('rep_word')})::BIGINT AS distance, count(*) AS words, sum(freq)::BIGINT AS occurrences FROM norm WHERE word <> rep_word GROUP BY distance",
    "edges_union_alpha0": f"WITH RECURSIVE {_V}, {sql.sigs(P)}, stars AS MATERIALIZED (SELECT DISTINCT min(word) OVER (PARTITION BY rep, sig) AS src, word AS dst FROM sigs), {sql.components('stars')} SELECT comp, count(*) AS size FROM cc GROUP BY comp",
    "index_both": "WITH RECURSIVE " + sql.index(P).replace("FROM documents", "FROM (SELECT text FROM documents UNION ALL SELECT text FROM conversations)") + " SELECT word, rep_word, size FROM norm",
    "infer_unmatched": f"{_ATTACHED} SELECT word FROM attached WHERE status = 'unmatched'",
    "rewrite_conversations": _REWRITE,
    "rewrite_joined": _REWRITE,
    "rewrite_documents": f"{_REDOC} SELECT id AS doc_id, n_changed, md5(text) AS text_md5 FROM rewritten",
    "dedup_after_norm": f"{_REDOC} SELECT 'before' AS stage, count(*) AS groups, coalesce(sum(n), 0)::BIGINT AS documents FROM (SELECT count(*) AS n FROM documents GROUP BY lower(text) HAVING count(*) > 1) UNION ALL SELECT 'after', count(*), coalesce(sum(n), 0)::BIGINT FROM (SELECT count(*) AS n FROM rewritten GROUP BY text HAVING count(*) > 1)",
    "coverage_by_alpha": _coverage("documents", HIGH),
    "coverage_conversations": _coverage("conversations", ("0.1", "0.2", "0.3", "0.5")),
    "case_components": f"{_QX}, top AS (SELECT rep_word, sum(CASE WHEN word <> rep_word THEN freq ELSE 0 END) AS moved FROM norm WHERE size > 1 GROUP BY rep_word ORDER BY moved DESC, rep_word LIMIT 20) SELECT rep_word, rep_freq, size, string_agg(word, ' ' ORDER BY freq DESC, word) AS members FROM norm WHERE rep_word IN (SELECT rep_word FROM top) GROUP BY ALL",
    "exact_jaccard_pairs": f"WITH {_exact(JACCARD)} SELECT src, dst, round(jaccard, 8) AS jaccard FROM truth",
    "edge_quality": f"WITH {sql.edges(P)}, {_exact(JACCARD)}, mine AS (SELECT src, dst FROM edges), c AS (SELECT (SELECT count(*) FROM mine) AS found, (SELECT count(*) FROM truth) AS expected, (SELECT count(*) FROM mine JOIN truth USING (src, dst)) AS hit) SELECT found, expected, hit, round(coalesce(hit / nullif(found, 0), 0), 8) AS precision, round(coalesce(hit / nullif(expected, 0), 0), 8) AS recall FROM c",
    "collision_curve": f"WITH {_V}, {sql.sigs(P)}, {_exact(JACCARD)}, r AS (SELECT src, dst, jaccard, sum((a.sig = b.sig)::INT) / {P.repetitions} AS rate FROM truth JOIN sigs a ON a.word = src JOIN sigs b ON b.word = dst AND a.rep = b.rep GROUP BY ALL) SELECT least(floor(jaccard * 10), 9)::BIGINT AS bin, count(*) AS pairs, round(avg(jaccard), 8) AS jaccard, round(avg(rate), 8) AS rate FROM r GROUP BY bin",
    "estimate_pq": f"WITH RECURSIVE {sql.edges(P)}, strong AS (SELECT src, dst FROM edges WHERE weight >= {QUALITY.index_min}), {sql.components('strong')} SELECT a.comp = b.comp AS inside, count(*) AS pairs, round(min(weight / 20), 8) AS least, round(max(weight / 20), 8) AS greatest, round(avg(weight / 20), 8) AS mean FROM edges JOIN cc a ON a.node = src JOIN cc b ON b.node = dst GROUP BY inside",
    "error_bounds": _bounds_sql(),
    "cost_counters": f"WITH {_V}, {sql.sigs(P)}, b AS (SELECT count(*) AS b, avg(n) AS m FROM (SELECT count(*) AS n FROM sigs GROUP BY rep, sig)), v AS (SELECT count(*) AS n, avg(length(word)) AS l FROM vocab) SELECT n AS words, b AS buckets, round(l, 4) AS mean_length, round(m, 4) AS mean_bucket, round(l * n * {P.repetitions}, 4) AS hashing, round(m * m * b, 4) AS pairing, round(l * n * 36, 4) AS enumeration FROM v, b",
    "same_prefix_groups": f"WITH {_V} SELECT left(word, 4) AS stem, count(*) AS words, sum(freq)::BIGINT AS freq FROM vocab WHERE length(word) >= 4 GROUP BY stem",
    "collapsed_words": f"WITH {_V}, k AS (SELECT word, list_sort({sql.gram_list('word', P.char_lens)}) AS g FROM vocab) SELECT word, min(word) OVER (PARTITION BY g) AS hub, count(*) OVER (PARTITION BY g) AS members FROM k WHERE len(g) > 0 QUALIFY members > 1",
    "classification_metrics": "WITH p AS (SELECT toxic AS y, list_has_any(regexp_extract_all(lower(text), '" + sql.WORD + "'), [" + ", ".join(f"'{w}'" for w in TOXIC) + "])::INT AS h FROM documents JOIN labels USING (doc_id)), c AS (SELECT count(*) AS n, sum(y * h) AS tp, sum((1 - y) * h) AS fp, sum(y * (1 - h)) AS fn, sum((1 - y) * (1 - h)) AS tn FROM p) SELECT n, round((tp + tn) / n, 8) AS accuracy, round(coalesce(tp / nullif(tp + fp, 0), 0), 8) AS precision, round(coalesce(tp / nullif(tp + fn, 0), 0), 8) AS recall, round(coalesce(2 * tp / nullif(2 * tp + fp + fn, 0), 0), 8) AS f1, round(coalesce((tp * tn - fp * fn) / nullif(sqrt(tp + fp) * sqrt(tp + fn) * sqrt(tn + fp) * sqrt(tn + fn), 0), 0), 8) AS matthews FROM c",
    "rank_correlation": "WITH r AS (SELECT p_brand, p_retailprice AS g, p_size::DOUBLE AS s, rank() OVER (PARTITION BY p_brand ORDER BY p_retailprice) + (count(*) OVER (PARTITION BY p_brand, p_retailprice) - 1) / 2 AS rg, rank() OVER (PARTITION BY p_brand ORDER BY p_size) + (count(*) OVER (PARTITION BY p_brand, p_size) - 1) / 2 AS rs FROM part) SELECT p_brand, round(corr(g, s), 6) AS pearson, round(corr(rg, rs), 6) AS spearman FROM r GROUP BY p_brand",
    "edit_deletion_index": _corrected(2, "levenshtein"),
    "edit_enumerate_k1": _corrected(1, "damerau_levenshtein"),
    "edit_enumerate_k2": _corrected(2, "damerau_levenshtein"),
    "edit_distances": f"WITH w AS (SELECT word, left(word, 1) AS c FROM ({sql.vocab()})), p AS (SELECT word, lead(word) OVER (PARTITION BY c ORDER BY word) AS next FROM w), q AS (SELECT word, next, {sql.single('word')} AS a, {sql.single('next')} AS b FROM p WHERE next IS NOT NULL) SELECT word, next, levenshtein(a, b)::DOUBLE AS lev, damerau_levenshtein(a, b)::DOUBLE AS damerau, round(jaro_winkler_similarity(a, b), 8) AS jaro_winkler FROM q",
    "stream_word_counts": sql.vocab("conversations"),
    "stream_distinct": "SELECT event_id, user_id FROM events",
    "stream_interval_join": relational.ORACLES["interval_join_events"].replace("epoch_us(ts) // 1000000 AS s", "epoch_us(ts) AS s").replace("c.s + 3600", "c.s + 3600000000"),
    "stream_frequent_words": f"SELECT word FROM ({sql.words_of('benchmark')}) GROUP BY word HAVING count(*) >= 5",
    "identity_correction": f"SELECT DISTINCT word, word AS corrected FROM ({sql.words_of('benchmark')})",
    "mips_exact": "SELECT query_id, id, round(score, 6) AS score, rank FROM (SELECT q.vec_id AS query_id, e.vec_id AS id, list_inner_product(q.embedding::DOUBLE[], e.embedding::DOUBLE[]) AS score, row_number() OVER (PARTITION BY q.vec_id ORDER BY list_inner_product(q.embedding::DOUBLE[], e.embedding::DOUBLE[]) DESC, e.vec_id) AS rank FROM embeddings q, embeddings e WHERE q.vec_id % 100 = 0) WHERE rank <= 10",
}
ORACLES |= {f"perturb_{r}": f"SELECT id, pos, clean_word, noisy_word FROM ({sql.noise('conversations', '(conv_id * 1000 + turn)', r)})" for r in workloads.RATES}
ORACLES |= relational.ORACLES | sqlapi.ORACLES
