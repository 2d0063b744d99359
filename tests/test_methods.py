"""Worked examples, variants and invariants of the methods on small inputs."""

import random
from itertools import combinations

import pytest
from hypothesis import given, settings
from hypothesis import strategies as st
from pyspark.sql import functions as F

from lexnorm.baselines import cosine, edit
from lexnorm.config import PRIME, HashParams
from lexnorm.functions import hashing, metrics, shingles, theory, tokens
from lexnorm.operators import graph, infer, rewrite, vocabulary
from lexnorm.operators.components import components
from lexnorm.plans import perturb
from lexnorm.plans.index import Index, build_index

FAMILIES = {"amazing": 90, "amazingg": 3, "amazinggg": 2, "amazingggg": 1, "feeling": 80, "feelingg": 2, "feelinggg": 1, "morning": 70, "zebra": 5, "x": 4}


def rows(df):
    return sorted(map(tuple, df.collect()), key=str)


def test_thresholds_are_exact():
    assert [HashParams(alpha=a, repetitions=t).index_min for a, t in (("0.07", 100), ("0.1", 30), ("0.2", 20), ("0.1", 3), ("0", 20))] == [7, 3, 4, 1, 1]
    assert (HashParams().infer_min(), HashParams().infer_min(True)) == (5, 4)
    assert HashParams.from_json(HashParams(char_lens=(2, 3)).to_json()) == HashParams(char_lens=(2, 3))


def test_bins_minima_and_densification():
    values = [12, 32, 56, 78, 130, 410, 415, 799]
    minima = [min((v for v in values if v * 10 // 800 == k), default=None) for k in range(10)]
    assert minima == [12, 130, None, None, None, 410, None, None, None, 799]
    fill = lambda right: [next(minima[j] for j in hashing.probe_order(k, 10, right) if minima[j] is not None) for k in range(10)]
    assert fill(True) == [12, 130, 410, 410, 410, 410, 799, 799, 799, 799]
    assert fill(False) == [12, 130, 130, 130, 130, 410, 410, 410, 410, 799]


def test_gram_sets(spark):
    df = spark.createDataFrame([("abc",), ("",), ("a",), ("aaa",), ("é",)], "w string")
    got = {r.w: set(r.g) for r in df.select("w", shingles.gram_set(F.col("w"), (1, 3, 5)).alias("g")).collect()}
    assert got["abc"] == {"a", "b", "c", "abc"} and got[""] == set() and got["aaa"] == {"a", "aaa"}
    only = {r.w: r.g for r in df.select("w", shingles.gram_set(F.col("w"), (3,)).alias("g")).collect()}
    assert only["a"] == [] and only[""] == []
    for r in df.select("w", shingles.gram_set(F.col("w"), "all").alias("g")).collect():
        assert set(r.g) == hashing.grams_of(r.w, "all")


@pytest.mark.parametrize(
    "params",
    [HashParams(), HashParams(bins=1), HashParams(densify="left"), HashParams(densify="coin_offset"), HashParams(scheme="kperm"), HashParams(width=62), HashParams(bin_space="universe"), HashParams(char_lens=(2, 3), fingerprint="crc32"), HashParams(fingerprint="xxhash64", repetitions=3)],
)
def test_kernel_equals_columns(spark, params):
    df = spark.createDataFrame([(w, 1) for w in [*FAMILIES, "ß", "日本語テキスト", "a"]], "word string, freq long")
    family = hashing.Family.draw(params)
    a, b = rows(hashing.signatures(df, family)), rows(hashing.signatures(df, family, "relational"))
    assert a == b and all(0 <= x < (PRIME if params.width == 31 else 2**62) for _, s in a for x in s)


def test_family_avoids_constant_functions():
    for seed in range(20):
        for r in hashing.Family.draw(HashParams(seed=seed)).repetitions:
            assert 0 < r.a[0] < PRIME and 0 <= r.b[0] < PRIME and r.a[0] * (PRIME - 1) + r.b[0] < 2**63


def _brute_edges(sigs, least):
    got = {r.word: r.sig for r in sigs.collect()}
    out = []
    for a, b in combinations(sorted(got), 2):
        w = sum(x == y for x, y in zip(got[a], got[b], strict=True))
        if w >= least:
            out.append((a, b, w))
    return sorted(out, key=str)


def test_edge_strategies_agree(spark):
    rng = random.Random(1)
    words = sorted({"".join(rng.choice("abc") for _ in range(rng.randint(2, 8))) for _ in range(150)})
    df = spark.createDataFrame([(w, 1) for w in words], "word string, freq long")
    sigs = hashing.signatures(df, hashing.Family.draw(HashParams(repetitions=10))).cache()
    for least in (1, 2, 4, 10):
        want = _brute_edges(sigs, least)
        assert rows(graph.edge_weights(sigs, 10, least, "pairs")) == want
        assert rows(graph.edge_weights(sigs, 10, least, "prefix")) == want
    nodes = df.select(F.col("word").alias("node"))
    full = graph.edge_weights(sigs, 10, 1, "pairs")
    assert rows(components(full, nodes)) == rows(components(graph.edge_weights(sigs, 10, 1, "union"), nodes))
    assert rows(components(graph.prune(full, 10), nodes)) == rows(components(graph.edge_weights(sigs, 10, 10, "intersect"), nodes))
    # A higher threshold refines the groups of a lower one.
    low, high = ({r.node: r.comp for r in components(graph.prune(full, w), nodes).collect()} for w in (2, 4))
    for c in set(high.values()):
        assert len({low[w] for w in high if high[w] == c}) == 1
    # Crowded buckets paired in blocks give the same pairs.
    from lexnorm.operators.buckets import explode

    members = graph._sized(explode(sigs))
    assert rows(graph._pairs(members)) == rows(graph._pairs(members, 3))


@pytest.mark.parametrize("method", ["star", "hash_min", "driver"])
def test_components(spark, method):
    edges = [("a", "b"), ("b", "c"), ("x", "y"), ("c", "a"), ("q", "q"), (None, "a")] + [(f"p{i:02}", f"p{i + 1:02}") for i in range(30)] + [("hub", f"h{i}") for i in range(30)]
    df = spark.createDataFrame(edges, "src string, dst string")
    got = dict(rows(components(df, method=method)))
    assert {got[x] for x in "abc"} == {"a"} and got["y"] == "x" and got["p30"] == "p00" and got["h7"] == "h0" and "q" not in got
    assert components(df.where("false"), method=method).count() == 0


def test_representative_ties_and_lists(spark):
    vocab = spark.createDataFrame([("b", 5), ("a", 5), ("c", 1), ("d", 9)], "word string, freq long")
    comps = spark.createDataFrame([("a", "a"), ("b", "a"), ("c", "a")], "node string, comp string")
    norm = vocabulary.build(vocab, comps)
    assert {r.word: r.rep_word for r in norm.collect()} == {"a": "a", "b": "a", "c": "a", "d": "d"}
    assert rows(vocabulary.as_map(norm)) == [("b", "a"), ("c", "a")]
    assert rows(vocabulary.as_lists(norm)) == [("a", 5, 3, ["a", "b", "c"])]


@pytest.fixture(scope="module")
def small(spark):
    df = spark.createDataFrame(list(FAMILIES.items()), "word string, freq long")
    return build_index(df, HashParams(bins=2, alpha="0.4"))


def test_index_groups_elongations(small):
    rep = {r.word: r.rep_word for r in small.norm.collect()}
    assert rep["amazinggg"] == "amazing" and rep["feelingg"] == "feeling" and rep["zebra"] == "zebra"
    for w, r in rep.items():
        assert rep[r] == r


def test_inference_hit_miss_known(spark, small):
    asked = spark.createDataFrame([("amazinggggg",), ("qqq",), ("zebra",), (None,), ("zebra",)], "word string")
    got = {r.word: r for r in infer.attach(asked, small).collect()}
    assert got["amazinggggg"].status == "attached" and got["amazinggggg"].rep_word == "amazing"
    assert got["qqq"].status == "unmatched" and got["qqq"].rep_word == "qqq"
    assert got["zebra"].status == "known" and len(got) == 3
    # An indexed word hashed as if unseen collides with itself in every repetition.
    self_hits = infer.collisions(small.sigs.where("word = 'zebra'"), small.sigs, 20, 20).where("word = indexed").collect()
    assert [r.weight for r in self_hits] == [20]


def test_save_load_extend(spark, small, tmp_path):
    small.save(str(tmp_path / "index"))
    again = Index.load(spark, str(tmp_path / "index"))
    assert rows(again.norm) == rows(small.norm) and again.params == small.params
    more = spark.createDataFrame([("amazingggggg", 1), ("zebra", 100), ("zebrra", 1)], "word string, freq long")
    both = spark.createDataFrame([*FAMILIES.items(), ("amazingggggg", 1), ("zebra", 100), ("zebrra", 1)], "word string, freq long").groupBy("word").agg(F.sum("freq").alias("freq"))
    assert rows(small.extend(more).norm.select("word", "freq", "rep_word", "size")) == rows(build_index(both, small.params).norm.select("word", "freq", "rep_word", "size"))


def test_rewrite(spark):
    df = spark.createDataFrame([(1, "Ab, cd!  AB\n"), (2, None), (3, ""), (4, "...x")], "id int, text string")
    m = spark.createDataFrame([("ab", "yes"), ("x", "x1")], "word string, rep_word string")
    want = [(1, "yes, cd!  yes\n", 2), (2, "", 0), (3, "", 0), (4, "...x1", 1)]
    assert rows(rewrite.apply(df, ["id"], "text", m, "broadcast")) == want
    assert rows(rewrite.apply(df, ["id"], "text", m, "join")) == want
    cased = {r.id: r.text for r in rewrite.apply(df, ["id"], "text", m, "broadcast", keep_case=True, protect=r"\.\.\.x").collect()}
    assert cased[1] == "Yes, cd!  YES\n" and cased[4] == "...x"
    same = rewrite.apply(df, ["id"], "text", m.where("false"), "join").where("id = 1").first().text
    assert same == "ab, cd!  ab\n"


@settings(max_examples=60, deadline=None)
@given(st.text("abcd", max_size=6), st.text("abcd", max_size=6))
def test_distances(a, b):
    import duckdb

    lev, dl, jw = duckdb.execute("SELECT levenshtein(?, ?), damerau_levenshtein(?, ?), jaro_winkler_similarity(?, ?)", [a, b] * 3).fetchone()
    assert edit.damerau(a, b) == dl and edit.damerau(a, b) <= lev == edit.weighted(a, b, "unit")
    if a and b:
        assert abs(edit.jaro_winkler(a, b) - jw) < 1e-9


def test_edit_baselines(spark):
    d = spark.createDataFrame([("the", 100), ("then", 10), ("tea", 5), ("there", 7)], "word string, score long")
    w = spark.createDataFrame([("teh",), ("the",), ("thn",), ("zzzzz",)], "word string")
    got = {r.word: (r.corrected, r.distance) for r in edit.enumerate_edits(w, d, 2).collect()}
    assert got == {"teh": ("the", 1), "the": ("the", 0), "thn": ("the", 1), "zzzzz": ("zzzzz", None)}
    assert {r.word: r.corrected for r in edit.deletion_index(w, d, 1, "dl").collect()} == {"teh": "the", "the": "the", "thn": "the", "zzzzz": "zzzzz"}
    assert {r.word: r.corrected for r in edit.phonetic(w, d).collect()}["thn"] == "then"


def test_vectors(spark):
    words = spark.createDataFrame([("morning",), ("evening",), ("zebra",)], "word string")
    dictionary = spark.createDataFrame([("morning", 5), ("zebra", 2)], "word string, score long")
    got = {r.word: r.corrected for r in cosine.correct(spark.createDataFrame([("morningg",), ("zebra",), ("qqqq",)], "word string"), dictionary).collect()}
    assert got == {"morningg": "morning", "zebra": "zebra", "qqqq": "qqqq"}
    v = cosine.subword_vectors(words).select(F.col("word").alias("id"), "vec")
    top = cosine.search(v, v, 1)
    assert all(r.query_id == r.id for r in top.collect())


def test_bounds_reference_points():
    want = {0.01: (3.53e-11, 4.26e-5), 0.02: (2.04e-5, 6.00e-4), 0.05: (4.98e-2, 1.59e-2), 0.1: (0.513, 0.1330), 0.15: (0.895, 0.3523)}
    for q, (printed, exact) in want.items():
        assert theory.fp_bound(1, 20, q, "0.2", "printed") == pytest.approx(printed, rel=2e-2)
        assert theory.fp_bound(1, 20, q, "0.2", "exact") == pytest.approx(exact, rel=2e-2)
        assert theory.fp_bound(1, 20, q, "0.2", "valid") >= theory.fp_bound(1, 20, q, "0.2", "exact")
    assert theory.fp_bound(1, 20, 0.01, "0.2", "printed") < theory.fp_bound(1, 20, 0.01, "0.2", "exact")
    tails = [theory.fp_bound(1, t, 0.05, "0.2", "exact") for t in (5, 10, 20, 40)]
    assert tails == sorted(tails, reverse=True)


def test_measures(spark):
    pred = spark.createDataFrame([(1, 1), (1, 1), (0, 0), (0, 1)], "y int, yhat int")
    r = metrics.classification(pred).first()
    assert (r.accuracy, r.f1) == (0.75, 0.8) and r.matthews == pytest.approx(0.57735, abs=1e-4)
    assert metrics.classification(pred.where("y = 1")).first().matthews == 0.0
    pairs = spark.createDataFrame([("a", 1.0, 1.0), ("a", 2.0, 1.0), ("a", 3.0, 5.0)], "k string, gold double, score double")
    assert metrics.correlations(pairs, ["k"]).first().spearman == pytest.approx(0.8660254, abs=1e-6)
    votes = spark.createDataFrame([("d", "m", i, r, label, True) for i, labels in enumerate((["good"] * 5, ["bad"] * 3 + ["neutral"] * 2, ["not sure"] * 5)) for r, label in enumerate(labels)], "dataset string, method string, sentence_id int, reviewer int, label string, corrected boolean")
    needs = spark.createDataFrame([("d", 0, True), ("d", 1, True), ("d", 2, False)], "dataset string, sentence_id int, needs_fix boolean")
    r = metrics.human_prf(votes, needs).first()
    assert (r.precision, r.recall) == (0.7, 0.5)
    r = metrics.human_prf(votes, needs, "majority").first()
    assert (r.precision, r.recall) == (0.5, 0.5)


def test_perturbation(spark):
    df = spark.createDataFrame([(i, f"Some words here number {i}") for i in range(200)] + [(999, None)], "id int, text string")
    got = perturb.noise(df, "id", "text", 40).collect()
    share = sum(r.selected for r in got) / len(got)
    assert 0.25 < share < 0.55
    for r in got:
        if not r.selected:
            assert r.noisy == r.clean
        for c, n in zip(r.clean_words, r.noisy_words, strict=True):
            assert len(c) - 2 <= len(n) <= len(c) and n
    assert rows(perturb.noise(df.repartition(7), "id", "text", 40).select("id", "noisy")) == rows(perturb.noise(df, "id", "text", 40).select("id", "noisy"))


def test_tokens(spark):
    df = spark.createDataFrame([("A b-c é1",), (None,), ("...",)], "text string")
    assert [r.w for r in df.select(tokens.words(F.col("text")).alias("w")).collect()] == [["a", "b", "c", "é1"], [], []]
    back = df.select("text", tokens.split_lossless(F.col("text"), lower=False).alias("s")).select("text", tokens.join_lossless(F.col("s.gaps"), F.col("s.words")).alias("t")).collect()
    assert all(r.t == (r.text or "") for r in back)


def test_matching_in_passes_and_blocks(spark, monkeypatch):
    """Passes, blocks and sides change nothing; groups are made without a table of edges."""
    from lexnorm.operators import matching

    words = [f"{w}{'g' * i}" for w in ("amazing", "feeling", "running") for i in range(1, 14)] + ["zebra", "q"]
    vocab = spark.createDataFrame([(w, 1) for w in words], "word string, freq long")
    sigs = hashing.signatures(vocab, hashing.Family.draw(HashParams())).localCheckpoint()
    want = rows(graph.edge_weights(sigs, 20, 4, "pairs"))
    new, old = sigs.where("word > 'f'"), sigs.where("word < 'm'")
    sides = rows(matching.pairs(new, 20, 4, old))
    assert sides and all(w >= 4 for _, _, w in sides)
    monkeypatch.setattr(matching, "PASS_BYTES", 30_000)
    monkeypatch.setattr(matching, "BLOCK_WORDS", 3)
    assert rows(graph.edge_weights(sigs, 20, 4)) == want
    assert rows(matching.pairs(new, 20, 4, old)) == sides
    index = build_index(vocab)
    groups = {r.word: r.comp for r in index.norm.collect()}
    assert index.made_edges is None
    assert groups == {r.node: r.comp for r in components(index.edges, vocab.select(F.col("word").alias("node"))).collect()}


def test_union_stars_in_passes(spark, monkeypatch):
    """One link for each word but the least of its group, however many repetitions join them, with or without telling groups to executors."""
    from lexnorm.operators import matching

    rng = random.Random(5)
    words = sorted({"".join(rng.choice("abcdefghij") for _ in range(rng.randint(1, 7))) for _ in range(300)})
    df = spark.createDataFrame([(w, 1) for w in words], "word string, freq long")
    nodes = df.select(F.col("word").alias("node"))
    for params in (HashParams(repetitions=6), HashParams(repetitions=5, width=62)):
        sigs = hashing.signatures(df, hashing.Family.draw(params)).localCheckpoint()
        want = {r.node: r.comp for r in components(graph.edge_weights(sigs, params.repetitions, 1, "pairs"), nodes, "driver").collect()}
        assert 1 < len(set(want.values())) < len(words)
        got = [(r.dst, r.src) for r in graph.edge_weights(sigs, params.repetitions, 1, "union").collect()]
        assert sorted(got) == sorted((w, c) for w, c in want.items() if w != c)
        monkeypatch.setattr(matching, "BROADCAST_NODES", 0)


def test_similar_pairs_meet_in_tasks(spark, monkeypatch):
    """All pairs of brute force, each once, with crowded substrings cut into blocks; no candidates are joined or made distinct."""
    from lexnorm.functions.hashing import grams_of
    from lexnorm.operators import similar

    rng = random.Random(9)
    words = sorted({"".join(rng.choice("abé") for _ in range(rng.randint(1, 12))) * rng.choice((1, 1, 2)) for _ in range(250)} | {"z" * 300, "z" * 301, "".join(map(chr, range(500, 800)))})
    df = spark.createDataFrame([(w,) for w in words] + [(None,)], "word string")
    monkeypatch.setattr(similar, "STEP", 500)
    for lens, least, rows_of_block in (((1, 3, 5), 0.7, 20_000), ((2, 3), 0.5, 10)):
        monkeypatch.setattr(similar, "BLOCK_ROWS", rows_of_block)
        sets = {w: grams_of(w, lens) for w in words}
        want = [(a, b, len(sets[a] & sets[b]) / len(sets[a] | sets[b])) for a, b in combinations(words, 2) if sets[a] | sets[b]]
        got = graph.exact_pairs(df, lens, least)
        assert "Join" not in got._jdf.queryExecution().toString()
        found = [(r.src, r.dst, r.jaccard) for r in got.collect()]
        assert found and sorted(found) == sorted(x for x in want if x[2] >= least)


def test_word_vectors_and_nearest_leave_words_in_tasks(spark, monkeypatch):
    """Vectors equal sums over the neighbours of each occurrence; the nearest word is found over several blocks, and Spark's driver-bound trainer isn't used."""
    import numpy as np
    import pyspark.ml.feature
    import xxhash

    from lexnorm.baselines import cosine

    monkeypatch.delattr(pyspark.ml.feature, "Word2Vec")
    for name, value in (("QUERY_BLOCK", 3), ("BLOCKS_AT_ONCE", 2), ("HELD_WORDS", 5), ("COMMON_SHARE", 0.1)):
        monkeypatch.setattr(cosine, name, value)
    texts = ["a b c d e f g h i j k", "a a b", "", None, "lone", "c a d a e a"]
    flat = [w for t in texts for w in (t or "").split()]
    sign = lambda w: 2.0 * np.unpackbits(np.array([xxhash.xxh64_intdigest(w.encode(), 3)], dtype="<u8").view(np.uint8))[:32] - 1
    weight = lambda w: round(64 * min(1.0, (0.1 * len(flat) / flat.count(w)) ** 0.5))
    want = {}
    for t in texts:
        w = (t or "").split()
        for i, x in enumerate(w):
            near = [y for j, y in enumerate(w) if j != i and abs(i - j) <= 5]
            want[x] = want.get(x, 0) + sum((weight(y) * sign(y) for y in near), np.zeros(32))
    docs = spark.createDataFrame([(t,) for t in texts], "text string").repartition(3)
    got = {r.word: np.array(r.vec) for r in cosine.word_vectors(docs).collect()}
    assert got.keys() == want.keys() and all((got[w] == want[w]).all() for w in want)
    rng = np.random.default_rng(1)
    vec = {f"w{i}": rng.standard_normal(8).astype(np.float32).tolist() for i in range(20)} | {"w3x": [1.0] * 8, "v3x": [1.0] * 8}
    rows = lambda names: spark.createDataFrame([(n, vec[n]) for n in names], "id string, vec array<float>")
    found = cosine.nearest(rows(["w0", "w1", "w2", "w3x"]), rows([n for n in vec if n not in ("w0", "w1", "w2")]), 0.2)
    want = cosine.search(rows(["w0", "w1", "w2", "w3x"]), rows([n for n in vec if n not in ("w0", "w1", "w2")]), 1, "cos").where("score >= 0.2")
    plain = lambda frame: {r.query_id: (r.id, round(r.score, 9)) for r in frame.collect()}
    assert plain(found) == plain(want) and plain(found)["w3x"][0] == "v3x"


def test_one_edit_without_a_row_for_each_letter(spark, monkeypatch):
    """Words one edit apart equal those found by listing all edits, though none are listed."""
    import itertools

    from lexnorm.baselines import edit

    names = ["".join(x) for n in (1, 2, 3) for x in itertools.product("abé", repeat=n)] + ["bb1a", "a😀b"]
    dictionary = spark.createDataFrame([(w, i % 5) for i, w in enumerate(names) if i % 2], "word string, score int")
    words = spark.createDataFrame([(w,) for w in [*names, "zab", "a😀", "abab", "z", None]], "word string")
    known = {r.word: r.score for r in dictionary.collect()}
    listed = {r.word: set(r.e) for r in words.where("word is not null").select("word", edit.edits(F.col("word"), "abé1😀").alias("e")).collect()}
    want = {w: (w, 0) if w in known else min(((c, 1) for c in e if c in known), key=lambda x: (-known[x[0]], x[0].encode()), default=(w, None)) for w, e in listed.items()}
    few = {r.word: set(r.e) & known.keys() for r in words.where("word is not null").select("word", edit.edits(F.col("word"), "a").alias("e")).collect()}
    monkeypatch.setattr(edit, "edits", None)
    assert {r.word: (r.corrected, r.distance) for r in edit.enumerate_edits(words, dictionary, 1).collect()} == want
    got = {r.word: r.corrected for r in edit.enumerate_edits(words, dictionary, 1, "a").collect()}
    assert all(got[w] in c or not c and got[w] == w for w, c in few.items() if w not in known)


def test_vectors_of_wanted_words_and_repeated_texts(spark):
    """A text that counts three times equals three texts; vectors of wanted words equal those of all words."""
    from lexnorm.baselines import cosine

    once = spark.createDataFrame([("a b c a d", 3), ("b e f g h i j k a", 1), ("never", 0)], "text string, times int")
    full = spark.createDataFrame([("a b c a d",)] * 3 + [("b e f g h i j k a",)], "text string")
    plain = lambda frame: {r.word: list(r.vec) for r in frame.collect()}
    want = plain(cosine.word_vectors(full))
    assert plain(cosine.word_vectors(once, times_col="times")) == want
    few = spark.createDataFrame([("a",), ("k",), ("k",), ("zz",), (None,)], "word string")
    assert plain(cosine.word_vectors(full, wanted=few)) == {w: want[w] for w in "ak"}


def test_swaps_of_the_words_of_some_rows(spark, tmp_path):
    """Corrections for some rows equal those of the whole table for their words, and no others are made."""
    from lexnorm.plans import perturb, workloads

    docs = [(i, " ".join(f"{a}{b}{i % 3}" for a in ("red", "green", "blue") for b in ("stone", "river"))) for i in range(40)]
    spark.createDataFrame(docs, "doc_id long, text string").write.parquet(f"{tmp_path}/documents.parquet")
    ids = spark.createDataFrame([(3,), (8,), (21,)], "id long")
    some = rows(workloads.swaps(spark, str(tmp_path), "documents", ("none", "edit_index", "word_vectors"), (20, 60), among=ids))
    full = rows(workloads.swaps(spark, str(tmp_path), "documents", ("none", "edit_index", "word_vectors"), (20, 60)))
    texts = workloads.sentences(spark, str(tmp_path), "documents").join(ids, "id")
    asked = {w for r in (20, 60) for x in perturb.noise(texts, "id", "text", r, 13).collect() for w in x.noisy_words}
    assert sorted(some) == sorted(r for r in full if r[1] in asked) and len(some) < len(full)


def test_small_groups_join_in_one_task(spark, monkeypatch):
    """Groups equal those of the star contractions, in one task for few edges only."""
    from lexnorm.operators import components as c

    edges = spark.createDataFrame([("b", "a"), ("c", "b"), ("x", "é"), ("q", "q"), (None, "a"), ("z", "x")], "src string, dst string")
    want = sorted(rows(c.components(edges)))
    assert sorted(rows(c.components(edges, method="task", limit=3))) == want
    monkeypatch.setattr(c, "star_components", None)
    assert sorted(rows(c.components(edges, method="task"))) == want
    assert c.components(edges.limit(0), method="task").count() == 0


def test_sentiment_sums_accepted_words_once(spark, tmp_path, monkeypatch):
    """Each method's sums equal those of its corrected texts, and no texts are written for a method."""
    from collections import Counter

    from pyspark.ml.feature import HashingTF

    from lexnorm.plans import workloads

    texts = [f"stone river{' bridge' * (i % 2)} {'stonne' if i == 4 else 'rivre' if i == 7 else 'water'} {'qqqq' if i == 9 else ''}" for i in range(40)] + ["onlyrare", "", None]
    spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string").write.parquet(f"{tmp_path}/documents.parquet")
    spark.createDataFrame([(i, i % 2) for i in range(len(texts))], "doc_id long, toxic int").write.parquet(f"{tmp_path}/labels.parquet")
    made = []
    keep = workloads.materialise
    monkeypatch.setattr(workloads, "materialise", lambda df, tag: made.append((tag, keep(df, tag))) or made[-1][1])
    got = workloads.sentiment(spark, str(tmp_path), "toxic", ("none", "edit_index")).collect()
    assert [r.method for r in got] == ["none", "edit_index"]
    fixed = [df for tag, df in made if tag == "fixed"]
    plain = lambda frame: Counter((r.y, tuple(r.x.toArray())) for r in frame.collect())
    for df, swap in zip(fixed, ({}, {"stonne": "stone"}), strict=True):
        assert "words" not in df.columns
        lists = [(float(i % 2), [swap.get(w, w) for w in (t or "").split()]) for i, t in enumerate(texts) if t]
        assert plain(df) == plain(HashingTF(numFeatures=256, inputCol="words", outputCol="x").transform(spark.createDataFrame(lists, "y double, words array<string>")))


def test_bucket_profiles_in_passes(spark, small, monkeypatch):
    """Counts of a few repetitions at a time equal those of all at once, also of no words."""
    from lexnorm.operators import buckets

    want = rows(buckets.profile(buckets.explode(small.sigs)))
    monkeypatch.setattr(buckets, "PASS_ROWS", 30)
    got = buckets.profiles(small.sigs, 20)
    assert rows(got) == want and len(want) == 20
    assert len(got.inputFiles()) >= 7
    none = small.sigs.where("false")
    assert theory.cost(small.vocab.where("false"), none, 20).first().buckets == 0 and buckets.profiles(none, 20).count() == 0


def test_index_keeps_no_second_copy(spark):
    """Pairs found are the table of edges; pairs, links and rounds go when groups are written."""
    import os

    from lexnorm.sources import store

    def tables(tag):
        top = store._made[spark.sparkContext.applicationId]
        return {x for x in os.listdir(top) if x.startswith(tag + "-")}

    vocab = spark.createDataFrame(list(FAMILIES.items()), "word string, freq long")
    before = {t: tables(t) for t in ("edges", "pairs", "links", "labels", "star", "sizes")}
    index = build_index(vocab, HashParams(bins=2, alpha="0.4"))
    groups = rows(index.norm.select("word", "comp"))
    assert {t: tables(t) for t in before} == before
    edges = rows(index.edges)
    assert edges and tables("edges") == before["edges"]
    assert rows(components(index.links, vocab.select(F.col("word").alias("node")))) == groups
    assert rows(components(index.edges, vocab.select(F.col("word").alias("node")), "hash_min")) == groups


def test_lighter_matches_are_left_out(spark):
    from lexnorm.operators import matching

    words = [f"{w}{'g' * i}" for w in ("amazing", "feeling") for i in range(1, 10)]
    family = hashing.Family.draw(HashParams())
    sigs = lambda some: hashing.signatures(spark.createDataFrame([(w, 1) for w in some], "word string, freq long"), family)
    new, old = sigs(words[::3]), sigs([w for w in words if w not in words[::3]])
    every, best = matching.pairs(new, 20, 4, old).collect(), matching.pairs(new, 20, 4, old, best=True).collect()
    heaviest = {w: max(r.weight for r in every if r.src == w) for w in {r.src for r in every}}
    top = lambda some: {(r.src, r.dst) for r in some if r.weight == heaviest[r.src]}
    assert heaviest and top(best) == top(every) and len(best) < len(every)
