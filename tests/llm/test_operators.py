"""The training-data operators against brute force on small inputs, odd ones included."""

import collections
import hashlib
import math
import random
import re
import zlib

import numpy as np
import pyarrow as pa
import public_tokenizers
import pytest
import xxhash
from pyspark.sql import functions as F

from lexnorm.llm import decontaminate, html_extract, language_model, license_scan, quality, simhash_dedup, substring_dedup, suffix_dedup, token_file, unigram, windows
from lexnorm.llm.words import Words

WORD = re.compile(r"[^\x20\x09-\x0D]+")


def corpus(n=60, seed=2):
    """Texts with copies, near copies, shared passages, blanks, a long one, and repeats within a text."""
    rng = random.Random(seed)
    vocab = [f"w{i}" for i in range(400)] + ["été", "日本", "x,y", "A", "a", " z"]
    text = lambda k: " ".join(rng.choice(vocab) for _ in range(k))
    passage, long = text(70), text(5000)
    out = [text(rng.randint(1, 120)) for _ in range(n)]
    out[5] = out[3] = text(90)
    out[7] = text(20) + "\n" + passage + "\t" + text(10)
    out[2] = passage + "  " + text(30)
    out[9] = out[8] + " extra"
    out[10] = (passage + " ") * 2
    out[11] = long
    out[12] = long.replace("w7 ", "w8 ")
    out += ["", None, " \n\t ", "one", None]
    return list(enumerate(out))


@pytest.fixture(scope="module")
def docs(spark):
    rows = [(i, t, "en", "s", len(t or ""), "clash", t) for i, t in corpus()]
    return spark.createDataFrame(rows, "doc_id long, text string, lang string, source string, n_chars int, tag string, kept_text string").repartition(3)


def without(docs):
    return docs.where("false")


def test_words_equal_regex():
    texts = [t for _, t in corpus()]
    w = Words(pa.array([None if t is None else t.encode() for t in texts], pa.binary()))
    assert w.counts.tolist() == [len(WORD.findall(t or "")) for t in texts]
    h = w.hashes()
    known = {}
    flat = [x for t in texts for x in WORD.findall(t or "")]
    for x, y in zip(flat, h.tolist(), strict=True):
        assert known.setdefault(x, y) == y
    assert len(set(known.values())) == len(known)


@pytest.mark.parametrize("module", [substring_dedup, suffix_dedup])
def test_substring_removal(spark, docs, module, monkeypatch):
    first = {}
    data = corpus()
    for i, t in data:
        w = WORD.findall(t or "")
        for k in range(len(w) - 49):
            first.setdefault(tuple(w[k : k + 50]), i)
    want = {}
    for i, t in data:
        w = WORD.findall(t or "")
        gone = set()
        for k in range(len(w) - 49):
            if first[tuple(w[k : k + 50])] < i:
                gone.update(range(k, k + 50))
        kept = " ".join(x for k, x in enumerate(w) if k not in gone)
        want[i] = (len(w), len(gone), hashlib.sha256(kept.encode()).hexdigest(), kept)
    assert sum(v[1] for v in want.values()) > 200
    run = lambda d, **o: {r.doc_id: (r.n_words, r.n_removed, r.kept_sha256, r.kept_text) for r in module.remove_repeats(d, **o).collect()}
    assert run(docs) == want
    assert run(without(docs)) == {}
    extra = docs.unionByName(docs.where("doc_id = 2")).unionByName(docs.where("doc_id = 5").withColumn("doc_id", F.lit(None).cast("long")))
    got = run(extra)
    assert got.pop(None)[1] == 0 and got == want
    carried = module.remove_repeats(docs, carry=("lang", "tag")).where("doc_id = 2").first()
    assert (carried.lang, carried.tag) == ("en", "clash")
    assert run(docs, **({"broadcast_rows": 0} if module is suffix_dedup else {"most_bits": 0})) == want
    monkeypatch.setattr(windows, "BROADCAST_ROWS", 0)
    assert run(docs) == want


def thue_morse(n, a="a", b="b"):
    """Two letters arranged so that sums of powers of any odd number agree for the two exchanges."""
    return "".join((a, b)[bin(i).count("1") & 1] for i in range(n))


@pytest.mark.parametrize("module", [substring_dedup, suffix_dedup])
def test_unlike_long_words_stay(spark, module):
    one, two = thue_morse(1024), thue_morse(1024, "b", "a")
    long = ["x" * n + "y" for n in (127, 128, 129, 5000)]
    rows = [(1, " ".join([one] * 50)), (2, " ".join([two] * 50)), (3, " ".join(long * 13)), (4, " ".join(long * 13) + " z"), (4, "other text of one id")]
    out = {(r.doc_id, r.n_words): r.n_removed for r in module.remove_repeats(spark.createDataFrame(rows, "doc_id long, text string")).collect()}
    assert out == {(1, 50): 0, (2, 50): 0, (3, 52): 0, (4, 53): 52, (4, 5): 0}


@pytest.mark.parametrize("module", [substring_dedup, suffix_dedup])
@pytest.mark.parametrize("seed", [1, 2])
def test_substring_removal_of_random_texts(spark, module, seed):
    """Few words and short windows, so that repeats abound, against brute force."""
    rng = random.Random(seed)
    words = [thue_morse(64), thue_morse(64, "b", "a"), "a", "b"]
    data = [(i, " ".join(rng.choices(words, k=rng.randint(0, 40)))) for i in range(40)]
    size, gram = 8, 4
    first, want = {}, {}
    for i, t in data:
        w = t.split()
        for k in range(len(w) - size + 1):
            first.setdefault(tuple(w[k : k + size]), i)
    for i, t in data:
        w = t.split()
        gone = {j for k in range(len(w) - size + 1) if first[tuple(w[k : k + size])] < i for j in range(k, k + size)}
        want[i] = (len(gone), " ".join(x for j, x in enumerate(w) if j not in gone))
    got = module.remove_repeats(spark.createDataFrame(data, "doc_id long, text string"), size=size, gram=gram)
    assert {r.doc_id: (r.n_removed, r.kept_text) for r in got.collect()} == want


def test_unlike_windows_are_no_repeats(spark):
    """The words of eight-word windows decide, not their hashes."""
    one, two = thue_morse(1024), thue_morse(1024, "b", "a")
    texts = pa.array([" ".join([one] * 8 + ["x"] + [two] * 8).encode(), " ".join([one] * 9).encode()], pa.binary())
    assert quality.statistics(texts)[0]["n_repeat_words"].tolist() == [0, 9]


def test_simhash(spark, docs):
    def fingerprint(text):
        w = (text or "").encode().lower().split()
        s = [b" ".join(w[i : i + 3]) for i in range(len(w) - 2)] if len(w) >= 3 else [b" ".join(w)] if w else []
        h = [xxhash.xxh64_intdigest(x, 42) for x in s]
        return sum(1 << b for b in range(64) if 2 * sum(x >> b & 1 for x in h) > len(h))

    data = corpus()
    fps = {i: fingerprint(t) for i, t in data}
    comp = {i: i for i in fps}
    for _ in fps:
        for a in fps:
            for b in fps:
                if (fps[a] ^ fps[b]).bit_count() <= 3:
                    comp[a] = comp[b] = min(comp[a], comp[b])
        if all(comp[a] == comp[b] for a in fps for b in fps if (fps[a] ^ fps[b]).bit_count() <= 3):
            break
    got = {r.doc_id: (int(r.fingerprint, 16), r.component_id) for r in simhash_dedup.near_duplicates(docs).collect()}
    assert got == {i: (fps[i], comp[i]) for i in fps}
    assert simhash_dedup.near_duplicates(without(docs)).count() == 0


def test_vantage_point_shards_find_all_pairs():
    rng = np.random.default_rng(4)
    base = rng.integers(0, 2**63, 1500, dtype=np.uint64)
    ball = base[0] ^ (np.uint64(1) << rng.integers(0, 64, 600, dtype=np.uint64)) ^ (np.uint64(1) << rng.integers(0, 64, 600, dtype=np.uint64))
    near = base[:400] ^ (np.uint64(1) << rng.integers(0, 64, 400, dtype=np.uint64))
    fps = np.unique(np.concatenate([base, ball, near]))
    tree, leaves = simhash_dedup.grow(fps[::3], len(fps), shard=100)
    assert leaves > 4
    r, cell, home = simhash_dedup.routes(tree, fps)
    parent = list(range(len(fps)))

    def root(x):
        while parent[x] != x:
            x = parent[x]
        return x

    for c in np.unique(cell):
        at = r[cell == c]
        for a, b in simhash_dedup.forest(fps[at], home[cell == c]):
            a, b = root(int(at[a])), root(int(at[b]))
            parent[max(a, b)] = min(a, b)
    want = list(range(len(fps)))

    def top(x):
        while want[x] != x:
            x = want[x]
        return x

    for i in range(len(fps)):
        for j in np.flatnonzero(np.bitwise_count(fps[i + 1 :] ^ fps[i]) <= 3) + i + 1:
            a, b = top(i), top(int(j))
            want[max(a, b)] = min(a, b)
    assert [root(i) for i in range(len(fps))] == [top(i) for i in range(len(fps))]


def test_quality_statistics(spark, docs):
    labels = spark.createDataFrame([(i, int(i % 4 > 0), 0) for i in range(60)] + [(None, 1, 0), (3, None, 0)], "doc_id long, quality int, toxic int")
    got = {r.doc_id: r for r in quality.judge(docs, labels).collect()}
    for i, t in corpus():
        w = WORD.findall(t or "")
        seen, dup = set(), 0
        for line in (t or "").split("\n"):
            if WORD.search(line):
                dup += line in seen
                seen.add(line)
        many = collections.Counter(tuple(w[k : k + 8]) for k in range(len(w) - 7))
        again = {k + j for k in range(len(w) - 7) if many[tuple(w[k : k + 8])] > 1 for j in range(8)}
        r = got[i]
        assert (r.n_words, r.word_chars, r.n_symbols, r.n_dup_lines, r.n_repeat_words) == (len(w), sum(map(len, w)), len(re.findall(r"[#*$%&|<>]", t or "")), dup, len(again))
        assert r.base_failed == (len(w) < 20 or 100 * len(again) > 30 * len(w)) and not (r.base_failed and r.kept)
    assert quality.judge(without(docs), labels).count() == 0
    nolabels = quality.judge(docs, labels.where("false")).where("not base_failed and not kept").count()
    assert nolabels == 0


def test_isolation_forest_finds_odd_rows():
    rng = np.random.default_rng(0)
    x = rng.normal(0.5, 0.05, (800, len(quality.FEATURES)))
    odd = x[:40].copy()
    odd[:, :5] += 0.6
    forest = quality.grow_forest(x[200:])
    assert np.median(forest.score(odd)) > np.percentile(forest.score(x[40:200]), 95)


def test_language_model(spark):
    rng = random.Random(0)
    a, b = [f"a{i}" for i in range(30)], [f"b{i}" for i in range(30)]
    data = [(i, " ".join(rng.choice(a if i % 2 else b) for _ in range(rng.randint(5, 60)))) for i in range(400)] + [(900, None), (901, ""), (902, "ABC abc zzz")]
    df = spark.createDataFrame(data, "doc_id long, text string")
    got = {r.doc_id: r for r in language_model.score(df).collect()}
    toks = {i: [*(t or "").encode().lower().split(), b""] for i, t in data}
    held = {i: zlib.crc32(str(i).encode()) % 7 == 2 for i in toks}
    c = collections.Counter(w for i, t in toks.items() if not held[i] for w in t)
    n, v = sum(c.values()), len(c)
    for i, t in toks.items():
        r = got[i]
        assert (r.held_out, r.n_tokens, r.n_known, r.train_tokens) == (held[i], len(t), sum(c[w] > 0 for w in t), n)
        assert r.base_score == pytest.approx(sum(math.log10((c[w] + 1) / (n + v + 1)) for w in t), rel=1e-9)
    out = [i for i in toks if held[i] and i < 900]
    assert sum(got[i].score for i in out) > sum(got[i].base_score for i in out)


def softmax(x):
    e = np.exp(x - x.max())
    return e / e.sum()


def test_language_model_score_equals_a_plain_reading_of_the_trained_model(spark, monkeypatch):
    """Every probability by whole softmaxes; all outcomes, and one unseen word for each class, sum to one."""
    lm = language_model
    models, trained = [], lm._trained
    monkeypatch.setattr(lm, "_trained", lambda *a: models.append(trained(*a)) or models[-1])
    rng = random.Random(5)
    vocab = [f"{x}{i}" for i in range(1500) for x in ("p", "q", "é", "Z")]
    data = [(i, " ".join(rng.choices(vocab, k=rng.randint(0, 60)))) for i in range(400)] + [(1000, "neverseen p1"), (1001, None), (None, "p1 p2"), (None, "p1 p2"), (2, "q3"), (1002, "x " * 30_000)]
    df = spark.createDataFrame([(i, t, "c", 0.0) for i, t in data], "doc_id long, text string, codes string, base double")
    rows = lm.score(df).collect()
    assert len(models) == lm.ROUNDS and len(rows) == len(data)
    m = models[-1]
    words = lambda t: (t or "").encode().lower().split()
    count = collections.Counter(w for i, t in data if i is None or zlib.crc32(str(i).encode()) % 7 != 2 for w in words(t))
    ranked = sorted(count, key=lambda w: (-count[w], w))
    own = {w: k for k, w in enumerate(ranked[: lm.OWN])}
    mass = collections.Counter()
    for w in ranked[lm.OWN :]:
        mass[w[-2:]] += count[w]
    ends = {e: k for k, e in enumerate(sorted(mass, key=lambda e: (-mass[e], e))[: lm.ENDINGS - 1])}
    of = lambda w: ends.get(w[-2:], lm.ENDINGS - 1)
    size, kinds = collections.Counter(), collections.Counter()
    for w in ranked[lm.OWN :]:
        size[of(w)] += count[w]
        kinds[of(w)] += 1
    code = lambda w: own[w] + 1 if w in own else lm.OWN + 1 + of(w)

    def spread(before):
        """Probabilities of all codes."""
        p = sum(m.context[c] * m.position[k] for k, c in enumerate(before))
        top = softmax(m.top @ p + m.top_bias)
        inner = np.concatenate([softmax((m.own @ p + m.own_bias)[g * lm.GROUP : (g + 1) * lm.GROUP]) for g in range(lm.GROUPS)])
        return np.concatenate([top[:1], np.repeat(top[1 : lm.GROUPS + 1], lm.GROUP) * inner, top[lm.GROUPS + 1 :]])

    share = lambda w: 1.0 if w in own else (count[w] + 1) / (size[of(w)] + kinds[of(w)] + 1)
    every = spread([1, 5, 0, 0])
    unseen = sum(every[lm.OWN + 1 + e] / (size[e] + kinds[e] + 1) for e in range(lm.ENDINGS))
    assert every[0] + sum(every[code(w)] * share(w) for w in ranked) + unseen == pytest.approx(1, abs=1e-5)
    memo = {}

    def score(t):
        codes = [code(w) for w in words(t)] + [0]
        out = 0.0
        for k, c in enumerate(codes):
            before = tuple(([*codes[:k][::-1], 0, 0, 0, 0])[: lm.CONTEXT])
            if before not in memo:
                memo[before] = spread(before)
            out += math.log10(memo[before][c])
        return out + sum(math.log10(share(w)) for w in words(t))

    asked = {i for i, _ in data[-60:]}
    want = sorted(score(t) for i, t in data if i in asked)
    got = sorted(r.score for r in rows if r.doc_id in asked)
    assert got == pytest.approx(want, rel=1e-4, abs=1e-3)


def test_language_model_does_not_depend_on_partitions(spark):
    rng = random.Random(7)
    data = [(i, " ".join(rng.choices([f"w{k}" for k in range(60)], k=40))) for i in range(300)]
    df = spark.createDataFrame(data, "doc_id long, text string")
    a, b = ({r.doc_id: r.score for r in language_model.score(df.repartition(n)).collect()} for n in (1, 7))
    assert a == pytest.approx(b, rel=1e-6)
    assert language_model.score(df.where("false")).count() == 0


def test_token_file(spark, docs):
    from tokenizers import Tokenizer

    path = public_tokenizers.path("byte_bpe_50k.json")
    t = Tokenizer.from_file(path)
    data = corpus() + [(500, "<|endoftext|> a　 b\n c"), (-3, "x")]
    df = spark.createDataFrame(data, "doc_id long, text string").repartition(3)
    got = {r.doc_id: (r.start, r.n_tokens, r.ids_crc32) for r in token_file.round_trip(df, path).collect()}
    want, at = {}, 0
    for i, x in sorted(data, key=lambda r: r[0]):
        ids = [*t.encode(x or "", add_special_tokens=False).ids, 0]
        want[i] = (at, len(ids), zlib.crc32(np.array(ids, dtype="<u4").tobytes()))
        at += len(ids)
    assert got == want
    assert token_file.round_trip(without(docs), path).count() == 0


def test_token_file_of_odd_rows_and_single_documents(spark):
    from tokenizers import Tokenizer

    path = public_tokenizers.path("byte_bpe_50k.json")
    t = Tokenizer.from_file(path)
    data = [(None, "no id"), (4, "b twice"), (4, "a twice"), (None, None), (2, "word " * 3000), (9, "")]
    df = spark.createDataFrame([(i, x, 7, 8) for i, x in data], "doc_id long, text string, part int, start int")
    rows = token_file.round_trip(df, path).orderBy("start").collect()
    ordered = sorted(data, key=lambda r: (r[0] is not None, r[0] or 0, r[1] or ""))
    ids = [[*t.encode(x or "", add_special_tokens=False).ids, 0] for _, x in ordered]
    assert [r.doc_id for r in rows] == [i for i, _ in ordered]
    assert [r.n_tokens for r in rows] == list(map(len, ids))
    assert [r.start for r in rows] == [sum(map(len, ids[:k])) for k in range(len(ids))]
    out = token_file.new_folder(spark, "token-file")
    token_file.write(df, out, path)
    got = {r.doc_id: (r.start, r.ids) for r in token_file.fetch(spark, out, [2, 9, 77]).collect()}
    assert got == {i: (sum(map(len, ids[:k])), ids[k]) for k, (i, _) in enumerate(ordered) if i in (2, 9)}


@pytest.mark.parametrize("name", ["byte_bpe_50k.json", "word_bpe_49k.json"])
def test_encoder_equals_the_library(name):
    from tokenizers import Tokenizer

    rng = random.Random(3)
    path = public_tokenizers.path(name)
    t = Tokenizer.from_file(path)
    signs = ["a", "B", "word", "é", "ß", "ǃ", "×", "ɏ", "ɐ", "日", "1", "42", "½", ".", ",", "'", "'s", "$$", "_", " ", "  ", "\n", "\n\n", "\t", "\r\n", "\u00a0", "\u2003", "\x00", "\x7f", "😀", "<|endoftext|>", "İ"]
    plain = ["a", "Bcd", "é", "9", "...", ".", ",", '"', " ", "\n"]
    texts = ["".join(rng.choices(some, k=rng.randint(0, 12))) for some in (signs, plain) for _ in range(1500)]
    enc = token_file.PieceEncoder(path, most=50)
    got = [x for i in range(0, len(texts), 100) for x in enc.encode(texts[i : i + 100])]
    want = [np.array(t.encode(x, add_special_tokens=False).ids, dtype="<u2").tobytes() for x in texts]
    assert [x for x, g, w in zip(texts, got, want) if g != w] == []


@pytest.mark.parametrize("gaps", [[0], [0, 0, 0], [0, 5, 1, 900, 0, 0, 3] * 60, list(range(300)), [0] + [100_000] * 130])
def test_elias_fano(gaps):
    values = np.cumsum(gaps)
    ef = token_file.EliasFano.encode(values)
    assert ef.decode().tolist() == values.tolist() and [ef.select(i) for i in range(len(values))] == values.tolist()
    block = token_file.pack(np.arange(len(gaps)), np.array(gaps), np.arange(values[-1], dtype="<u4").astype("<u2").tobytes(), 2)
    read = token_file.Block.read(block)
    assert all(len(read.document(k)) == g for k, g in enumerate(gaps[:80]))


def test_unigram(spark, docs):
    path = public_tokenizers.path("piece_bpe_32k.model")
    u = unigram.loaded(path, True)
    score = {u.pieces.text[i].encode(): u.score[i] for i in u.pieces.text}

    def best(word):
        top = [0.0] + [-math.inf] * len(word)
        starts = [k for k in range(len(word)) if word[k] & 0xC0 != 0x80] + [len(word)]
        for k, s in enumerate(starts[:-1]):
            top[starts[k + 1]] = max(top[starts[k + 1]], top[s] + u.least)
            for e in starts[k + 1 :]:
                if word[s:e] in score:
                    top[e] = max(top[e], top[s] + score[word[s:e]])
        return top[-1]

    words = [f"▁{w}".encode() for w in ("hello", "tokenization", "été", "日本語", "a\nb", "🎉x", "zzzzqqq")]
    for w, ids in zip(words, u.segment(words), strict=True):
        plain = [int(i) for i in ids if int(i) in u.pieces.text]
        assert b"".join(u.surface[int(i)] for i in ids) == w
        if len(plain) == len(ids):
            assert sum(u.score[plain]) == pytest.approx(best(w))
    for r in unigram.encode_documents(docs, path, rank_scores=True).collect():
        assert r.decoded and r.n_ids == len(r.ids) and r.ids_crc32 == zlib.crc32(np.array(r.ids, dtype="<u4").tobytes())
    assert u.encode(["", "  two  spaces "]) and u.decode(u.encode(["  two  spaces "])[0].tolist()) == "  two  spaces "


def test_decontamination(spark, docs):
    rng = random.Random(5)
    item = [f"t{i}" for i in range(60)]
    edited = [w if rng.random() > 0.12 else "other" for w in item]
    del edited[20:23]
    rows = [(1, "start " + " ".join(item) + " end"), (2, " ".join(edited)), (3, "t1 t2 t3 nothing else of it"), (4, None), (5, ""), (6, " ".join(rng.sample(item, 60)))]
    df = spark.createDataFrame(rows, "doc_id long, text string")
    bench = spark.createDataFrame([(7, " ".join(item)), (8, None), (9, ""), (None, "t1 t2 t3 t4")], "item_id long, text string")
    got = {r.doc_id: r for r in decontaminate.scan(df, bench).collect()}
    assert got[1].contaminated and got[1].score == 1.0 and got[1].best_item == 7
    assert got[2].contaminated and 0.5 <= got[2].score < 1
    assert not any(got[i].contaminated for i in (3, 4, 5, 6))
    assert decontaminate.scan(docs, bench.where("false")).where("contaminated").count() == 0


def test_decontamination_finds_an_edited_copy_in_many_documents(spark):
    item = [f"t{i}" for i in range(60)]
    edited = " ".join("other" if i % 6 == 5 else w for i, w in enumerate(item))
    rows = [(i, f"s{i} {edited} e{i}") for i in range(120)] + [(i, f"s{i} e{i}") for i in range(120, 240)]
    got = decontaminate.scan(spark.createDataFrame(rows, "doc_id long, text string"), spark.createDataFrame([(7, " ".join(item))], "item_id long, text string")).collect()
    assert {r.doc_id for r in got if r.contaminated} == set(range(120))
    assert {r.best_item for r in got if r.doc_id < 120} == {7}


def test_alignment_is_smith_waterman():
    rng = random.Random(1)

    def plain(a, b):
        h = [[0] * (len(b) + 1) for _ in range(len(a) + 1)]
        for i in range(len(a)):
            for j in range(len(b)):
                h[i + 1][j + 1] = max(0, h[i][j] + (2 if a[i] == b[j] else -1), h[i][j + 1] - 1, h[i + 1][j] - 1)
        return max(map(max, h))

    for _ in range(60):
        a, b = ([rng.randint(0, 4) for _ in range(rng.randint(0, 12))] for _ in range(2))
        assert decontaminate.align(np.array(a, dtype=np.int64), np.array(b, dtype=np.int64)) == (plain(a, b) if a and b else 0)


def test_licences(spark, docs):
    lines = ["Licensed under the Apache License, Version 2.0.", "Released under the MIT License.", "This work is licensed under the GNU General Public License, version 3.", "Licensed under CC BY-NC 4.0.", "All rights reserved.", "Permission is hereby granted, free of charge,\nto any person obtaining a copy of this software\nand associated documentation files"]
    df = spark.createDataFrame([*enumerate(f"some text\n{x}\nmore text" for x in lines), (10, "The river is green."), (11, None), (12, "His driving license expired.")], "doc_id long, text string")
    got = {r.doc_id: r.families for r in license_scan.scan(df).collect()}
    assert [got[i] for i in range(6)] == [["apache"], ["mit"], ["gpl"], ["creative_commons"], ["proprietary"], ["mit"]]
    assert got[10] == got[11] == got[12] == []
    assert license_scan.scan(docs).where("n_licences > 0").count() == 0


PAGE = """<!DOCTYPE html><html><head><title>T</title><script>var a="<p>no</p>";</script></head><body class="post">
<header><a href="/">Home</a></header><nav><ul><li><a href="/a">A</a><li><a href="/b">B</a></ul></nav>
<div class="cookie-notice">We use cookies on this site to give you the best experience that we can.</div>
<article><h1>A &amp; B</h1><p>The first   paragraph of the story is here, and it says all that is to be said about it.<p>Short one.
<div class="ad">Buy the best of all the things that you have ever seen in this shop today.</div>
<p>Another paragraph that the writer has put in for the sake of the test &lt;ok&gt; &eacute;.</p>
<section id="comments"><p>I think that this is the worst article that I have ever read in all of my life.</p></section></article>
<aside><p>Related: the other stories that you may like to read when you have the time.</p></aside>
<form><p>Leave a reply and we will be in touch with you as soon as we can.</p></form><footer>&copy; site</footer></body>"""


def test_html(spark):
    want = "A & B The first paragraph of the story is here, and it says all that is to be said about it. Short one. Another paragraph that the writer has put in for the sake of the test <ok> é."
    assert html_extract.main_text(PAGE) == want
    bare = PAGE.replace("<article>", "<div>").replace("</article>", "</div>").replace("<h1>", "<p>").replace("</h1>", "</p>")
    assert "first paragraph" in html_extract.main_text(bare) and "cookies" not in html_extract.main_text(bare)
    df = spark.createDataFrame([(1, "u", PAGE, "x"), (2, None, None, "y"), (3, "v", "", "z"), (4, "w", "<p>a < b", "q"), (5, "w", "<div " * 3000, "q")], "page_id long, url string, html string, text string")
    got = {r.page_id: (r.text, r.n_chars) for r in html_extract.extract(df).collect()}
    assert got[1] == (want, len(want)) and got[2] == got[3] == ("", 0) and len(got) == 5


def test_html_keeps_long_runs_of_short_lines():
    good = "<p>" + "It is the first of the things that we have to say about the work and all of it is for the reader. " * 3 + "</p>"
    lines = [f"line {i}" for i in range(500)]
    text = html_extract.main_text(good + "".join(f"<p>{x}</p>" for x in lines) + good)
    assert all(f" {x} " in text for x in lines)


LONG = "It is the first of the things that we have to say about the work and all of it is for the reader. " * 2 + "That is all of it."


def test_html_of_hard_pages():
    assert html_extract.main_text(f"<p class=it's>{LONG}</p><p>{LONG} again</p>") == f"{LONG} {LONG} again"
    story = "".join(f"<div>{LONG} {i}</div>" for i in range(4))
    teaser = "<article class=card><h3>Read this</h3><p>A teaser for it.</p></article>"
    assert html_extract.main_text(f"<nav><a href=/>Home</a></nav>{teaser}<h1>Story</h1>{story}") == "Story " + " ".join(f"{LONG} {i}" for i in range(4))
    wrapped = f"<div class=sidebar-page><p>{LONG}</p><footer>The imprint of the site</footer></div>"
    assert html_extract.main_text(wrapped) == LONG
    assert html_extract.main_text(f"<div class=comments><p>{LONG}</p></div><p>{LONG}x</p><aside>{LONG}</aside>") == f"{LONG}x"
    assert html_extract.main_text("<div>" * 20_000 + LONG) == LONG
    assert html_extract.main_text(f"<p hidden>{LONG}</p><p style='display:none'>{LONG}</p><template>{LONG}</template>") == ""


def test_html_rules_decide():
    """Without tags, roles and class words, numbers and neighbours tell text from the rest."""
    links = "".join(f"<div><a href=/{i}>Section number {i} of the site and more</a></div>" for i in range(6))
    short = "<div>A short line of it.</div>"
    page = f"{links}{short}<div>{LONG}</div>{short}<div>{LONG}</div>{links}{short}"
    line = "A short line of it."
    assert html_extract.main_text(page) == f"{LONG} {line} {LONG}"
    assert "Section" in html_extract.main_text(page, html_extract.Rules(most_links=1.0, density_high=0.0, length_high=0, length_low=0))


@pytest.mark.parametrize("seed", range(5))
def test_html_second_pass_equals_a_search_outwards(seed):
    rng = random.Random(seed)
    for _ in range(200):
        n = rng.randint(0, 12)
        found = [html_extract.Block("x", 0, rng.random() < 0.2, rng.random() < 0.5, rng.random() < 0.2) for _ in range(n)]
        first = [rng.choice(("good", "bad", "near", "short", "short")) for _ in range(n)]

        def look(i, step, sections):
            j = i
            while True:
                if sections and step < 0 and found[j].heading:
                    return None
                j += step
                if not 0 <= j < n or found[j].in_article != found[j - step].in_article:
                    return "bad"
                if sections and step > 0 and found[j].heading:
                    return None
                if first[j] in ("good", "bad") and not found[j].marked:
                    return first[j]

        want = []
        for i, x in enumerate(first):
            near, wide = ((look(i, -1, s), look(i, 1, s)) for s in (True, False))
            want.append(x if x in ("good", "bad") else html_extract.inherit(found[i], x, near, wide))
        assert html_extract.second_pass(found, first) == want


def test_html_of_odd_rows(spark):
    df = spark.createDataFrame([(None, None, f"<p>{LONG}</p>", "a"), (1, "u", f"<p>{LONG}</p>", "b"), (1, "u", f"<p>{LONG}</p>", "b"), (2, "v", f"<p>{LONG}</p>" * 3000, "c")], "page_id long, url string, html string, text string")
    got = sorted(((r.page_id or 0, r.url, r.n_chars) for r in html_extract.extract(df).collect()), key=str)
    n = len(LONG)
    assert got == [(0, None, n), (1, "u", n), (1, "u", n), (2, "v", 3000 * n + 2999)]
    assert html_extract.extract(df.where("false")).count() == 0


def test_pipeline_drops_near_copies_of_jaccard_080(spark):
    import corpus_pipeline as cp

    rng = random.Random(8)
    text = lambda k: [f"v{rng.randrange(5000)}" for _ in range(k)]
    runs = lambda w: {tuple(w[i : i + 5]) for i in range(len(w) - 4)}
    rows, drop = [], set()
    for i in range(60):
        one, edits = text(150), rng.choice((1, 3, 5, 8))
        two = list(one)
        for at in rng.sample(range(150), edits):
            two[at] = "edited"
        rows += [(2 * i, " ".join(one)), (2 * i + 1, " ".join(two))]
        if len(runs(one) & runs(two)) / len(runs(one) | runs(two)) >= 0.8:
            drop.add(2 * i + 1)
    assert 15 < len(drop) < 50
    d = spark.createDataFrame([(i, t, "en", "s", len(t)) for i, t in rows], "doc_id long, text string, lang string, source string, n_chars long").repartition(3)
    assert {r.doc_id for r in cp.simhash_near_dedup(spark, d, "").collect()} == set(range(120)) - drop


def test_near_copies_are_all_joined(spark, monkeypatch):
    """Groups equal brute force where bands find nothing, with runs that crowd the first ones and buckets of several blocks."""
    monkeypatch.setattr(simhash_dedup, "CROWD", 4)
    monkeypatch.setattr(simhash_dedup, "GRID", 8)
    monkeypatch.setattr(simhash_dedup, "_candidates", lambda distinct, radius: distinct.select(F.col("doc_id").alias("src"), F.col("doc_id").alias("dst")).where("false"))
    rng = random.Random(5)
    text = lambda k: [f"v{rng.randrange(9000)}" for _ in range(k)]
    passage, rows = text(60), [(900, ""), (901, None), (902, "one two"), (903, "one  TWO"), (904, "one two three")]
    for i in range(40):
        one = passage + text(rng.choice((5, 20, 90)))
        two = list(one)
        for at in rng.sample(range(len(one)), rng.choice((1, 2, 4))):
            two[at] = "edited"
        rows += [(3 * i, " ".join(one)), (3 * i + 1, " ".join(two)), (3 * i + 2, " ".join(one[1:] + ["end"]))]
    sets = {}
    for i, t in rows:
        w = (t or "").lower().split()
        sets[i] = {tuple(w[k : k + 5]) for k in range(max(1, len(w) - 4))} if w else set()
    group = {i: i for i in sets}
    for a in sets:
        for b in sets:
            if a < b and 5 * len(sets[a] & sets[b]) >= 4 * len(sets[a] | sets[b]) and group[a] != group[b]:
                low, high = sorted((group[a], group[b]))
                group = {k: low if v == high else v for k, v in group.items()}
    assert 20 < len(set(group.values())) < 110
    d = spark.createDataFrame(rows, "doc_id long, text string").repartition(3)
    assert {r.doc_id: r.component_id for r in simhash_dedup.near_copies(d).collect()} == group


def test_shared_passages_nominate_no_pairs(spark, monkeypatch):
    """Long texts that share a passage only aren't tried with each other; rare runs come first."""
    tried, missed = [], simhash_dedup._missed

    def counted(*args):
        out = missed(*args)
        tried.append(out.count())
        return out

    monkeypatch.setattr(simhash_dedup, "_missed", counted)
    rng = random.Random(6)
    text = lambda k: [f"v{rng.randrange(9000)}" for _ in range(k)]
    passage = text(40)
    rows = [(i, " ".join(text(700) + passage + text(700))) for i in range(60)]
    d = spark.createDataFrame(rows, "doc_id long, text string").repartition(3)
    assert {r.doc_id: r.component_id for r in simhash_dedup.near_copies(d).collect()} == {i: i for i in range(60)}
    assert tried == [0]
    # A cell tells how many rows hold its runs; runs of one row come first and are left out.
    table = simhash_dedup._crowds(d, 60 * 1436, 5)
    common = simhash_dedup._run_sets([" ".join(passage).encode()], 5)[0]
    assert set(simhash_dedup._levels(table, common).tolist()) <= {2, 3}
    assert len(simhash_dedup._first(common, table)) == 8


def test_pipeline(spark, docs):
    import corpus_pipeline as cp

    assert [n for n, _ in cp.STAGES] == ["quality_rules", "simhash_near_dedup", "suffix_array_dedup", "benchmark_decontamination", "unigram_encoding"]
    d = docs.select("doc_id", "text", "lang", "source", F.col("n_chars").cast("long").alias("n_chars")).unionByName(docs.where("doc_id in (20, 21)").select(F.lit(None).cast("long").alias("doc_id"), "text", F.lit(None).cast("string").alias("lang"), "source", F.col("n_chars").cast("long").alias("n_chars")))
    for name, stage in cp.STAGES[:-1]:
        out = stage(spark, d, "/root/testdata/sf0.001")
        assert out.columns == list(cp.COLUMNS), name
        assert stage(spark, d.where("false"), "/root/testdata/sf0.001").count() == 0
    kept = {r.doc_id for r in cp.simhash_near_dedup(spark, d, "").collect()}
    assert 3 in kept and 5 not in kept and None in kept
    short = {r.doc_id: r.text for r in cp.suffix_array_dedup(spark, d, "").collect()}
    assert len(short[7].split()) == 30 and 10 not in short
    assert cp.unigram_encoding(spark, d, "").where("decoded").count() == d.count()


#: Wordings that stand nowhere in the module.
HELD_OUT = {
    "mit": ["Distributed under the MIT licence, see LICENSE.txt", "Dieses Programm wird unter der MIT-Lizenz angeboten", "Code is MIT licensed", "We ship it under the MIT license.", "It is MIT License software"],
    "gpl": ["GPLv2 only", "under the terms of the GNU LGPL version 3", "It may be copied under the terms of the GNU GPL", "You can use it according to the GNU General Public License v3", "This file falls under the LGPL 2.1", "Freigegeben unter der GNU GPL, Version 3"],
    "apache": ["The code is under Apache 2", "This module is offered under an Apache 2.0 license", "Use permitted by the Apache License 2.0", "The sources come with the Apache License, v2", "Diese Bibliothek unterliegt der Apache-Lizenz 2.0"],
    "creative_commons": ["Published under Creative Commons Attribution-ShareAlike 3.0", "Text is available under CC BY-SA 3.0", "Photos: CC-BY-4.0", "Image used under a Creative Commons licence", "Except where noted, content is CC BY 4.0"],
    "bsd": ["It is offered under the two-clause BSD licence", "BSD licensed, see COPYING", "This tool carries a BSD license", "Code under BSD-3-Clause"],
    "mpl": ["Files here fall under the MPL 2.0", "The engine is offered under the Mozilla Public License", "Covered by MPL-1.1"],
    "public_domain": ["This text has been placed in the public domain", "Data is dedicated under CC0", "The maps are in the public domain"],
    "proprietary": ["Copyright 2021 Some Company, all rights reserved", "No part of this book may be reproduced without permission in writing from the publisher", "All rights reserved worldwide"],
}


def test_license_recall_on_unseen_wordings():
    asked = [(f, w) for f, ws in HELD_OUT.items() for w in ws]
    hits = [f in license_scan.classify(f"some words of the text\n{w}\nmore words here") for f, w in asked]
    assert sum(hits) >= 0.9 * len(hits)
    for w in ("Licensed under the Q Public License", "This is under the Eiffel Forum License", "Released under the Sleepycat License, see file", "Distributed under the Zope Public License 2.1"):
        assert license_scan.classify(w) == ["unknown"]
    for w in ("The general public has rights reserved to few.", "Commons are creative places.", "A copy of this letter is in the file.", "The apache tribe moved on.", "The software was sold.", "", "\n\n", "."):
        assert license_scan.classify(w) == []


def test_license_training_halves_share_no_source():
    a, b = ({t for t, _ in license_scan.training_rows(5, held)} for held in (False, True))
    from lexnorm.llm.license_templates import SENTENCES

    sentences = {x for texts in SENTENCES.values() for x in texts}
    assert not a & b & sentences and sentences <= a | b


def test_license_scan_of_odd_rows(spark, docs):
    long = "the river is green and the day is long " * 20_000 + "\nReleased under the MIT License.\n" + "word " * 20_000
    rows = [(None, "All rights reserved."), (1, "Licensed under CC BY-NC 4.0."), (1, "Licensed under CC BY-NC 4.0."), (2, long), (3, None), (4, "")]
    df = spark.createDataFrame([(i, t, 5) for i, t in rows], "doc_id long, text string, line int")
    got = sorted(((r.doc_id or 0, r.families, [x.line for x in r.found]) for r in license_scan.scan(df).collect()), key=str)
    assert got == [(0, ["proprietary"], [0]), (1, ["creative_commons"], [0]), (1, ["creative_commons"], [0]), (2, ["mit"], [1]), (3, [], []), (4, [], [])]
    assert license_scan.scan(without(docs)).count() == 0
