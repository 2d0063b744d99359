"""Language-model scores: a log-bilinear model trained with noise-contrastive estimation.

Word counts come from every training document. The most frequent words are outcomes
of their own, in groups by rank; all others share classes by their last two bytes, the
most frequent endings having a class each. A token's probability is that of its group
or class after the tokens before it, times, in a group, that of the word in it after
the same tokens, and in a class the word's smoothed share of the class's count. Each
class keeps the share of one unseen word, so all outcomes sum to one.

Both levels share one prediction from the context and are trained together by NCE.
Training documents fall into shards by a hash of their id and text. Each shard trains
from a common start in one task, and parameters are averaged by tokens seen, in
``ROUNDS`` rounds: the result depends on the documents alone, not on partitions.
Counts of frequent words are broadcast (``HOT_WORDS`` at most); those of rarer words
are joined.
"""

from __future__ import annotations

import math
from collections import Counter
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
import pyarrow.compute
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from lexnorm.llm.words import Words, slices
from lexnorm.sources.store import materialise, ship

#: Frequent words whose counts are broadcast; the bound holds whatever the corpus.
HOT_WORDS = 200_000
#: Code 0 is the end of a document, then come own words by rank, then classes by ending, the last for all other endings.
GROUP, GROUPS, ENDINGS = 64, 64, 96
OWN = GROUP * GROUPS
CODES = 1 + OWN + ENDINGS
TOP = 1 + GROUPS + ENDINGS
DIM = 16
CONTEXT = 4
#: Noise words of a batch at either level.
NOISE_TOP, NOISE_OWN = 24, 24
#: Tokens of a step: a 256th of a shard's, within these bounds.
LEAST_BATCH, MOST_BATCH = 64, 2048
RATE = 0.035
#: Passes over all training documents, whatever their number; the shards' models are averaged after each.
ROUNDS = 2
#: Shards grow in number and size with the root of the corpus: the tokens of one shard of one.
SHARD_TOKENS = 250_000
SEED = 11
FOLDS, HELD_OUT = 7, 2
#: Distinct words a task counts before it sends what it has.
FLUSH = 400_000
NEVER = np.float32(-1e9)


@dataclass
class Shares:
    """Unigram shares of the outcomes of both levels; an outcome without words has none."""

    top: np.ndarray
    own: np.ndarray

    @staticmethod
    def of(ends: int, own: np.ndarray, classes: np.ndarray) -> Shares:
        counts = np.zeros(OWN)
        counts[: len(own)] = own
        top = np.concatenate([[ends + 1.0], counts.reshape(GROUPS, GROUP).sum(axis=1), classes + 1.0])
        return Shares(top / top.sum(), counts / max(counts.sum(), 1))


def _log(x: np.ndarray) -> np.ndarray:
    return np.where(x > 0, np.log(np.maximum(x, 1e-300)), NEVER).astype(np.float32)


def top_of(codes: np.ndarray) -> np.ndarray:
    """The first-level outcome of each code."""
    return np.where(codes > OWN, codes - OWN + GROUPS, (codes + GROUP - 1) // GROUP)


@dataclass
class Model:
    """Vectors of context codes, weights by context position, vectors and biases of the outcomes of both levels."""

    context: np.ndarray
    position: np.ndarray
    top: np.ndarray
    own: np.ndarray
    top_bias: np.ndarray
    own_bias: np.ndarray

    SHAPES = ((CODES, DIM), (CONTEXT, DIM), (TOP, DIM), (OWN, DIM), (TOP,), (OWN,))

    @staticmethod
    def start(shares: Shares, seed: int = SEED) -> Model:
        rng = np.random.default_rng(seed)
        draw = lambda *s: rng.normal(0, 0.1, s).astype(np.float32)
        return Model(draw(CODES, DIM), np.full((CONTEXT, DIM), 1 / CONTEXT, np.float32), draw(TOP, DIM), draw(OWN, DIM), _log(shares.top), _log(shares.own))

    def parts(self) -> tuple[np.ndarray, ...]:
        return self.context, self.position, self.top, self.own, self.top_bias, self.own_bias

    def flat(self) -> np.ndarray:
        return np.concatenate([x.ravel() for x in self.parts()]).astype(np.float32)

    @staticmethod
    def of(flat: np.ndarray) -> Model:
        cuts = np.cumsum([math.prod(s) for s in Model.SHAPES])[:-1]
        return Model(*(x.reshape(s).astype(np.float32) for x, s in zip(np.split(flat, cuts), Model.SHAPES, strict=True)))

    def log10(self, codes: np.ndarray) -> np.ndarray:
        """Normalised log10 probability of each code of whole documents after its context; a class counts as one outcome."""
        out = np.empty(len(codes))
        within = first_of(codes)
        padded = np.concatenate([np.zeros(CONTEXT, codes.dtype), codes])
        for i in range(0, len(codes), 1 << 16):
            c = codes[i : i + (1 << 16)]
            p = sum(v * w for v, w in zip(shifted(self.context, padded, within, i, len(c))[0], self.position, strict=True))
            got, tops = np.empty(len(c)), top_of(c)
            for j in range(0, len(c), 4096):
                part = slice(j, j + 4096)
                got[part] = _normalised(np.add(s := p[part] @ self.top.T, self.top_bias, out=s), tops[part])
            group = np.where((c > 0) & (c <= OWN), (c - 1) // GROUP, GROUPS)
            order = np.argsort(group, kind="stable")
            cuts = np.searchsorted(group[order], np.arange(GROUPS + 1))
            for g in np.flatnonzero(np.diff(cuts)).tolist():
                rows, part = order[cuts[g] : cuts[g + 1]], slice(g * GROUP, (g + 1) * GROUP)
                s = p[rows] @ self.own[part].T
                s += self.own_bias[part]
                got[rows] += _normalised(s, c[rows] - 1 - g * GROUP)
            out[i : i + len(c)] = got
        return out / np.log(10)


def _normalised(s: np.ndarray, chosen: np.ndarray) -> np.ndarray:
    """Log probability of the chosen outcome of each row of scores; rows too large for plain sums are shifted first."""
    own = s[np.arange(len(chosen)), chosen]
    with np.errstate(over="ignore", divide="ignore"):
        out = own - np.log(np.exp(s).sum(axis=1))
    odd = np.flatnonzero(~np.isfinite(out))
    if len(odd):
        top = s[odd].max(axis=1)
        out[odd] = own[odd] - top - np.log(np.exp(s[odd] - top[:, None]).sum(axis=1))
    return out


def first_of(codes: np.ndarray) -> np.ndarray:
    """How many codes stand before each in its document."""
    n = len(codes)
    first = np.zeros(n, dtype=np.int64)
    starts = np.flatnonzero(codes[:-1] == 0) + 1
    first[starts] = starts
    return np.arange(n) - np.maximum.accumulate(first)


def shifted(context: np.ndarray, padded: np.ndarray, within: np.ndarray, at: int, n: int) -> tuple[list[np.ndarray], list[np.ndarray]]:
    """Vectors of the tokens before each of ``n``, nearest first, from one look-up; before a document's start stand ends.

    Also the rows, by distance, where it is such an end.
    """
    rows = context[padded[at : at + n + CONTEXT]]
    vectors, outside = [], []
    for k in range(CONTEXT):
        out = np.flatnonzero(within[at : at + n] <= k)
        v = rows[CONTEXT - 1 - k : CONTEXT - 1 - k + n]
        if len(out):
            v = v.copy()
            v[out] = context[0]
        vectors.append(v)
        outside.append(out)
    return vectors, outside


def train(model: Model, stream: Iterator[np.ndarray], shares: Shares, batch: int = MOST_BATCH, rate: float = RATE, seed: int = SEED) -> int:
    """NCE over a stream of codes (whole documents, ends included); Adagrad steps; returns tokens seen."""
    rng = np.random.default_rng(seed)
    levels = []
    for share, k in ((shares.top, NOISE_TOP), (shares.own, NOISE_OWN)):
        levels.append((np.cumsum(share), k, _log(share * k)))
    parts = model.parts()
    square = [np.ones(x.shape, np.float32) for x in parts]
    span = np.arange(DIM)

    def sigma(x: np.ndarray) -> np.ndarray:
        """The logistic function, in place; an overflow gives zero, as it should."""
        np.negative(x, out=x)
        with np.errstate(over="ignore"):
            np.exp(x, out=x)
        x += 1
        return np.reciprocal(x, out=x)

    def spread(rows: np.ndarray, values: np.ndarray, n: int) -> np.ndarray:
        return np.bincount((rows[:, None] * DIM + span).ravel(), values.ravel(), n * DIM).reshape(n, DIM).astype(np.float32)

    def contrast(p: np.ndarray, c: np.ndarray, level: int, vectors: np.ndarray, bias: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """Gradients of predictions, vectors and biases."""
        cdf, k, logq = levels[level]
        noise = np.minimum(np.searchsorted(cdf, rng.random(k) * cdf[-1], side="right"), len(cdf) - 1)
        q, qn = vectors[c], vectors[noise]
        right = 1 - sigma(np.einsum("ij,ij->i", p, q) + (bias - logq)[c])
        wrong = p @ qn.T
        wrong += bias[noise] - logq[noise]
        np.negative(sigma(wrong), out=wrong)
        rows = np.concatenate([c, noise])
        dv = spread(rows, np.concatenate([right[:, None] * p, wrong.T @ p]), len(vectors))
        db = np.bincount(rows, np.concatenate([right, wrong.sum(axis=0)]), len(vectors)).astype(np.float32)
        return right[:, None] * q + wrong @ qn, dv, db

    seen = 0
    for codes in stream:
        within, tops = first_of(codes), top_of(codes)
        padded = np.concatenate([np.zeros(CONTEXT, codes.dtype), codes])
        for i in range(0, len(codes), batch):
            c, t = codes[i : i + batch], tops[i : i + batch]
            n = len(c)
            seen += n
            vectors, outside = shifted(model.context, padded, within, i, n)
            p = sum(v * w for v, w in zip(vectors, model.position, strict=True))
            dp, dt, dtb = contrast(p, t, 0, model.top, model.top_bias)
            mine = np.flatnonzero((c > 0) & (c <= OWN))
            dpo, do, dob = contrast(p[mine], c[mine] - 1, 1, model.own, model.own_bias) if len(mine) else (0, 0, 0)
            dp[mine] += dpo
            dw = np.stack([(dp * v).sum(axis=0) for v in vectors])
            each, start = np.zeros((n + CONTEXT, DIM), np.float32), np.zeros(DIM, np.float32)
            for k, (w, out) in enumerate(zip(model.position, outside, strict=True)):
                g = dp * w
                if len(out):
                    start += g[out].sum(axis=0)
                    g[out] = 0
                each[CONTEXT - 1 - k : CONTEXT - 1 - k + n] += g
            dc = spread(padded[i : i + n + CONTEXT], each, CODES)
            dc[0] += start
            for x, g, s in zip(parts, (dc, dw, dt, do, dtb, dob), square, strict=True):
                s += g * g
                x += rate * g / np.sqrt(s)
    return seen


class Vocabulary:
    """Codes and counts of frequent words, found by hash."""

    def __init__(self, words: list[bytes], counts: np.ndarray, endings: list[bytes]):
        order = np.argsort(h := Words(pa.array([b" ".join(words)], pa.binary())).hashes())
        self.keys, self.rank = h[order], order.astype(np.int32)
        self.counts = counts.astype(np.float64)
        self.endings = np.full(1 << 16, ENDINGS - 1, dtype=np.int16)
        for i, e in enumerate(endings):
            self.endings[e[0] | e[1] << 8 if len(e) > 1 else e[0]] = i
        # A word of one byte has no byte before it: its ending is that byte and a zero.

    def look_up(self, w: Words) -> tuple[np.ndarray, np.ndarray]:
        """Rank (-1 for rarer words) and code of every word."""
        h = w.hashes()
        rank = np.full(len(h), -1, dtype=np.int32)
        if len(self.keys):
            at = np.minimum(np.searchsorted(self.keys, h), len(self.keys) - 1)
            hit = self.keys[at] == h
            rank[hit] = self.rank[at[hit]]
        if not len(h):
            return rank, np.zeros(0, np.int32)
        last = w.data[w.ends - 1].astype(np.int64)
        long = w.ends - w.starts > 1
        ending = np.where(long, w.data[w.ends - 2] | last << 8, last)
        return rank, np.where((rank >= 0) & (rank < OWN), rank + 1, OWN + 1 + self.endings[ending]).astype(np.int32)


def with_ends(codes: np.ndarray, counts: np.ndarray) -> np.ndarray:
    """Add code 0 after each document."""
    ends = np.cumsum(counts + 1) - 1
    out = np.zeros(len(codes) + len(counts), dtype=np.int32)
    keep = np.ones(len(out), dtype=bool)
    keep[ends] = False
    out[keep] = codes
    return out


def word_counts(documents: DataFrame) -> DataFrame:
    """``word, n`` over the documents; tasks add up what they read before anything is shuffled."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        total: Counter[bytes] = Counter()

        def out() -> pa.RecordBatch:
            b = pa.RecordBatch.from_arrays([pa.array(total.keys(), pa.binary()), pa.array(total.values(), pa.int64())], names=["word", "n"])
            total.clear()
            return b

        for whole in batches:
            for b in slices(whole, "text", 1 << 22):
                w = Words(b.column(0), lower=True)
                _, first, n = np.unique(w.hashes(), return_index=True, return_counts=True)
                raw = w.data.tobytes()
                words = [raw[s:e] for s, e in zip(w.starts[first].tolist(), w.ends[first].tolist())]
                for x, k in zip(words, n.tolist()):
                    total[x] += k
                if len(total) > FLUSH:
                    yield out()
        yield out()

    return documents.select("text").mapInArrow(run, "word binary, n long").groupBy("word").agg(F.sum("n").alias("n"))


def shards_of(tokens: int) -> int:
    return max(1, math.ceil(math.sqrt(tokens / SHARD_TOKENS)))


def _trained(coded: DataFrame, shares: Shares, start: Model, shards: int, batch: int) -> Model:
    """The average, by tokens, of the models that the shards train from ``start``."""
    shared = coded.sparkSession.sparkContext.broadcast((shares, start.flat()))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        q, flat = shared.value

        def stream(first: pa.RecordBatch, left: list[pa.RecordBatch]) -> Iterator[np.ndarray]:
            """The shard's documents, some at a time; what follows it stays in ``left``."""
            shard, b = first.column(0)[0].as_py(), first
            held: list[bytes] = []
            size = 0
            while b is not None:
                mine = pa.compute.sum(pa.compute.equal(b.column(0), shard)).as_py() or 0
                for x in b.column(1).slice(0, mine):
                    held.append(x.as_py())
                    size += len(held[-1])
                    if size > 1 << 19:
                        yield np.frombuffer(b"".join(held), "<i2").astype(np.int32)
                        held, size = [], 0
                if mine < b.num_rows:
                    left.append(b.slice(mine))
                    break
                b = next((x for x in batches if x.num_rows), None)
            if held:
                yield np.frombuffer(b"".join(held), "<i2").astype(np.int32)

        now = next((x for x in batches if x.num_rows), None)
        while now is not None:
            model, left = Model.of(flat), []
            seen = train(model, stream(now, left), q, batch)
            yield pa.RecordBatch.from_arrays([pa.array([float(seen)]), pa.array([model.flat().tobytes()], pa.binary())], names=["weight", "flat"])
            now = left[0] if left else None

    def summed(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        """Models of one task, added up: one row of fixed size goes on."""
        total = weight = 0.0
        for b in batches:
            for w, x in zip(b.column(0).to_pylist(), b.column(1), strict=True):
                total = total + w * np.frombuffer(x.as_py(), np.float32).astype(np.float64)
                weight += w
        if weight:
            yield pa.RecordBatch.from_arrays([pa.array([weight]), pa.array([(total / weight).astype(np.float32).tobytes()], pa.binary())], names=["weight", "flat"])

    kind = "weight double, flat binary"
    placed = coded.select("shard", "codes", "doc_id", "tag").repartitionById(shards, F.col("shard")).sortWithinPartitions("shard", "doc_id", "tag")
    models = materialise(placed.select("shard", "codes").mapInArrow(run, kind), "models")
    rows = models.orderBy("weight", "flat").toLocalIterator() if shards <= 64 else models.repartition(64).mapInArrow(summed, kind).toLocalIterator()
    total = weight = 0.0
    for r in rows:
        total = total + r.weight * np.frombuffer(bytes(r.flat), np.float32).astype(np.float64)
        weight += r.weight
    return Model.of((total / weight).astype(np.float32)) if weight else start


def score(documents: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """Scores of every row, learned from the rows outside the held-out fold.

    Columns: ``doc_id, held_out, n_tokens, n_known, train_tokens, base_score,
    score``. A null or empty text is one end token. A null id is never held out.
    Repeated rows count and are scored as often as they occur. Other columns are
    ignored; an empty table gives an empty result.
    """
    spark = documents.sparkSession
    ship(spark)
    fold = F.crc32(F.col(id_col).cast("long").cast("string").cast("binary")) % FOLDS
    docs = documents.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).cast("binary").alias("text"), F.coalesce(fold == HELD_OUT, F.lit(False)).alias("held_out"))
    learned = docs.where("not held_out")
    counts = materialise(word_counts(learned), "counts")
    n_docs = learned.count()
    n_words, distinct = counts.agg(F.coalesce(F.sum("n"), F.lit(0)), F.count("*")).first()
    total, types = n_words + n_docs, distinct + (n_docs > 0)
    hot = counts.orderBy(F.desc("n"), "word").limit(HOT_WORDS).toArrow()
    words, ns = [bytes(w) for w in hot.column("word").to_pylist()], hot.column("n").to_numpy()
    # Counts and words by ending, at most 65,536 rows; own words are taken off.
    by_end = {bytes(e): [n, v] for e, n, v in counts.groupBy(F.expr("substring(word, -2, 2)")).agg(F.sum("n"), F.count("*")).collect()}
    for w, n in zip(words[:OWN], ns[:OWN].tolist()):
        by_end[w[-2:]][0] -= n
        by_end[w[-2:]][1] -= 1
    endings = sorted((e for e in by_end if by_end[e][1]), key=lambda e: (-by_end[e][0], e))[: ENDINGS - 1]
    place = {e: i for i, e in enumerate(endings)}
    size, kinds = np.zeros(ENDINGS), np.zeros(ENDINGS)
    for e, (n, v) in by_end.items():
        size[place.get(e, ENDINGS - 1)] += n
        kinds[place.get(e, ENDINGS - 1)] += v
    vocabulary = Vocabulary(words, ns, endings)
    shares = Shares.of(n_docs, ns[:OWN], size)
    #: log10 of the denominator of a word's share of its class.
    within = np.log10(size + kinds + 1)
    shared = spark.sparkContext.broadcast((vocabulary, within))
    log_ends = float(np.log10(n_docs + 1))

    def code(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        known, bottoms = shared.value
        log_counts = np.log10(known.counts + 1)
        for whole in batches:
            for b in slices(whole, "text", 1 << 21):
                w = Words(b.column(1), lower=True)
                rank, codes = known.look_up(w)
                n = w.counts
                owner = np.repeat(np.arange(len(n)), n)
                add = lambda v, o: np.bincount(o, v, len(n)).astype(float)
                logs = np.where(rank >= 0, log_counts[rank] if len(log_counts) else 0.0, 0.0)
                classed = np.flatnonzero(codes > OWN)
                part = add(logs[classed] - bottoms[codes[classed] - OWN - 1], owner[classed])
                rare = np.flatnonzero(rank < 0)
                cuts = np.searchsorted(owner[rare], np.arange(len(n) + 1)).astype(np.int32)
                raw = w.data.tobytes()
                tail = pa.ListArray.from_arrays(pa.array(cuts), pa.array([raw[s:e] for s, e in zip(w.starts[rare].tolist(), w.ends[rare].tolist())], pa.binary()))
                stream = with_ends(codes, n).astype("<i2").tobytes()
                ends = (np.cumsum(n + 1) * 2).tolist()
                yield pa.RecordBatch.from_arrays(
                    [b.column(0), b.column(2), pa.array(n + 1), pa.array(add((rank >= 0).astype(float), owner).astype(np.int64)), pa.array(add(logs, owner) + log_ends), pa.array(part), tail, pa.array([stream[s:e] for s, e in zip([0, *ends], ends)], pa.binary())],
                    names=["doc_id", "held_out", "n_tokens", "n_hot", "base", "part", "tail", "codes"],
                )

    kind = "doc_id long, held_out boolean, n_tokens long, n_hot long, base double, part double, tail array<binary>, codes binary"
    shards = shards_of(total)
    batch = min(MOST_BATCH, max(LEAST_BATCH, total // shards // 256))
    tag = F.xxhash64("doc_id", "codes")
    coded = docs.select("doc_id", "text", "held_out").mapInArrow(code, kind).withColumn("row", F.monotonically_increasing_id()).withColumn("tag", tag)
    coded = materialise(coded.withColumn("shard", F.pmod("tag", F.lit(shards)).cast("int")), "coded")
    model = Model.start(shares)
    for _ in range(ROUNDS if n_docs else 0):
        model = _trained(coded.where("not held_out"), shares, model, shards, batch)
    fitted = spark.sparkContext.broadcast(model.flat())

    def chain(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        lm = Model.of(fitted.value)
        for whole in batches:
            for b in slices(whole, "codes", 1 << 20):
                codes = np.frombuffer(b"".join(x.as_py() for x in b.column(0)), "<i2").astype(np.int32)
                n = b.column(1).to_numpy()
                logs = lm.log10(codes)
                yield pa.RecordBatch.from_arrays([pa.array(np.bincount(np.repeat(np.arange(len(n)), n), logs, len(n)).astype(float)), *b.columns[1:]], names=["chain", *b.schema.names[1:]])

    # Rarer words get their counts by a join on the word; no word in it is frequent.
    tail = coded.select("row", F.explode("tail").alias("word"))
    found = tail.join(counts, "word").groupBy("row").agg(F.count("*").alias("more"), F.sum(F.log10(F.col("n") + 1)).alias("logs"))
    log_all = float(np.log10(total + types + 1))
    scored = coded.select("codes", "n_tokens", "row", "doc_id", "held_out", "n_hot", "base", "part").mapInArrow(chain, "chain double, n_tokens long, row long, doc_id long, held_out boolean, n_hot long, base double, part double")
    out = scored.join(found, "row", "left").na.fill({"more": 0, "logs": 0.0})
    return out.select(
        "doc_id",
        "held_out",
        "n_tokens",
        (F.col("n_hot") + F.col("more") + F.lit(int(n_docs > 0))).alias("n_known"),
        F.lit(total).cast("long").alias("train_tokens"),
        (F.col("base") + F.col("logs") - F.col("n_tokens") * F.lit(log_all)).alias("base_score"),
        (F.col("chain") + F.col("part") + F.col("logs")).alias("score"),
    )
