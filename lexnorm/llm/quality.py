"""Quality rules with an isolation forest over their statistics.

Base rules reject outright. What they pass is judged by an isolation forest: many
trees of random splits, grown on small subsamples of the rule statistics of
documents labelled good. Documents unlike those fall to a leaf after few splits.
The threshold on the mean path length is calibrated on labelled rows.

The forest and the threshold are fitted on at most ``FIT_ROWS`` labelled
documents (those with the lowest hash of their id); statistics and verdicts cover
every document.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from lexnorm.llm.words import ROLLING, Words, carried, mix, restored, slices
from lexnorm.sources.store import ship

#: Bound of the labelled sample.
FIT_ROWS = 20_000
TREES = 100
SUBSAMPLE = 256
SEED = 17
#: Scores stay below one; without labels of both kinds no document is rejected by its score.
ACCEPT_ALL = 2.0
MIN_WORDS = 20
MOST_REPEATED = 30  # percent of words in repeated windows
WINDOW = 8
#: Characters counted as symbols (fixed values).
SYMBOLS = b"#*$%&|<>"

BASE = ("n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words")
#: Statistics the forest sees, all of them shares or ratios that length hardly moves. What the base
#: rules settle (repeated windows) is left out, so a good text with one repeated line isn't odd.
FEATURES = ("symbol_share", "upper_share", "bang_share", "mean_word", "long_words", "short_words", "common_share", "ended_words", "line_words", "stutter_share")

_IS_SYMBOL = np.zeros(256, dtype=bool)
_IS_SYMBOL[list(SYMBOLS)] = True
_CLASS = {
    "upper": np.isin(np.arange(256), np.arange(65, 91)),
    "lower": np.isin(np.arange(256), np.arange(97, 123)) | (np.arange(256) >= 0xC0),
    "bang": np.isin(np.arange(256), np.frombuffer(b"!?", np.uint8)),
    "ended": np.isin(np.arange(256), np.frombuffer(b".,;:!?", np.uint8)),
}


def _sums(flags: np.ndarray, off: np.ndarray) -> np.ndarray:
    total = np.zeros(len(flags) + 1, dtype=np.int64)
    np.cumsum(flags, out=total[1:])
    return total[off[1:]] - total[off[:-1]]


def _dup_lines(text: bytes) -> int:
    if b"\n" not in text:
        return 0
    seen: set[bytes] = set()
    n = 0
    for line in text.split(b"\n"):
        if line.strip(b" \t\n\x0b\x0c\r"):
            n += line in seen
            seen.add(line)
    return n


def _repeat_words(w: Words, hashes: np.ndarray) -> np.ndarray:
    """Words inside windows of eight that occur twice or more in their text."""
    n = len(hashes) - WINDOW + 1
    out = np.zeros(len(w), dtype=np.int64)
    if n <= 0:
        return out
    owner = np.repeat(np.arange(len(w)), w.counts)
    ends = np.repeat(w.first[1:], w.counts)[:n]
    starts = np.flatnonzero(np.arange(n) + WINDOW <= ends)
    if not len(starts):
        return out
    keys = mix(ROLLING[0](hashes, WINDOW)[starts] + owner[starts].astype(np.uint64) * np.uint64(0x9E3779B97F4A7C15))
    order = np.argsort(keys, kind="stable")
    k = keys[order]
    same = k[1:] == k[:-1]
    first, second = starts[order[:-1]][same], starts[order[1:]][same]
    alike = owner[first] == owner[second]
    for i in range(WINDOW):  # equal hashes of windows count only if their words agree
        alike &= hashes[first + i] == hashes[second + i]
    same[same] = alike
    again = np.zeros(len(k), dtype=bool)
    again[1:] |= same
    again[:-1] |= same
    hit = starts[order[again]]
    mark = np.zeros(len(hashes) + 1, dtype=np.int32)
    np.add.at(mark, hit, 1)
    np.add.at(mark, hit + WINDOW, -1)
    return np.bincount(owner[np.cumsum(mark[:-1]) > 0], minlength=len(w))


def statistics(texts: pa.Array) -> tuple[dict[str, np.ndarray], np.ndarray]:
    """Base counts, and the feature matrix, of a batch of texts."""
    w = Words(texts)
    h = w.hashes()
    d, off, n = w.data, w.off, w.counts
    # Code points outside white space: bytes that don't continue a character.
    points = _sums(w.solid & ((d & 0xC0) != 0x80), off)
    raw = [x.as_py() or b"" for x in texts]
    base = {
        "n_words": n,
        "word_chars": points,
        "n_symbols": _sums(_IS_SYMBOL[d], off),
        "n_dup_lines": np.array([_dup_lines(x) for x in raw], dtype=np.int64),
        "n_repeat_words": _repeat_words(w, h),
    }
    by = {k: _sums(v[d], off) for k, v in _CLASS.items()}
    sizes = w.ends - w.starts
    owner = np.repeat(np.arange(len(w)), n)
    count = lambda flags: np.bincount(owner[flags], minlength=len(w))
    stutter = np.zeros(len(h), dtype=bool)
    stutter[1:] = (h[1:] == h[:-1]) & (owner[1:] == owner[:-1])
    tails = _CLASS["ended"][d[w.ends - 1]] if len(w.ends) else np.zeros(0, bool)
    lines = np.array([x.count(b"\n") + 1 for x in raw], dtype=np.int64)
    one, ch = np.maximum(n, 1), np.maximum(points, 1)
    letters = np.maximum(by["upper"] + by["lower"], 1)
    features = np.stack(
        [
            base["n_symbols"] / ch,
            by["upper"] / letters,
            by["bang"] / one,
            np.minimum(points / one, 20),
            count(sizes >= 12) / one,
            count(sizes <= 3) / one,
            count(sizes == 1) / one,
            count(tails) / one,
            np.log1p(n / lines),
            count(stutter) / one,
        ],
        axis=1,
    )
    return base, features


@dataclass(frozen=True)
class Forest:
    """Trees as flat arrays: feature (-1 at leaves), cut, children, and path length at leaves."""

    feature: np.ndarray
    cut: np.ndarray
    left: np.ndarray
    right: np.ndarray
    depth: np.ndarray
    roots: np.ndarray
    norm: float
    low: np.ndarray
    high: np.ndarray

    def score(self, x: np.ndarray) -> np.ndarray:
        """Anomaly score in (0, 1): near one half for the usual, higher for the odd."""
        x = np.clip((x - self.low) / np.maximum(self.high - self.low, 1e-12), -1, 2)
        total = np.zeros(len(x))
        rows = np.arange(len(x))
        for root in self.roots:
            at = np.full(len(x), root)
            while True:
                f = self.feature[at]
                live = f >= 0
                if not live.any():
                    break
                go = x[rows, np.maximum(f, 0)] < self.cut[at]
                at = np.where(live, np.where(go, self.left[at], self.right[at]), at)
            total += self.depth[at]
        return 2.0 ** (-(total / len(self.roots)) / self.norm)


def _usual_path(n: int) -> float:
    """Mean depth of an unsuccessful search in a random binary tree of ``n`` keys."""
    return 0.0 if n < 2 else 2 * (np.log(n - 1) + 0.5772156649) - 2 * (n - 1) / n if n > 2 else 1.0


def grow_forest(x: np.ndarray, trees: int = TREES, subsample: int = SUBSAMPLE, seed: int = SEED) -> Forest:
    rng = np.random.default_rng(seed)
    low, high = (x.min(axis=0), x.max(axis=0)) if len(x) else (np.zeros(len(FEATURES)), np.ones(len(FEATURES)))
    scaled = np.clip((x - low) / np.maximum(high - low, 1e-12), -1, 2)
    size = min(subsample, len(x))
    most = max(1, int(np.ceil(np.log2(max(size, 2)))))
    feature, cut, left, right, depth, roots = [], [], [], [], [], []

    def add(points: np.ndarray, d: int) -> int:
        me = len(feature)
        for a in (feature, cut, left, right, depth):
            a.append(-1)
        depth[me] = d + _usual_path(len(points))
        if d >= most + 4 or len(points) <= 1:
            return me
        # Splits are drawn a little past the range seen, so that what lies beyond it is cut off early.
        f = int(rng.integers(x.shape[1]))
        lo, hi = points[:, f].min(), points[:, f].max()
        pad = 0.1 * max(hi - lo, 0.02)
        c = rng.uniform(lo - pad, hi + pad)
        go = points[:, f] < c
        feature[me], cut[me] = f, c
        left[me] = add(points[go], d + 1)
        right[me] = add(points[~go], d + 1)
        return me

    for _ in range(trees):
        pick = rng.choice(len(scaled), size, replace=False) if size else np.zeros(0, int)
        roots.append(add(scaled[pick], 0))
    return Forest(np.array(feature), np.array(cut, dtype=float), np.array(left), np.array(right), np.array(depth, dtype=float), np.array(roots), max(_usual_path(size), 1.0), low, high)


def calibrate(scores: np.ndarray, good: np.ndarray) -> float:
    """The threshold that best tells good from bad labelled rows, false rejections counting threefold."""
    if not len(scores) or good.all() or not good.any():
        return ACCEPT_ALL
    order = np.argsort(scores, kind="stable")
    s, g = scores[order], good[order]
    kept_good = np.concatenate([[0], np.cumsum(g)]) / g.sum()
    kept_bad = np.concatenate([[0], np.cumsum(~g)]) / (~g).sum()
    value = 3 * kept_good - kept_bad
    edge = np.concatenate([[True], s[1:] != s[:-1], [True]])
    best = int(np.flatnonzero(edge)[np.argmax(value[edge])])
    if best == len(s):
        return float(s[-1]) + 1e-9
    return float((s[best] + (s[best - 1] if best else s[best])) / 2)


def fit(documents: DataFrame, labels: DataFrame, rows: int = FIT_ROWS, seed: int = SEED) -> tuple[Forest, float]:
    """Grow the forest on documents labelled good and set its threshold on labelled ones."""
    known = labels.where("doc_id is not null and quality is not null").groupBy("doc_id").agg(F.min("quality").alias("quality"))
    chosen = known.orderBy(F.xxhash64("doc_id"), "doc_id").limit(rows)
    if known.count() == 0:
        return grow_forest(np.zeros((0, len(FEATURES)))), ACCEPT_ALL

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for whole in batches:
            for b in slices(whole, "text"):
                base, x = statistics(b.column(0))
                yield pa.RecordBatch.from_arrays([b.column(1), pa.array(_fails(base)), pa.array(list(x), pa.list_(pa.float64()))], names=["quality", "failed", "x"])

    # At most ``rows`` ids and labels: a bounded broadcast, so no text of other documents moves.
    taken = documents.join(F.broadcast(chosen), "doc_id").select("doc_id", "text", "quality").dropDuplicates(["doc_id"])
    got = taken.select("text", F.col("quality").cast("int").alias("quality")).mapInArrow(run, "quality int, failed boolean, x array<double>").where("not failed").toArrow()
    x = np.array(got.column("x").to_pylist(), dtype=float).reshape(-1, len(FEATURES))
    good = np.array(got.column("quality").to_pylist(), dtype=int) == 1
    order = np.lexsort(x.T[::-1])  # the same fit however rows arrive
    x, good = x[order], good[order]
    # Every other row calibrates; the rest grows the trees.
    grown = grow_forest(x[::2][good[::2]] if good[::2].any() else x[::2], seed=seed)
    return grown, calibrate(grown.score(x[1::2]), good[1::2])


def _fails(base: dict[str, np.ndarray]) -> np.ndarray:
    return (base["n_words"] < MIN_WORDS) | (100 * base["n_repeat_words"] > MOST_REPEATED * base["n_words"])


RESULT = "doc_id long, " + ", ".join(f"{k} long" for k in BASE) + ", base_failed boolean, score double, kept boolean"


def judge(documents: DataFrame, labels: DataFrame, id_col: str = "doc_id", text_col: str = "text", carry: tuple[str, ...] = ()) -> DataFrame:
    """Statistics and verdict of every row.

    Columns: ``doc_id``, the five counts, ``base_failed``, the anomaly ``score``
    and ``kept``. A null or empty text has zero counts and fails the base rules.
    Null ids and repeated rows are judged like any other. Without labels nothing
    is rejected beyond the base rules. Columns named in ``carry`` come along, others
    are ignored; an empty table gives an empty result.
    """
    ship(documents.sparkSession)
    extra, kinds = carried(documents, carry)
    docs = documents.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).cast("binary").alias("text"), *extra)
    forest, threshold = fit(docs.select("doc_id", "text"), labels.select(F.col("doc_id").cast("long").alias("doc_id"), "quality"))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for whole in batches:
            for b in slices(whole, "text"):
                base, x = statistics(b.column(1))
                failed, score = _fails(base), forest.score(x)
                cols = [b.column(0), *(pa.array(base[k], pa.int64()) for k in BASE), pa.array(failed), pa.array(score), pa.array(~failed & (score < threshold)), *b.columns[2:]]
                yield pa.RecordBatch.from_arrays(cols, names=["doc_id", *BASE, "base_failed", "score", "kept", *b.schema.names[2:]])

    return restored(docs.mapInArrow(run, RESULT + kinds), carry)
