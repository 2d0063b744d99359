"""Benchmark decontamination: n-gram seeds, then Smith-Waterman alignment.

Test items are a query set against all documents, taken in blocks of a bounded
number of words. Every n-gram of an item is a seed, however many documents hold
it, so a passage copied everywhere is found like one that was copied once.
Documents that hold seeds of an item are aligned with it, word by word, around
each cluster of seeds; stretches that many documents share are aligned once while
remembered. The best local score, as a share of the item's own, tells copies that
were edited or paraphrased.
"""

from __future__ import annotations

import string
from collections.abc import Iterator
from dataclasses import dataclass, field
from itertools import repeat

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from lexnorm.llm.words import carried, restored, slices
from lexnorm.sources.store import ship

GRAM = 3
#: Seeds of an item that a document must hold to be aligned (all, if the item has fewer).
HITS = 2
MATCH, MISMATCH, GAP = 2, -1, -1
#: Share of an item's own score from which a document counts as contaminated.
THRESHOLD = 0.5
#: Words of one block of items.
BLOCK_WORDS = 2_000_000
#: Radix of n-gram codes: a prime above any block's vocabulary.
RADIX = 2_147_483_647
PUNCTUATION = string.punctuation.encode()


def normalised(text: bytes | None) -> list[bytes]:
    """Words in lower case (A-Z) without ASCII punctuation."""
    return (text or b"").translate(None, PUNCTUATION).lower().split()


@dataclass
class Items:
    """A block of test items with their words as numbers and their seeds as codes."""

    ids: list[int]
    index: dict[bytes, int] = field(default_factory=dict)
    words: list[np.ndarray] = field(default_factory=list)
    gram: int = GRAM
    codes: np.ndarray = field(default_factory=lambda: np.zeros(0, np.int64))  # distinct, sorted
    owners: list[list[tuple[int, int]]] = field(default_factory=list)  # (item, offset) of each code
    needed: np.ndarray = field(default_factory=lambda: np.zeros(0, np.int64))

    @staticmethod
    def of(rows: list[tuple[int, bytes]], gram: int = GRAM) -> Items:
        out = Items([r[0] for r in rows], gram=gram)
        for _, text in rows:
            out.words.append(np.array([out.index.setdefault(w, len(out.index)) for w in normalised(text)], dtype=np.int64))
        seeds: dict[int, list[tuple[int, int]]] = {}
        for i, w in enumerate(out.words):
            for at, code in enumerate(out.grams(w).tolist()):
                seeds.setdefault(code, []).append((i, at))
        out.keep(sorted(seeds), seeds)
        return out

    def grams(self, words: np.ndarray) -> np.ndarray:
        """Codes of all n-grams; -1 where a word is in no item. Mixed radix modulo 2**63, checked by the alignment."""
        n = len(words) - self.gram + 1
        if n <= 0:
            return np.zeros(0, dtype=np.int64)
        code = np.zeros(n, dtype=np.uint64)
        bad = np.zeros(n, dtype=bool)
        for k in range(self.gram):
            w = words[k : k + n]
            code = code * np.uint64(RADIX) + w.astype(np.uint64)
            bad |= w < 0
        out = (code & np.uint64((1 << 63) - 1)).astype(np.int64)
        out[bad] = -1
        return out

    def keep(self, codes: list[int], seeds: dict[int, list[tuple[int, int]]]) -> None:
        self.codes = np.array(codes, dtype=np.int64)
        self.owners = [seeds[c] for c in codes]
        distinct = np.zeros(len(self.ids), dtype=np.int64)
        for own in self.owners:
            for i in {i for i, _ in own}:
                distinct[i] += 1
        self.needed = np.maximum(np.minimum(distinct, HITS), 1)

    def find(self, words: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Positions in ``words`` where a seed starts, and the seed's number."""
        g = self.grams(words)
        if not len(g) or not len(self.codes):
            return np.zeros(0, np.int64), np.zeros(0, np.int64)
        at = np.flatnonzero(g >= 0)
        k = np.minimum(np.searchsorted(self.codes, g[at]), len(self.codes) - 1)
        hit = self.codes[k] == g[at]
        return at[hit], k[hit]

    def numbers(self, words: list[bytes]) -> np.ndarray:
        return np.fromiter(map(self.index.get, words, repeat(-1)), dtype=np.int64, count=len(words))


def align(item: np.ndarray, words: np.ndarray) -> int:
    """Best Smith-Waterman score of ``item`` against any stretch of ``words``."""
    if not len(item) or not len(words):
        return 0
    at = np.arange(len(words) + 1) * -GAP
    row = np.zeros(len(words) + 1, dtype=np.int64)
    best = 0
    for w in item:
        now = np.maximum(row + GAP, 0)
        np.maximum(now[1:], row[:-1] + np.where(words == w, MATCH, MISMATCH), out=now[1:])
        row = np.maximum.accumulate(now + at) - at  # gaps within the row
        best = max(best, int(row.max()))
    return best


class Aligner:
    """Scores documents against items; equal stretches are aligned once."""

    def __init__(self, items: Items, most: int = 20_000):
        self.items, self.most = items, most
        self.known: dict[tuple[int, bytes], int] = {}

    def best(self, words: np.ndarray) -> tuple[int, int | None, float]:
        """Items aligned, the best one's id (the smallest of equals), and its share of the item's own score."""
        items = self.items
        at, seeds = items.find(words)
        by: dict[int, list[tuple[int, int, int]]] = {}
        for p, k in zip(at.tolist(), seeds.tolist(), strict=True):
            for i, offset in items.owners[k]:
                by.setdefault(i, []).append((p - offset, p, k))
        top: tuple[float, int | None] = (0.0, None)
        aligned = 0
        for i, hits in by.items():
            if len({k for _, _, k in hits}) < items.needed[i]:
                continue
            aligned += 1
            size = len(items.words[i])
            hits.sort()
            score = lo = 0
            while lo < len(hits):
                hi = lo + 1
                while hi < len(hits) and hits[hi][0] - hits[hi - 1][0] <= size:
                    hi += 1
                first = max(0, hits[lo][0] - size // 2)
                stretch = words[first : hits[hi - 1][0] + size + size // 2]
                key = (i, stretch.tobytes())
                if key not in self.known:
                    if len(self.known) >= self.most:
                        self.known.clear()
                    self.known[key] = align(items.words[i], stretch)
                score = max(score, self.known[key])
                lo = hi
            share = score / (MATCH * size)
            if share > top[0] or (share == top[0] and top[1] is not None and items.ids[i] < top[1]):
                top = (share, items.ids[i])
        return aligned, top[1], top[0]


def _blocks(benchmark: DataFrame, item_id: str, item_text: str) -> Iterator[list[tuple[int, bytes]]]:
    rows, words = [], 0
    for r in benchmark.select(F.col(item_id).cast("long").alias("i"), F.col(item_text).cast("binary").alias("t")).where("i is not null and t is not null").orderBy("i", "t").toLocalIterator():
        n = len(r.t) // 4 + 1
        if rows and words + n > BLOCK_WORDS:
            yield rows
            rows, words = [], 0
        rows.append((r.i, bytes(r.t)))
        words += n
    if rows:
        yield rows


def scan(documents: DataFrame, benchmark: DataFrame, id_col: str = "doc_id", text_col: str = "text", item_id: str = "item_id", item_text: str = "text", threshold: float = THRESHOLD, carry: tuple[str, ...] = ()) -> DataFrame:
    """``doc_id, n_aligned, best_item, score, contaminated`` for every row of ``documents``.

    Null and empty texts, and items under ``GRAM`` words, match nothing. Null ids
    and repeated rows are scanned like any other. Null and empty items are left
    out; without items nothing is contaminated. Columns named in ``carry`` come
    along, others are ignored.
    """
    ship(documents.sparkSession)
    extra, kinds = carried(documents, carry)
    docs = documents.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).cast("binary").alias("text"), *extra)
    # Blocks are scanned one after another in each task; each is sent once.
    shared = [docs.sparkSession.sparkContext.broadcast(Items.of(rows)) for rows in _blocks(benchmark, item_id, item_text)]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        aligners = [Aligner(x.value) for x in shared]
        for whole in batches:
            for b in slices(whole, "text"):
                rows = []
                for text in b.column(1):
                    words = normalised(text.as_py())
                    n, best, score = 0, None, 0.0
                    for a in aligners:
                        m, i, s = a.best(a.items.numbers(words))
                        n += m
                        if s > score or (s == score and best is not None and i is not None and i < best):
                            best, score = i, s
                    rows.append((n, best, score, score >= threshold))
                n, best, score, dirty = zip(*rows, strict=True) if rows else ((),) * 4
                yield pa.RecordBatch.from_arrays([b.column(0), pa.array(n, pa.int64()), pa.array(best, pa.int64()), pa.array(score, pa.float64()), pa.array(dirty, pa.bool_()), *b.columns[2:]], names=["doc_id", "n_aligned", "best_item", "score", "contaminated", *b.schema.names[2:]])

    return restored(docs.mapInArrow(run, "doc_id long, n_aligned long, best_item long, score double, contaminated boolean" + kinds), carry)
