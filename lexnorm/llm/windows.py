"""Windows of consecutive words, their anchors, and removal of covered words.

Shared by both substring de-duplicators. A window of ``size`` words has one
*anchor*: the leftmost smallest hash among its runs of ``gram`` words. Equal
windows have equal anchors, so an anchor that occurs in one document only
clears every window it stands for. Anchors are compared by fast hashes, which can
only let too many windows through; windows themselves are told apart by BLAKE2b
of their words.
"""

from __future__ import annotations

import hashlib
from collections.abc import Callable, Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
import pyarrow.compute
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from lexnorm.llm.words import ROLLING, Words, mix, slices
from lexnorm.sources.store import materialise

SIZE = 50
GRAM = 25


@dataclass
class Anchored:
    """Per batch: valid window starts, the anchor position of each, and hashes."""

    words: Words
    starts: np.ndarray  # word index of each window
    anchors: np.ndarray  # word index of its anchor
    grams: np.ndarray  # hash of the gram at each word index

    def owner(self, at: np.ndarray) -> np.ndarray:
        """The text each word index belongs to."""
        return np.searchsorted(self.words.first, at, side="right") - 1


def anchored(texts: pa.Array, size: int = SIZE, gram: int = GRAM) -> Anchored:
    w = Words(texts)
    h = w.hashes()
    g = ROLLING[0](h, gram)
    n = len(h) - size + 1
    none = np.zeros(0, dtype=np.int64)
    if n <= 0:
        return Anchored(w, none, none, g)
    ends = np.repeat(w.first[1:], w.counts)[:n]
    starts = np.flatnonzero(np.arange(n) + size <= ends)
    span = size - gram + 1
    offsets = np.empty(n, dtype=np.int64)
    view = np.lib.stride_tricks.sliding_window_view(g, span)
    step = 1 << 16
    for i in range(0, n, step):
        offsets[i : i + step] = view[i : i + step].argmin(axis=1)
    return Anchored(w, starts, starts + offsets[starts], g)


def window_keys(w: Words, starts: np.ndarray, size: int = SIZE) -> tuple[np.ndarray, np.ndarray]:
    """128 bits of BLAKE2b over the words of each window, joined by spaces, as two signed 64-bit columns."""
    text, begin, end = w.spaced()
    whole, digest = memoryview(text), hashlib.blake2b
    raw = b"".join([digest(whole[s:e], digest_size=16).digest() for s, e in zip(begin[starts].tolist(), end[starts + size - 1].tolist(), strict=True)])
    both = np.frombuffer(raw, dtype="<i8").reshape(-1, 2)
    return both[:, 0].copy(), both[:, 1].copy()


#: Tables of at most so many rows of two longs (16 MB) are broadcast; larger ones are joined by a shuffle.
BROADCAST_ROWS = 1_000_000
#: The start that stands for every window of a text.
WHOLE = -1


def keyed(documents: DataFrame, id_col: str = "doc_id", text_col: str = "text", extra: list | None = None) -> DataFrame:
    """The columns the operators need: id, text as bytes, and 32 bits that tell rows of one id apart."""
    return documents.select(
        F.col(id_col).cast("long").alias("doc_id"),
        F.col(text_col).cast("binary").alias("text"),
        F.xxhash64(F.col(text_col)).bitwiseAND(0xFFFFFFFF).alias("tag"),
        *(extra or []),
    )


def later_copies(documents: DataFrame) -> DataFrame:
    """``doc_id, tag`` of documents whose whole text also stands in a smaller one.

    All their windows are repeated, so none need be compared; the smallest copy
    speaks for its group, however large the group is.
    """
    keys = documents.where("doc_id is not null and text is not null").select("doc_id", "tag", F.unhex(F.sha2("text", 256)).alias("digest"))
    lead = materialise(keys.groupBy("digest").agg(F.min("doc_id").alias("lead"), F.max("doc_id").alias("last")).where("lead < last").drop("last"), "copies")
    return materialise(keys.join(lead, "digest").where("doc_id > lead").select("doc_id", "tag").distinct(), "copies")


def without(documents: DataFrame, copies: DataFrame) -> DataFrame:
    if copies.count() <= BROADCAST_ROWS:
        copies = F.broadcast(copies)
    return documents.join(copies, ["doc_id", "tag"], "left_anti").select("doc_id", "text", "tag")


def first_seen(windows: DataFrame) -> DataFrame:
    """``doc_id, tag, start`` of windows (h1, h2, doc_id, place) that also start in a smaller document.

    The smallest document of each window is found with partial aggregation, so
    a passage in a third of all documents sends one row a task.
    """
    first = materialise(
        windows.groupBy("h1", "h2").agg(F.min("doc_id").alias("lowest"), F.max("doc_id").alias("highest")).where("lowest < highest").drop("highest"),
        "first-windows",
    )
    later = windows.join(first, ["h1", "h2"]).where("doc_id > lowest")
    return later.select("doc_id", F.shiftrightunsigned("place", 32).alias("tag"), F.col("place").bitwiseAND(0xFFFFFFFF).cast("int").alias("start"))


def windows_batch(a: Anchored, starts: np.ndarray, ids: pa.Array, tags: pa.Array, size: int) -> pa.RecordBatch:
    """Rows (h1, h2, doc_id, place); ``place`` packs a text's tag and the start within it."""
    owner = a.owner(starts)
    h1, h2 = window_keys(a.words, starts, size)
    place = (tags.to_numpy(zero_copy_only=False).astype(np.int64)[owner] << 32) | (starts - a.words.first[owner])
    return pa.RecordBatch.from_arrays([pa.array(h1), pa.array(h2), ids.take(pa.array(owner)), pa.array(place)], names=["h1", "h2", "doc_id", "place"])


WINDOWS = "h1 long, h2 long, doc_id long, place long"


def retained(documents: DataFrame, size: int = SIZE, gram: int = GRAM) -> DataFrame:
    """``prefix, doc_id, place`` of the suffixes at anchors; a text gives equal prefixes once."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for whole in batches:
            for b in slices(whole, "text"):
                a = anchored(b.column(1), size, gram)
                at = np.unique(a.anchors)
                owner = a.owner(at)
                _, once = np.unique(a.grams[at] + mix(owner.astype(np.uint64)), return_index=True)
                at, owner = at[once], owner[once]
                place = (b.column(2).to_numpy(zero_copy_only=False)[owner] << 32) | (at - a.words.first[owner])
                yield pa.RecordBatch.from_arrays([pa.array(a.grams[at].view(np.int64)), b.column(0).take(pa.array(owner)), pa.array(place)], names=["prefix", "doc_id", "place"])

    return documents.mapInArrow(run, "prefix long, doc_id long, place long")


def _extended(size: int, gram: int, wanted: Callable[[], np.ndarray]) -> Callable[[Iterator[pa.RecordBatch]], Iterator[pa.RecordBatch]]:
    """Windows of ``size`` words around the anchors whose prefix is wanted: its extensions left and right."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        keys = wanted()
        for whole in batches:
            for b in slices(whole, "text"):
                a = anchored(b.column(1), size, gram)
                if not len(a.starts) or not len(keys):
                    continue
                mine = a.grams[a.anchors]
                hit = keys[np.minimum(np.searchsorted(keys, mine), len(keys) - 1)] == mine
                yield windows_batch(a, a.starts[hit], b.column(0), b.column(2), size)

    return run


def extend(documents: DataFrame, prefixes: DataFrame, size: int = SIZE, gram: int = GRAM, broadcast_rows: int = BROADCAST_ROWS) -> DataFrame:
    """All windows whose anchor has one of ``prefixes``, as (h1, h2, doc_id, place).

    Up to ``broadcast_rows`` prefixes go to every task; more are joined to
    the suffixes and then to the texts by document.
    """
    if prefixes.count() <= broadcast_rows:
        found = prefixes.toArrow().column("prefix").to_numpy()
        shared = documents.sparkSession.sparkContext.broadcast(np.sort(found.view(np.uint64)))
        return documents.mapInArrow(_extended(size, gram, lambda: shared.value), WINDOWS)
    suffixes = retained(documents, size, gram).join(prefixes, "prefix")
    mine = suffixes.groupBy("doc_id", F.shiftrightunsigned("place", 32).alias("tag")).agg(F.collect_set("prefix").alias("prefixes"))
    joined = documents.join(mine, ["doc_id", "tag"]).select("doc_id", "text", "tag", "prefixes")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for i in range(b.num_rows):
                one = b.slice(i, 1)
                keys = np.sort(np.asarray(one.column(3)[0].as_py(), dtype=np.int64).view(np.uint64))
                yield from _extended(size, gram, lambda keys=keys: keys)(iter([one.select(["doc_id", "text", "tag"])]))

    return joined.mapInArrow(run, WINDOWS)


RESULT = "doc_id long, n_words long, n_removed long, kept_sha256 string, kept_text string"


def _kept(words: list[bytes], lows: list[int] | None, highs: list[int] | None, size: int) -> list[bytes]:
    """Words outside all windows that start from ``low`` to ``high``."""
    if not lows:
        return words
    if WHOLE in lows:
        return [] if len(words) >= size else words
    out, at = [], 0
    for lo, hi in zip(lows, highs or (), strict=True):  # in order
        if lo > at:
            out += words[at:lo]
        at = max(at, hi + size)
    return out + words[at:]


def start_ranges(repeated: DataFrame) -> DataFrame:
    """``doc_id, tag, lows, highs``: runs of consecutive window starts, in order."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            starts = b.column(2)
            at = np.asarray(starts.flatten(), dtype=np.int64)
            first = np.concatenate([[0], np.cumsum(np.asarray(pa.compute.list_value_length(starts), dtype=np.int64))])
            fresh = np.ones(len(at), dtype=bool)
            fresh[1:] = at[1:] != at[:-1] + 1
            fresh[first[:-1][first[:-1] < len(at)]] = True
            lo = np.flatnonzero(fresh)
            hi = np.concatenate([lo[1:], [len(at)]])[: len(lo)] - 1
            offsets = pa.array(np.searchsorted(lo, first).astype(np.int32))
            lists = [pa.ListArray.from_arrays(offsets, pa.array(at[x].astype(np.int32))) for x in (lo, hi)]
            yield pa.RecordBatch.from_arrays([b.column(0), b.column(1), *lists], names=["doc_id", "tag", "lows", "highs"])

    grouped = repeated.groupBy("doc_id", "tag").agg(F.array_sort(F.collect_set("start")).alias("starts"))
    return grouped.mapInArrow(run, "doc_id long, tag long, lows array<int>, highs array<int>")


def remove_covered(documents: DataFrame, repeated: DataFrame, copies: DataFrame, size: int, with_text: bool, kinds: str = "") -> DataFrame:
    """Drop the words of ``documents`` (see :func:`keyed`) that a repeated window covers.

    Up to ``BROADCAST_ROWS`` ranges of starts go to every task and no text is
    moved; more are joined to the texts by document.
    """
    marks = materialise(start_ranges(repeated.unionByName(copies.withColumn("start", F.lit(WHOLE)))), "ranges")
    if (marks.agg(F.sum(F.size("lows"))).first()[0] or 0) <= BROADCAST_ROWS:
        marks = F.broadcast(marks)
    joined = documents.join(marks, ["doc_id", "tag"], "left").select("doc_id", "text", "lows", "highs", *(c for c in documents.columns if c.startswith("carried_")))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for whole in batches:
            for b in slices(whole, "text", 1 << 23):
                cols: list[list] = [[], [], [], []]
                for text, lows, highs in zip(b.column(1), b.column(2), b.column(3), strict=True):
                    words = (text.as_py() or b"").split()
                    kept = _kept(words, lows.as_py(), highs.as_py(), size)
                    out = b" ".join(kept)
                    for c, v in zip(cols, (len(words), len(words) - len(kept), hashlib.sha256(out).hexdigest(), out if with_text else None), strict=True):
                        c.append(v)
                yield pa.RecordBatch.from_arrays(
                    [b.column(0), pa.array(cols[0], pa.int64()), pa.array(cols[1], pa.int64()), pa.array(cols[2]), pa.array(cols[3], pa.binary()).cast(pa.string()), *b.columns[4:]],
                    names=["doc_id", "n_words", "n_removed", "kept_sha256", "kept_text", *b.schema.names[4:]],
                )

    return joined.mapInArrow(run, RESULT + kinds)
