"""Exact substring de-duplication behind a count-min prefilter.

Two passes over the texts. The first adds the anchors of all windows to a
count-min sketch: each task sends only the cells it touched, and the cells are
merged by shard. A merged cell never undercounts, so a window whose anchor is
estimated to occur once occurs in one place only. The second pass sends just the
windows whose estimate is two or more to an exact grouping on 128 bits of BLAKE2b
of their words, which decides. A sketch that is too small for the corpus sends more
windows to the grouping; it never loses one.

A sketch of up to 2**MOST_BITS cells goes to every task. Beyond that the cells stay
where they were merged, one for each 64-bit hash that occurs, and the anchors of
repeated cells are joined back to their texts.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from lexnorm.llm.windows import GRAM, SIZE, WINDOWS, anchored, extend, first_seen, keyed, later_copies, remove_covered, retained, windows_batch, without
from lexnorm.llm.words import carried, mix, restored, slices
from lexnorm.sources.store import materialise, ship

ROWS = 2
SHARD_BITS = 16
#: Bits of a broadcast sketch: between 16 KB and 64 MB, whatever the corpus.
LEAST_BITS, MOST_BITS = 17, 29


def sketch_bits(documents: DataFrame, text_col: str, gram: int, size: int) -> int:
    """log2 of the cells: about four for each anchor of the corpus and row of the sketch."""
    total = documents.agg(F.sum(F.octet_length(F.col(text_col)))).first()[0] or 0
    anchors = total / 6.5 * 2 / (size - gram + 2)
    return int(max(LEAST_BITS, np.ceil(np.log2(8 * anchors + 1))))


def _cells(keys: np.ndarray, bits: int) -> tuple[np.ndarray, ...]:
    """One cell for each key in each of the sketch's rows; row r owns the r-th half."""
    half = bits - 1
    k = keys.view(np.uint64)
    low = np.uint64((1 << half) - 1)
    return tuple(((k >> np.uint64(r * (64 - half))) & low) + np.uint64(r << half) for r in range(ROWS))


def repeated_cells(documents: DataFrame, bits: int, size: int = SIZE, gram: int = GRAM) -> bytes:
    """A bit for each cell of the merged sketch: set if its count is two or more."""

    def touched(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        parts = []
        for whole in batches:
            for b in slices(whole, "text"):
                a = anchored(b.column(b.schema.get_field_index("text")), size, gram)
                at = np.unique(a.anchors)
                # A gram counts once a text: what a text repeats within itself is nobody's copy.
                _, once = np.unique(a.grams[at] + mix(a.owner(at).astype(np.uint64)), return_index=True)
                parts.append(a.grams[at[once]])
        keys = np.concatenate(parts) if parts else np.zeros(0, np.uint64)
        cells, counts = np.unique(np.concatenate(_cells(keys, bits)), return_counts=True)
        shard = (cells >> np.uint64(SHARD_BITS)).astype(np.int64)
        inner = (cells & np.uint64((1 << SHARD_BITS) - 1)).astype(np.uint16)
        cuts = np.flatnonzero(np.diff(shard)) + 1
        bounds = np.concatenate([[0], cuts, [len(shard)]]) if len(shard) else np.zeros(1, np.int64)
        rows = []
        for lo, hi in zip(bounds[:-1], bounds[1:], strict=True):
            once = counts[lo:hi] == 1
            rows.append((int(shard[lo]), inner[lo:hi][once].tobytes(), inner[lo:hi][~once].tobytes()))
        for i in range(0, len(rows), 4096):
            s, o, m = zip(*rows[i : i + 4096], strict=True)
            yield pa.RecordBatch.from_arrays([pa.array(s, pa.int64()), pa.array(o, pa.binary()), pa.array(m, pa.binary())], names=["shard", "once", "more"])

    def merged(key: tuple[pa.Scalar, ...], batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        # Each task adds at most 2**SHARD_BITS cells to a shard; batches are added as they come.
        count = np.zeros(1 << SHARD_BITS, dtype=np.int32)
        for b in batches:
            for once, more in zip(b.column(1), b.column(2), strict=True):
                np.add.at(count, np.frombuffer(once.as_py(), np.uint16), 1)
                np.add.at(count, np.frombuffer(more.as_py(), np.uint16), 2)
            np.minimum(count, 2, out=count)
        yield pa.RecordBatch.from_arrays([pa.array([key[0].as_py()], pa.int64()), pa.array([np.packbits(count >= 2).tobytes()], pa.binary())], names=["shard", "bits"])

    spread = documents.select("text").mapInArrow(touched, "shard long, once binary, more binary")
    rows = spread.groupBy("shard").applyInArrow(merged, "shard long, bits binary").toLocalIterator()
    out = np.zeros(1 << (bits - 3), dtype=np.uint8)
    for shard, packed in rows:
        out[shard << (SHARD_BITS - 3) : (shard + 1) << (SHARD_BITS - 3)] = np.frombuffer(packed, np.uint8)
    return out.tobytes()


def candidate_windows(documents: DataFrame, sketch: bytes, bits: int, size: int = SIZE, gram: int = GRAM) -> DataFrame:
    """Windows whose anchor the sketch estimates at two or more, as (h1, h2, doc_id, place)."""
    shared = documents.sparkSession.sparkContext.broadcast(sketch)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        marks = np.frombuffer(shared.value, np.uint8)
        for whole in batches:
            for b in slices(whole, "text"):
                a = anchored(b.column(1), size, gram)
                if not len(a.starts):
                    continue
                keys = a.grams[a.anchors]
                hit = np.ones(len(keys), dtype=bool)
                for c in _cells(keys, bits):
                    hit &= (marks[c >> np.uint64(3)] >> (np.uint8(7) - (c & np.uint64(7)).astype(np.uint8)) & 1).astype(bool)
                yield windows_batch(a, a.starts[hit], b.column(0), b.column(2), size)

    return documents.mapInArrow(run, WINDOWS)


def remove_repeats(documents: DataFrame, id_col: str = "doc_id", text_col: str = "text", size: int = SIZE, gram: int = GRAM, with_text: bool = True, carry: tuple[str, ...] = (), most_bits: int = MOST_BITS) -> DataFrame:
    """Remove every word covered by a window that also starts in a smaller document.

    Returns ``doc_id, n_words, n_removed, kept_sha256, kept_text`` for each input
    row. Null or empty texts and texts under ``size`` words keep all their words.
    A null id is never smaller than another and its text is kept whole. Rows that
    repeat id and text get the same result. Columns named in
    ``carry`` come along, others are ignored, whatever their names. An empty table gives an empty result.
    """
    ship(documents.sparkSession)
    bits = sketch_bits(documents, text_col, gram, size)
    extra, kinds = carried(documents, carry)
    docs = keyed(documents, id_col, text_col, extra)
    copies = later_copies(docs)
    compared = without(docs.where("doc_id is not null"), copies)
    if bits <= most_bits:
        found = candidate_windows(compared, repeated_cells(compared, bits, size, gram), bits, size, gram)
    else:
        cells = retained(compared, size, gram).groupBy("prefix").agg(F.count("*").alias("n")).where("n > 1")
        found = extend(compared, materialise(cells.select("prefix"), "cells"), size, gram)
    windows = materialise(found, "windows")
    return restored(remove_covered(docs, first_seen(windows), copies, size, with_text, kinds), carry)
