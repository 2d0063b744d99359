"""Words of texts: extraction, lossless splitting, counting."""

from __future__ import annotations

import math
import struct
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

#: A word: a run of letters and digits (``word``) or of anything but white space (``whitespace``).
PATTERNS = {"word": r"[\p{L}\p{N}]+", "whitespace": r"\S+"}


def words(text: Column, mode: str = "word", lower: bool = True) -> Column:
    """All words of a text in order; an empty array for null."""
    source = F.lower(text) if lower else text
    return F.coalesce(F.regexp_extract_all(source, F.lit(f"({PATTERNS[mode]})"), F.lit(1)), F.array().cast("array<string>"))


def tokenize(df: DataFrame, id_cols: list[str], text_col: str = "text", mode: str = "word", lower: bool = True, max_len: int | None = None) -> DataFrame:
    """One row for each word: the id columns, ``pos`` from 0, ``word``."""
    out = df.select(*id_cols, F.posexplode(words(F.col(text_col), mode, lower)).alias("pos", "word"))
    return out if max_len is None else out.where(F.length("word") <= max_len)


def split_lossless(text: Column, mode: str = "word", lower: bool = True) -> Column:
    """``struct(gaps, words)`` with one gap more than words: gap, word, gap, ..., gap gives the text back."""
    source = F.coalesce(F.lower(text) if lower else text, F.lit(""))
    return F.struct(F.split(source, PATTERNS[mode], -1).alias("gaps"), words(source, mode, False).alias("words"))


def join_lossless(gaps: Column, new_words: Column) -> Column:
    """The text of gaps and (replaced) words."""
    padded = F.concat(new_words, F.array(F.lit("")))
    return F.array_join(F.zip_with(gaps, padded, lambda g, w: F.concat(g, F.coalesce(w, F.lit("")))), "")


def vocabulary(df: DataFrame, text_col: str = "text", mode: str = "word", lower: bool = True, min_freq: int = 1, min_len: int = 1, max_len: int | None = None, by: list[str] | None = None) -> DataFrame:
    """``word, freq`` (with ``by`` columns first): map-side partial counts, one shuffle by word."""
    tokens = df.select(*(by or []), F.explode(words(F.col(text_col), mode, lower)).alias("word"))
    if min_len > 1:
        tokens = tokens.where(F.length("word") >= min_len)
    if max_len is not None:
        tokens = tokens.where(F.length("word") <= max_len)
    out = tokens.groupBy(*(by or []), "word").agg(F.count("*").alias("freq"))
    return out if min_freq <= 1 else out.where(F.col("freq") >= min_freq)


def sketch_counts(df: DataFrame, text_col: str = "text", eps: float = 0.001, confidence: float = 0.99, seed: int = 42, by: list[str] | None = None) -> DataFrame:
    """A count-min sketch of word counts (binary), mergeable and of fixed size."""
    tokens = df.select(*(by or []), F.explode(words(F.col(text_col))).alias("word"))
    return tokens.groupBy(*(by or [])).agg(F.count_min_sketch("word", F.lit(eps), F.lit(confidence), F.lit(seed)).alias("sketch"))


def _murmur(raw: bytes, seed: int) -> int:
    """The 32-bit hash that Spark's sketch uses: MurmurHash3 over four bytes at a time, then over single signed bytes."""
    mask = 0xFFFFFFFF
    h, n = seed & mask, len(raw) & ~3
    units = [int.from_bytes(raw[i : i + 4], "little") for i in range(0, n, 4)] + [b - 256 if b > 127 else b for b in raw[n:]]
    for k in units:
        k = (k * 0xCC9E2D51) & mask
        k = (((k << 15) | (k >> 17)) & mask) * 0x1B873593 & mask
        h ^= k
        h = (((h << 13) | (h >> 19)) & mask) * 5 + 0xE6546B64 & mask
    h ^= len(raw)
    h = (h ^ (h >> 16)) * 0x85EBCA6B & mask
    h = (h ^ (h >> 13)) * 0xC2B2AE35 & mask
    h ^= h >> 16
    return h - (1 << 32) if h >> 31 else h


def sketch_estimates(df: DataFrame, sketches: DataFrame, by: list[str], text_col: str = "text") -> DataFrame:
    """``by, word, freq, estimate``: what each group's sketch says of its words, beside their counts.

    Estimates are read in Arrow batches from the sketch's serial form: version, total,
    depth, width, a multiplier for each row, counters.
    """
    counted = vocabulary(df, text_col, by=by).join(F.broadcast(sketches), by).select(*by, "word", "freq", "sketch")
    schema = counted.drop("sketch").schema.add("estimate", "long")
    at = len(by)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        read: dict[int, tuple[int, int, np.ndarray]] = {}
        for b in batches:
            out = []
            for word, sketch in zip(b.column(at).to_pylist(), b.column(at + 2)):
                raw = sketch.as_py()
                key = hash(raw)
                if key not in read:
                    depth, width = struct.unpack_from(">ii", raw, 12)
                    read[key] = depth, width, np.frombuffer(raw, ">i8", depth * width, 20 + 8 * depth).reshape(depth, width)
                depth, width, table = read[key]
                one = _murmur(word.encode(), 0)
                two = _murmur(word.encode(), one)
                cells = [(one + i * two + (1 << 31)) % (1 << 32) - (1 << 31) for i in range(depth)]
                out.append(min(int(table[i, abs(int(math.fmod(c, width)))]) for i, c in enumerate(cells)))
            yield pa.RecordBatch.from_arrays([*b.columns[: at + 2], pa.array(out, pa.int64())], names=[*b.schema.names[: at + 2], "estimate"])

    return counted.mapInArrow(run, schema)
