"""Words of many texts at a time, as NumPy arrays over the Arrow buffers.

A word is a maximal run of bytes outside ``\\x20`` and ``\\x09``-``\\x0D``. UTF-8
bytes of other characters never fall in that set, so byte runs equal the runs of
characters. A null text has no words.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute
import xxhash

SPACE = np.zeros(256, dtype=bool)
SPACE[[9, 10, 11, 12, 13, 32]] = True
LOWER = np.arange(256, dtype=np.uint8)
LOWER[65:91] += 32

_U = np.uint64
#: Odd multipliers (fixed values; any odd numbers serve).
LANE = 0x9E3779B97F4A7C15
WINDOW_BASES = (0xD6E8FEB86659FD93, 0xA0761D6478BD642F)
_MASK = (1 << 64) - 1
#: Words of more eight-byte lanes are hashed by XXH3 one by one.
MOST_LANES = 16
_LANE_MASK = np.array([(1 << (8 * k)) - 1 for k in range(8)] + [_MASK], dtype=np.uint64)


def mix(x: np.ndarray) -> np.ndarray:
    """Spread 64-bit values (xor-shift and multiply rounds)."""
    x = x ^ (x >> _U(30))
    x = x * _U(0xBF58476D1CE4E5B9)
    x = x ^ (x >> _U(27))
    x = x * _U(0x94D049BB133111EB)
    return x ^ (x >> _U(31))


def _powers(base: int, n: int) -> np.ndarray:
    p = np.full(n, base & _MASK, dtype=_U)
    if n:
        p[0] = 1
    return np.cumprod(p, dtype=_U)


class Powers:
    """Powers of an odd base and of its inverse modulo 2**64, grown on demand."""

    def __init__(self, base: int):
        self.base, self.inverse = base, pow(base, -1, 1 << 64)
        self.up = self.down = np.zeros(0, dtype=_U)

    def get(self, n: int) -> tuple[np.ndarray, np.ndarray]:
        if len(self.up) < n:
            size = max(n, 2 * len(self.up), 1024)
            self.up, self.down = _powers(self.base, size), _powers(self.inverse, size)
        return self.up[:n], self.down[:n]


def span_hashes(data: np.ndarray, starts: np.ndarray, size: np.ndarray) -> np.ndarray:
    """A 64-bit hash of each span of bytes: eight at a time, each mixed into what came before.

    Mixing is no polynomial in the bytes, so no arrangement of two letters cancels out.
    """
    out = mix(size.astype(_U) * _U(LANE))
    padded = np.zeros(len(data) + 8, dtype=np.uint8)
    padded[: len(data)] = data
    lanes = np.ndarray((len(data) + 1,), "<u8", padded, strides=(1,))
    live = np.flatnonzero(size <= 8 * MOST_LANES)
    for k in range(MOST_LANES):
        live = live[size[live] > 8 * k]
        if not len(live):
            break
        lane = lanes[starts[live] + 8 * k] & _LANE_MASK[np.minimum(size[live] - 8 * k, 8)]
        out[live] = mix((out[live] ^ lane) * _U(LANE) + _U(k + 1))
    for i in np.flatnonzero(size > 8 * MOST_LANES).tolist():
        out[i] = xxhash.xxh3_64_intdigest(data[starts[i] : starts[i] + size[i]], 1)
    return out


class Words:
    """Byte bounds of the words of a batch of texts."""

    def __init__(self, texts: pa.Array, lower: bool = False):
        texts = texts.fill_null(b"") if texts.null_count else texts
        if not pa.types.is_binary(texts.type):
            texts = texts.cast(pa.binary())
        n = len(texts)
        _, offsets, data = texts.buffers()
        off = np.frombuffer(offsets, dtype=np.int32)[texts.offset : texts.offset + n + 1].astype(np.int64) if n else np.zeros(1, np.int64)
        raw = np.frombuffer(data, dtype=np.uint8)[off[0] : off[-1]] if data is not None else np.zeros(0, np.uint8)
        self.off = off - off[0]
        self.data = LOWER[raw] if lower else raw
        size = len(self.data)
        edge = np.zeros(size + 1, dtype=bool)
        edge[self.off] = True
        solid = ~SPACE[self.data]
        before = np.ones(size, dtype=bool)
        before[1:] = ~solid[:-1]
        after = np.ones(size, dtype=bool)
        after[:-1] = ~solid[1:]
        self.solid = solid
        self.starts = np.flatnonzero(solid & (before | edge[:-1]))
        self.ends = np.flatnonzero(solid & (after | edge[1:])) + 1
        #: Index of each text's first word; one more entry at the end.
        self.first = np.searchsorted(self.starts, self.off)

    @property
    def counts(self) -> np.ndarray:
        return np.diff(self.first)

    def __len__(self) -> int:
        return len(self.off) - 1

    def hashes(self) -> np.ndarray:
        """A 64-bit hash of every word."""
        return span_hashes(self.data, self.starts, self.ends - self.starts)

    def spaced(self) -> tuple[bytes, np.ndarray, np.ndarray]:
        """All words with one space after each, and where each starts and ends there."""
        keep = self.solid.copy()
        inner = self.ends[self.ends < len(self.data)]
        keep[inner[~self.solid[inner]]] = True
        out = np.where(self.solid, self.data, np.uint8(32))[keep]
        at = np.cumsum(keep)
        starts = at[self.starts] - 1 if len(self.starts) else self.starts
        return out.tobytes(), starts, starts + (self.ends - self.starts)

    def joined(self, lo: int, hi: int) -> bytes:
        """Words ``lo`` to ``hi`` of the batch, joined by one space."""
        return b" ".join(self.data[self.starts[lo] : self.ends[hi - 1]].tobytes().split()) if hi > lo else b""


class Rolling:
    """Hashes of all runs of ``size`` consecutive values.

    Unlike runs may share a hash: what decides compares the words themselves.
    """

    def __init__(self, base: int):
        self.powers = Powers(base)

    def __call__(self, h: np.ndarray, size: int) -> np.ndarray:
        n = len(h) - size + 1
        if n <= 0:
            return np.zeros(0, dtype=_U)
        up, down = self.powers.get(len(h) + 1)
        total = np.zeros(len(h) + 1, dtype=_U)
        np.cumsum(h * up[:-1], out=total[1:])
        return mix((total[size:] - total[:n]) * down[:n])


ROLLING = tuple(Rolling(b) for b in WINDOW_BASES)


def slices(batch: pa.RecordBatch, column: str, most_bytes: int = 1 << 20) -> Iterator[pa.RecordBatch]:
    """Cut a batch so that each part holds about ``most_bytes`` of ``column`` (one text at least)."""
    n = batch.num_rows
    if not n:
        return
    at = batch.schema.get_field_index(column)
    sizes = np.asarray(pa.compute.fill_null(pa.compute.binary_length(batch.column(at)), 0), dtype=np.int64)
    total = np.concatenate([[0], np.cumsum(sizes)])
    i = 0
    while i < n:
        j = max(i + 1, int(np.searchsorted(total, total[i] + most_bytes, side="right")) - 1)
        yield batch.slice(i, j - i)
        i = j


def carried(documents, carry: tuple[str, ...]) -> tuple[list, str]:
    """Columns to send along under names that clash with nothing, and their part of a result schema."""
    from pyspark.sql import functions as F

    kinds = dict(documents.dtypes)
    columns = [F.col(f"`{c}`").alias(f"carried_{i}") for i, c in enumerate(carry)]
    return columns, "".join(f", carried_{i} {kinds[c]}" for i, c in enumerate(carry))


def restored(frame, carry: tuple[str, ...]):
    """Give carried columns their own names back."""
    for i, c in enumerate(carry):
        frame = frame.withColumnRenamed(f"carried_{i}", c)
    return frame
