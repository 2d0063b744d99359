"""Pairs of words whose sets of substrings are similar, found and verified in tasks.

Two sets of similarity ``least`` share one of the first ``n - ceil(least n) + 1``
substrings of each in any one order of all substrings, so a task that holds the
words of a substring finds the pairs that meet there. The order is rarest first
by an approximate table of counts; errors in that table cost time only. Parities
of hashed substrings bound the difference of two sets from below; what they allow
is compared exactly, and told at the first substring that both words share.
"""

from __future__ import annotations

import math
import zlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame

from lexnorm.functions.hashing import grams_of
from lexnorm.operators.matching import CELLS_HELD, tally
from lexnorm.sources.store import materialise, ship

#: Cells of the table of counts (a byte each), and substrings that a task remembers.
CELLS, HELD_GRAMS = 1 << 22, 1_000_000
#: Rows of a group of substrings, and of a block of a crowded one.
GROUP_ROWS, BLOCK_ROWS = 100_000, 20_000
STEP = 1 << 20
#: What is sent of a word to one of its substrings, packed by part: single rows would take twice the disk.
ROW = pa.schema([("key", pa.int64()), ("block", pa.int16()), ("n", pa.int32()), ("remaining", pa.int32()), ("parity", pa.int64()), ("word", pa.string()), ("ahead", pa.binary())])
PACKED_ROWS = 150_000


def _cell(gram: str) -> int:
    return zlib.crc32(gram.encode()) % CELLS


def _bit(gram: str) -> int:
    return 1 << (zlib.crc32(gram.encode(), 0x5BD1E995) >> 26)


def _places(n: int) -> str:
    """The kind of number that holds places in a set of ``n``."""
    return "<u1" if n <= 256 else "<u4"


def candidates(key: np.ndarray, n: np.ndarray, left: np.ndarray, block: np.ndarray, parity: np.ndarray, least: float) -> Iterator[tuple[np.ndarray, np.ndarray]]:
    """Row indices of pairs of one key that sizes, places and parities allow to have similarity ``least``."""
    order = np.lexsort((n, key))
    key, n, left, block, parity = (x[order] for x in (key, n, left, block, parity))
    rank = np.cumsum(np.concatenate([[0], key[1:] != key[:-1]]))
    wide = int(n.max()) + 1
    most = np.minimum(wide - 1, np.floor(n / least + 1e-6).astype(np.int64)) if least > 0 else np.full(len(n), wide - 1)
    count = np.searchsorted(rank * wide + n, rank * wide + most, "right") - np.arange(len(n)) - 1
    ends = np.cumsum(count)
    i = 0
    while i < len(n):
        j = max(i + 1, int(np.searchsorted(ends, (ends[i - 1] if i else 0) + STEP, "right")))
        a = np.repeat(np.arange(i, j), count[i:j])
        b = a + 1 + np.arange(len(a)) - np.repeat(ends[i:j] - count[i:j] - (ends[i - 1] if i else 0), count[i:j])
        i = j
        # Blocks 1 and 2 of a cut key meet each other; rows of block 0 meet all rows of it.
        shared = np.ceil((n[a] + n[b]) * (least / (1 + least)) - 1e-6).astype(np.int64)
        fit = (np.minimum(left[a], left[b]) >= shared) & ((block[a] + block[b]) % 3 == 0)
        a, b, shared = a[fit], b[fit], shared[fit]
        fit = np.bitwise_count(parity[a] ^ parity[b]) <= n[a] + n[b] - 2 * shared
        yield order[a[fit]], order[b[fit]]


def pairs(vocab: DataFrame, char_lens: tuple[int, ...] | str, least: float) -> DataFrame:
    """``src, dst, jaccard`` (src < dst) of all pairs of distinct words with similarity ``least`` or more."""
    spark = vocab.sparkSession
    ship(spark)
    vocab = materialise(vocab.select("word").where("word is not null"), "words")

    def cells(batches: Iterator[pa.RecordBatch]) -> Iterator[np.ndarray]:
        memo: dict[str, int] = {}
        found: list[int] = []
        for b in batches:
            for w in b.column(0).to_pylist():
                for g in grams_of(w, char_lens):
                    if (c := memo.get(g)) is None:
                        c = memo[g] = _cell(g)
                    found.append(c)
            if len(memo) > HELD_GRAMS:
                memo.clear()
            if len(found) > CELLS_HELD:
                yield np.array(found, dtype=np.int64)
                found = []
        if found:
            yield np.array(found, dtype=np.int64)

    steps = spark.sparkContext.broadcast(tally(vocab, cells, CELLS))
    parts = max(16, vocab.count() * 8 // GROUP_ROWS)

    def members(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        full = steps.value
        memo: dict[str, tuple[int, str, int, int]] = {}

        def packed(rows: list[tuple]) -> pa.RecordBatch:
            part = np.array([r[0] for r in rows]) % 2_147_483_647 % parts
            order = np.argsort(part, kind="stable")
            some, first = np.unique(part[order], return_index=True)
            every = pa.RecordBatch.from_arrays([pa.array(c, f.type) for c, f in zip(zip(*rows, strict=True), ROW, strict=True)], schema=ROW).take(pa.array(order))
            blobs = [every.slice(i, j - i).serialize().to_pybytes() for i, j in zip(first.tolist(), [*first[1:].tolist(), len(order)], strict=True)]
            return pa.RecordBatch.from_arrays([pa.array(some.astype(np.int32)), pa.array(blobs, pa.binary())], names=["part", "rows"])

        rows: list[tuple] = []
        for b in batches:
            for w in b.column(0).to_pylist():
                own, parity = [], 0
                for at, g in enumerate(sorted(grams_of(w, char_lens))):
                    if (known := memo.get(g)) is None:
                        known = memo[g] = (int(full[_cell(g)]), g, zlib.crc32(g.encode()) << 7 ^ zlib.adler32(g.encode()), _bit(g))
                    parity ^= known[3]
                    own.append((known[0], g, at, known[2]))
                own.sort()
                n = len(own)
                ahead = np.array([x[2] for x in own], dtype=_places(n)).tobytes()
                for pos in range(min(n, n - math.ceil(n * least - 1e-6) + 1)):
                    step, _, _, key = own[pos]
                    blocks = math.ceil(2 ** (step / 8) / BLOCK_ROWS)
                    mine = zlib.crc32(w.encode()) % blocks
                    for other in range(blocks):
                        low, high = min(mine, other), max(mine, other)
                        split = key + (low * 65_521 + high) * 0x9E3779B97F4A7C15 & (1 << 63) - 1 if blocks > 1 else key
                        rows.append((split, 0 if low == high else 1 if mine == low else 2, n, n - pos, parity - (1 << 64) if parity >> 63 else parity, w, ahead[: len(ahead) // n * (pos + 1)]))
                if len(rows) > PACKED_ROWS:
                    yield packed(rows)
                    rows = []
            if len(memo) > HELD_GRAMS:
                memo.clear()
        if rows:
            yield packed(rows)

    def search(packs: pa.Table) -> pa.Table:
        group = pa.Table.from_batches([pa.ipc.read_record_batch(pa.py_buffer(x), ROW) for x in packs.column("rows").to_pylist()], ROW)
        key, block, n, left, parity = (group.column(c).to_numpy() for c in ("key", "block", "n", "remaining", "parity"))
        words, ahead = group.column("word").to_pylist(), group.column("ahead").to_pylist()
        sets: dict[str, set[str]] = {}
        here: dict[int, list[str]] = {}
        out: list[tuple[str, str, float]] = []

        def begun(i: int) -> list[str]:
            if (got := here.get(i)) is None:
                known = sorted(sets.setdefault(words[i], grams_of(words[i], char_lens)))
                got = here[i] = [known[k] for k in np.frombuffer(ahead[i], _places(n[i])).tolist()]
            return got

        for some, others in candidates(key, n, left, block, parity.view(np.uint64), least):
            for i, j in zip(some.tolist(), others.tolist(), strict=True):
                first, second = begun(i), begun(j)
                one, two = sets[words[i]], sets[words[j]]
                # The pair is told at the first substring of the order that both words have.
                if first[-1] != second[-1] or words[i] == words[j] or not two.isdisjoint(first[:-1]):
                    continue
                shared = len(one & two)
                if (value := shared / (len(one) + len(two) - shared)) >= least:
                    out.append((min(words[i], words[j]), max(words[i], words[j]), value))
        src, dst, value = zip(*out, strict=True) if out else ((), (), ())
        return pa.table({"src": pa.array(src, pa.string()), "dst": pa.array(dst, pa.string()), "jaccard": pa.array(value, pa.float64())})

    sent = vocab.mapInArrow(members, "part int, rows binary")
    return sent.groupBy("part").applyInArrow(search, "src string, dst string, jaccard double")
