"""Token ids in a binary file with Elias-Fano document boundaries.

Layout of one block (little-endian):

    magic  8 bytes  b"TIDSEF01"
    header 7 x u64  documents, ids, width of an id in bytes, low bits, bytes of the low part, bytes of the high part, samples
    doc ids         i64 for each document
    low part        the low bits of every boundary, packed
    high part       bit (boundary >> low) + i set for the i-th boundary
    samples         u32 for every 64th boundary: its bit position in the high part, so ``select`` starts near
    ids             all token ids of the block, one after another

There is a boundary at the start of each document and one at the end, so a
document's ids lie between two neighbouring boundaries. A boundary costs about
2 + log2(ids / documents) bits instead of 64.

Blocks travel through Spark's own writers: a file of the format is a Parquet
part whose rows are blocks in ascending document order. Any store that Spark
reaches will do, and a lost executor repeats just its part.
"""

from __future__ import annotations

import gc
import os
import re
import struct
import zlib
from collections.abc import Iterator
from dataclasses import dataclass
from functools import reduce
from operator import or_

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from lexnorm.llm.memo import Memo
from lexnorm.llm.words import slices, span_hashes
from lexnorm.sources.store import new_folder, ship

MAGIC = b"TIDSEF01"
HEADER = struct.Struct("<7Q")
STEP = 64
#: A block is closed once it holds so many ids; a longer document has a block of its own.
BLOCK_IDS = 1 << 20
END_ID = 0
#: Columns of a block's row: its part, the ids of that part before it, its ids, rows without an id, its first and last id.
BLOCK_NAMES = ["part", "before", "n_ids", "n_null", "first_id", "last_id", "block"]
BLOCK_KINDS = [pa.int32(), *[pa.int64()] * 5, pa.binary()]


class EliasFano:
    """A non-decreasing sequence in near-minimal space, with ``select``."""

    def __init__(self, n: int, low: int, lows: np.ndarray, highs: np.ndarray, samples: np.ndarray):
        self.n, self.low, self.lows, self.highs, self.samples = n, low, lows, highs, samples

    @staticmethod
    def encode(values: np.ndarray) -> EliasFano:
        v = np.asarray(values, dtype=np.uint64)
        n = len(v)
        top = int(v[-1]) if n else 0
        low = max(0, (top // max(n, 1)).bit_length() - 1) if n else 0
        bits = ((v[:, None] >> np.arange(low, dtype=np.uint64)) & np.uint64(1)).astype(np.uint8).ravel()
        at = (v >> np.uint64(low)) + np.arange(n, dtype=np.uint64)
        high = np.zeros(int(at[-1]) + 1 if n else 0, dtype=np.uint8)
        high[at.astype(np.int64)] = 1
        return EliasFano(n, low, np.packbits(bits, bitorder="little"), np.packbits(high, bitorder="little"), at[::STEP].astype(np.uint32))

    def select(self, i: int) -> int:
        """The i-th value: the position of the i-th set bit of the high part gives its upper bits."""
        if not 0 <= i < self.n:
            raise IndexError(i)
        at = int(self.samples[i // STEP])
        left = i % STEP
        byte, word = at >> 3, int(self.highs[at >> 3]) >> (at & 7) << (at & 7)
        while (have := word.bit_count()) <= left:
            left -= have
            byte += 1
            word = int(self.highs[byte])
        for _ in range(left):
            word &= word - 1
        pos = (byte << 3) + (word & -word).bit_length() - 1
        value = (pos - i) << self.low
        first = i * self.low
        for k in range(self.low):
            value |= (int(self.lows[(first + k) >> 3]) >> ((first + k) & 7) & 1) << k
        return value

    def decode(self) -> np.ndarray:
        """All values."""
        at = np.flatnonzero(np.unpackbits(self.highs, bitorder="little"))[: self.n].astype(np.int64)
        high = (at - np.arange(self.n)) << self.low
        bits = np.unpackbits(self.lows, bitorder="little")[: self.n * self.low].reshape(self.n, self.low).astype(np.int64)
        return high + (bits << np.arange(self.low)).sum(axis=1)


def pack(doc_ids: np.ndarray, lengths: np.ndarray, ids: bytes, width: int) -> bytes:
    """One block from documents' ids, laid end to end in ``ids``."""
    ef = EliasFano.encode(np.concatenate([[0], np.cumsum(lengths)]))
    head = HEADER.pack(len(doc_ids), len(ids) // width, width, ef.low, len(ef.lows), len(ef.highs), len(ef.samples))
    return b"".join((MAGIC, head, np.asarray(doc_ids, "<i8").tobytes(), ef.lows.tobytes(), ef.highs.tobytes(), ef.samples.astype("<u4").tobytes(), ids))


@dataclass
class Block:
    """A read block; ``document(k)`` finds the k-th document by ``select`` alone."""

    doc_ids: np.ndarray
    bounds: EliasFano
    ids: np.ndarray

    @staticmethod
    def read(raw: bytes) -> Block:
        if raw[:8] != MAGIC:
            raise ValueError("not a token block")
        docs, n, width, low, lows, highs, samples = HEADER.unpack_from(raw, 8)
        at = 8 + HEADER.size

        def take(kind: str, count: int) -> np.ndarray:
            nonlocal at
            out = np.frombuffer(raw, kind, count, at)
            at += out.nbytes
            return out

        doc_ids = take("<i8", docs)
        bounds = EliasFano(docs + 1, low, take("u1", lows), take("u1", highs), take("<u4", samples))
        return Block(doc_ids, bounds, take(f"<u{width}", n))

    def document(self, k: int) -> np.ndarray:
        return self.ids[self.bounds.select(k) : self.bounds.select(k + 1)]


#: Kinds of bytes in plain texts: letters (ASCII, and UTF-8 of U+00C0 to U+024F), digits, signs, space, line feed.
_OTHER, _LETTER, _DIGIT, _SIGN, _SPACE, _LINE = range(6)
_KIND = np.zeros(256, dtype=np.uint8)
_KIND[33:127] = _SIGN
for _low, _high, _kind in ((48, 58, _DIGIT), (65, 91, _LETTER), (97, 123, _LETTER), (0x80, 0xC0, _LETTER), (0xC3, 0xCA, _LETTER), (32, 33, _SPACE), (10, 11, _LINE)):
    _KIND[_low:_high] = _kind
#: Where white space stands next to white space or at an end, runs of it can't be told from words by single bytes.
_CUT = re.compile(r"(?<=\S)(?= \S)")


def byte_letters() -> list[str]:
    """The letter that stands for each byte in a byte-level vocabulary: itself if printable, else one from U+0100 on."""
    shown = {*range(33, 127), *range(161, 173), *range(174, 256)}
    rest = iter(range(256, 512))
    return [chr(b if b in shown else next(rest)) for b in range(256)]


class PieceEncoder:
    """Encodes texts piece by piece, each distinct piece once while remembered.

    A byte-level BPE cuts a text into runs of letters, digits and signs, each with
    the space before it, and never merges across cuts. In plain texts the cuts of a
    whole batch are found on its bytes, each distinct run goes to the library's model
    once, and ids are laid out by one gather. Other texts are cut before " word" only
    and their pieces encoded as texts; those that hold the text of an added token, and
    all texts of tokenizers of another kind, are encoded whole.
    """

    def __init__(self, path: str, most: int = 400_000, width: int = 2):
        from tokenizers import Tokenizer

        self.tokenizer = Tokenizer.from_file(path)
        self.kind = f"<u{width}"
        self.runs = Memo(self._runs, most)
        self.others = Memo(self._ids, most // 8)
        self.added = [t.content for t in self.tokenizer.get_added_tokens_decoder().values()]
        pre = self.tokenizer.pre_tokenizer
        self.cuts = self.tokenizer.normalizer is None and type(pre).__name__ == "ByteLevel" and not pre.add_prefix_space and pre.use_regex
        self.letters = dict(enumerate(byte_letters()))

    def _ids(self, texts: list[str]) -> list[bytes]:
        return [np.array(e.ids, dtype=self.kind).tobytes() for e in self.tokenizer.encode_batch_fast(texts, add_special_tokens=False)]

    def _runs(self, runs: list[bytes]) -> list[bytes]:
        model, letters = self.tokenizer.model, self.letters
        tokenize = model.tokenize
        found = [[t.id for t in tokenize(r.decode("latin-1").translate(letters))] for r in runs]
        raw, width = np.array([i for f in found for i in f], dtype=self.kind).tobytes(), np.dtype(self.kind).itemsize
        ends = (np.cumsum([len(f) for f in found]) * width).tolist()
        return [raw[s:e] for s, e in zip([0, *ends], ends)]

    def _plain(self, kinds: np.ndarray, data: np.ndarray, off: np.ndarray) -> np.ndarray:
        """Whether each text has single spaces and line feeds between runs, and letters of known kind."""
        bad = kinds == _OTHER
        blank = kinds >= _SPACE
        edge = np.zeros(len(data) + 1, dtype=bool)
        edge[off] = True
        bad |= blank & (edge[:-1] | edge[1:])
        if len(data) > 1:
            one, two = data[:-1], data[1:]
            pairs = blank[:-1] & blank[1:]
            pairs |= (one == 39) & (kinds[1:] == _LETTER)  # what follows an apostrophe may be a contraction
            pairs |= ((one == 0xC3) & ((two == 0x97) | (two == 0xB7))) | ((one == 0xC9) & (two > 0x8F))
            bad[:-1] |= pairs
        total = np.zeros(len(data) + 1, dtype=np.int64)
        np.cumsum(bad, out=total[1:])
        return total[off[1:]] == total[off[:-1]]

    def encode(self, texts: list[str]) -> list[bytes]:
        """The ids of each text, as little-endian integers of the encoder's width."""
        if not self.cuts:
            return self._ids(texts)
        raws = [t.encode() for t in texts]
        blob = b"".join(raws)
        data = np.frombuffer(blob, dtype=np.uint8)
        off = np.cumsum([0, *map(len, raws)])
        kinds = _KIND[data]
        plain = self._plain(kinds, data, off)
        special = np.zeros(len(texts), dtype=bool)
        for token in self.added:
            if token.encode() in blob:
                special |= np.array([token in t for t in texts])
        out = self._laid_out(blob, data, kinds, off, np.flatnonzero(plain & ~special), len(texts))
        cut = np.flatnonzero(~plain & ~special).tolist()
        for i, x in zip(cut, self.others.joined([_CUT.split(texts[i]) for i in cut]), strict=True):
            out[i] = x
        whole = np.flatnonzero(special).tolist()
        for i, x in zip(whole, self._ids([texts[i] for i in whole]), strict=True):
            out[i] = x
        return out

    def _laid_out(self, blob: bytes, data: np.ndarray, kinds: np.ndarray, off: np.ndarray, chosen: np.ndarray, n: int) -> list[bytes]:
        """Ids of the chosen texts of a batch; the others' places stay empty."""
        out = [b""] * n
        first = np.zeros(len(data) + 1, dtype=bool)
        first[off] = True
        begins = first[:-1].copy()
        begins[1:] |= (kinds[1:] != kinds[:-1]) & (kinds[:-1] != _SPACE)
        starts = np.flatnonzero(begins)
        ends = np.append(starts[1:], len(data))
        owner = np.searchsorted(off, starts, side="right") - 1
        mine = np.zeros(n, dtype=bool)
        mine[chosen] = True
        mine = mine[owner]
        starts, ends, owner = starts[mine], ends[mine], owner[mine]
        if not len(starts):
            return out
        _, index, which = np.unique(span_hashes(data, starts, ends - starts), return_index=True, return_inverse=True)
        runs = [blob[s:e] for s, e in zip(starts[index].tolist(), ends[index].tolist())]
        ids = self.runs.each(runs)
        width = np.dtype(self.kind).itemsize
        sizes = np.fromiter(map(len, ids), dtype=np.int64, count=len(ids)) // width
        pool = np.frombuffer(b"".join(ids), dtype=self.kind)
        at = np.cumsum(sizes) - sizes
        count = sizes[which]
        done = np.cumsum(count)
        laid = pool[np.repeat(at[which] - (done - count), count) + np.arange(done[-1])].tobytes()
        bounds = np.concatenate([[0], done])[np.searchsorted(owner, np.arange(n + 1))] * width
        for i in chosen.tolist():
            out[i] = laid[bounds[i] : bounds[i + 1]]
        return out


_caches: dict[tuple[str, int], PieceEncoder] = {}


def _cache(path: str, width: int) -> PieceEncoder:
    os.environ["TOKENIZERS_PARALLELISM"] = "false"
    gc.set_threshold(200_000, 20, 100)  # pieces are many and form no cycles
    if (path, width) not in _caches:
        _caches[path, width] = PieceEncoder(path, width=width)
    return _caches[path, width]


def write(documents: DataFrame, out: str, tokenizer: str, width: int = 2, end_id: int = END_ID, id_col: str = "doc_id", text_col: str = "text") -> None:
    """Encode every text and write blocks under ``out`` in ascending id order.

    ``width`` is the bytes of an id (2 serves vocabularies up to 65,536). A null
    text is empty: it has the end id alone. Null ids come first; repeated rows
    keep a place each, in the order of their texts. Other columns are ignored.
    """
    ship(documents.sparkSession)
    rows = documents.select(F.col(id_col).cast("long").alias("doc_id"), F.coalesce(F.col(text_col).cast("string"), F.lit("")).alias("text"))
    ordered = rows.repartitionByRange(F.asc_nulls_first("doc_id")).sortWithinPartitions(F.asc_nulls_first("doc_id"), "text")
    end = np.array([end_id], dtype=f"<u{width}").tobytes()

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        from pyspark import TaskContext

        part, before = TaskContext.get().partitionId(), 0
        ids: list[int] = []
        lengths: list[int] = []
        nulls: list[bool] = []
        data: list[bytes] = []
        total = 0

        def block() -> pa.RecordBatch:
            nonlocal before, total
            raw = pack(np.array(ids, dtype=np.int64), np.array(lengths, dtype=np.int64), b"".join(data), width)
            known = [i for i, null in zip(ids, nulls, strict=True) if not null]
            row = (part, before, total, sum(nulls), known[0] if known else None, known[-1] if known else None, raw)
            before, total = before + total, 0
            for x in (ids, lengths, nulls, data):
                x.clear()
            return pa.RecordBatch.from_arrays([pa.array([v], k) for v, k in zip(row, BLOCK_KINDS, strict=True)], names=BLOCK_NAMES)

        cache = _cache(tokenizer, width)
        for b in batches:
            for some in slices(b, "text", 1 << 22):
                for doc, raw in zip(some.column(0).to_pylist(), cache.encode(some.column(1).to_pylist()), strict=True):
                    n = len(raw) // width + 1
                    if ids and total + n > BLOCK_IDS:
                        yield block()
                    ids.append(0 if doc is None else doc)
                    nulls.append(doc is None)
                    lengths.append(n)
                    data.append(raw + end)
                    total += n
        if ids:
            yield block()

    ordered.mapInArrow(run, "part int, before long, n_ids long, n_null long, first_id long, last_id long, block binary").write.parquet(out)


def _placed(spark: SparkSession, path: str, blocks: DataFrame) -> DataFrame:
    """Blocks with ``start``, the ids of the whole file before each: parts add up one sum each, a block knows its place in its part."""
    sums = spark.read.parquet(path).groupBy("part").agg(F.sum("n_ids").alias("n")).orderBy("part").collect()
    at, starts = 0, []
    for part, n in sums:
        starts.append((part, at))
        at += n
    table = spark.createDataFrame(starts, "part int, part_start long")
    return blocks.join(F.broadcast(table), "part").withColumn("start", F.col("part_start") + F.col("before"))


def _documents(blocks: DataFrame, wanted: np.ndarray | None, with_ids: bool) -> DataFrame:
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for start, n_null, raw in zip(b.column(0).to_pylist(), b.column(1).to_pylist(), b.column(2), strict=True):
                block = Block.read(raw.as_py())
                n = len(block.doc_ids)
                some = np.arange(n) if wanted is None else np.flatnonzero(np.isin(block.doc_ids, wanted) & (np.arange(n) >= n_null))
                for i in range(0, len(some), 1000):
                    rows = some[i : i + 1000]
                    bounds = [(block.bounds.select(k), block.bounds.select(k + 1)) for k in rows.tolist()]
                    found = [block.ids[s:e].astype("<u4") for s, e in bounds]
                    cols = [
                        pa.array(block.doc_ids[rows], mask=rows < n_null),
                        pa.array([start + s for s, _ in bounds], pa.int64()),
                        pa.array([e - s for s, e in bounds], pa.int64()),
                        pa.array([zlib.crc32(x.tobytes()) for x in found], pa.int64()),
                    ]
                    if with_ids:
                        cols.append(pa.array([x.astype(np.int64) for x in found], pa.list_(pa.int64())))
                    yield pa.RecordBatch.from_arrays(cols, names=["doc_id", "start", "n_tokens", "ids_crc32", "ids"][: len(cols)])

    return blocks.select("start", "n_null", "block").mapInArrow(run, "doc_id long, start long, n_tokens long, ids_crc32 long" + (", ids array<long>" if with_ids else ""))


def read(spark: SparkSession, path: str, with_ids: bool = False) -> DataFrame:
    """``doc_id, start, n_tokens, ids_crc32`` (and ``ids``) of every document of the file, found by ``select``."""
    ship(spark)
    return _documents(_placed(spark, path, spark.read.parquet(path)), None, with_ids)


def fetch(spark: SparkSession, path: str, doc_ids: list[int]) -> DataFrame:
    """The same with ``ids`` for a few documents: blocks that can't hold them aren't read."""
    ship(spark)
    wanted = np.array(sorted(set(doc_ids)), dtype=np.int64)
    blocks = spark.read.parquet(path)
    near = [F.col("last_id").__ge__(int(i)) & F.col("first_id").__le__(int(i)) for i in wanted]
    chosen = blocks.where(reduce(or_, near)) if near else blocks.where("false")
    return _documents(_placed(spark, path, chosen), wanted, True)


def round_trip(documents: DataFrame, tokenizer: str, **options) -> DataFrame:
    """Write the token file of ``documents`` to the shared folder and read every document back."""
    spark = documents.sparkSession
    path = new_folder(spark, "token-file")
    write(documents, path, tokenizer, **options)
    return read(spark, path)
