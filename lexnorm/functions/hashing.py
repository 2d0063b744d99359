"""Word signatures: universal hashing, one-permutation binning, densification, folding.

Two back ends give the same values: ``relational`` is plain columns and one
aggregation, and ``arrow`` a NumPy kernel that hashes each distinct substring
once for a batch of words.
"""

from __future__ import annotations

import hashlib
import random
import zlib
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from lexnorm.config import PRIME, UNIVERSE, HashParams
from lexnorm.functions.shingles import gram_set
from lexnorm.sources.store import ship


@dataclass(frozen=True)
class Repetition:
    """Constants of one repetition, reduced modulo PRIME so that products fit 62 bits."""

    a: tuple[int, ...]  # one for each bin if every bin has its own permutation, else one
    b: tuple[int, ...]
    fold_a: int
    fold_b: int
    fold2_a: int
    fold2_b: int
    coins: tuple[bool, ...]  # True: an empty bin borrows from the right


@dataclass(frozen=True)
class Family:
    params: HashParams
    repetitions: tuple[Repetition, ...]

    @staticmethod
    def draw(params: HashParams) -> Family:
        """All constants from the seed alone, so a stored seed restores an index's functions."""
        rng = random.Random(params.seed)

        def multiplier() -> int:
            while True:
                if a := rng.randint(1, UNIVERSE) % PRIME:
                    return a

        def shift() -> int:
            return rng.randint(0, UNIVERSE - 1) % PRIME

        n = params.bins if params.scheme == "kperm" else 1
        out = []
        for _ in range(params.repetitions):
            a, b = tuple(multiplier() for _ in range(n)), tuple(shift() for _ in range(n))
            out.append(Repetition(a, b, multiplier(), shift(), multiplier(), shift(), tuple(rng.random() < 0.5 for _ in range(params.bins))))
        return Family(params, tuple(out))


def fingerprint(gram: Column, kind: str = "md5_32") -> Column:
    """A substring as an integer in [0, PRIME)."""
    if kind == "md5_32":
        raw = F.conv(F.substring(F.md5(gram), 1, 8), 16, 10).cast("long")
    elif kind == "crc32":
        raw = F.crc32(gram)
    elif kind == "xxhash64":
        raw = F.pmod(F.xxhash64(gram), F.lit(UNIVERSE))
    else:
        raise ValueError(kind)
    return raw % F.lit(PRIME)


def fingerprint_of(gram: str, kind: str) -> int:
    raw = gram.encode()
    if kind == "md5_32":
        return int(hashlib.md5(raw).hexdigest()[:8], 16) % PRIME
    if kind == "crc32":
        return zlib.crc32(raw) % PRIME
    if kind == "xxhash64":
        return xxhash.xxh64_intdigest(raw, 42) % UNIVERSE % PRIME
    raise ValueError(kind)


def affine(x: Column, a: int, b: int) -> Column:
    return (x * F.lit(a) + F.lit(b)) % F.lit(PRIME)


def probe_order(k: int, bins: int, right: bool) -> list[int]:
    """Bins an empty bin ``k`` looks at, nearest first, around the circle."""
    step = 1 if right else -1
    return [(k + step * i) % bins for i in range(bins)]


def sides(r: Repetition, params: HashParams) -> list[bool]:
    if params.densify in ("left", "right"):
        return [params.densify == "right"] * params.bins
    return list(r.coins)


#: What ``coin_offset`` adds for each step walked, so that borrowed minima differ from native ones.
OFFSET = 1_000_003


def densify(minima: list[Column], right: list[bool], offset: bool = False) -> list[Column]:
    """Fill null bins with the first non-null one on the coin's side."""
    m = len(minima)
    out = []
    for k in range(m):
        order = probe_order(k, m, right[k])
        out.append(F.coalesce(*((minima[j] + F.lit(OFFSET * i)) % F.lit(PRIME) if offset and i else minima[j] for i, j in enumerate(order))))
    return out


def fold(dense: list[Column], a: int, b: int) -> Column:
    """Chain of hashed sums over the bins, from zero."""
    out = F.lit(0).cast("long")
    for s in dense:
        out = ((s + out) % F.lit(PRIME) * F.lit(a) + F.lit(b)) % F.lit(PRIME)
    return out


def family_table(spark, family: Family) -> DataFrame:
    """The constants as a table, one row a repetition."""
    p = family.params
    rows = [(i, *r.a, *r.b, r.fold_a, r.fold_b, r.fold2_a, r.fold2_b, *sides(r, p)) for i, r in enumerate(family.repetitions)]
    n = len(family.repetitions[0].a)
    names = ["rep", *(f"a{k}" for k in range(n)), *(f"b{k}" for k in range(n)), "fa", "fb", "fa2", "fb2", *(f"right{k}" for k in range(p.bins))]
    kinds = ["int", *["long"] * (2 * n + 4), *["boolean"] * p.bins]
    return spark.createDataFrame(rows, ", ".join(f"{c} {t}" for c, t in zip(names, kinds, strict=True)))


def bin_minima(vocab: DataFrame, family: Family) -> DataFrame:
    """``word, rep, m0..`` (null: empty bin): every substring times every repetition, minima by one aggregation."""
    p = family.params
    grams = vocab.select("word", F.explode(gram_set(F.col("word"), p.char_lens)).alias("gram"))
    x = grams.select("word", fingerprint(F.col("gram"), p.fingerprint).alias("x"))
    wide = x.crossJoin(F.broadcast(family_table(vocab.sparkSession, family)))
    if p.scheme == "kperm":
        minima = [F.min((F.col("x") * F.col(f"a{k}") + F.col(f"b{k}")) % F.lit(PRIME)).alias(f"m{k}") for k in range(p.bins)]
        return wide.groupBy("word", "rep").agg(*minima)
    h = wide.select("word", "rep", ((F.col("x") * F.col("a0") + F.col("b0")) % F.lit(PRIME)).alias("h"))
    h = h.withColumn("bin", F.expr(f"cast(h * {p.bins} div {p.space} as int)"))
    return h.groupBy("word", "rep").agg(*(F.min(F.when(F.col("bin") == k, F.col("h"))).alias(f"m{k}") for k in range(p.bins)))


def densified(minima: DataFrame, family: Family) -> DataFrame:
    """``word, rep, d0..`` without nulls."""
    p = family.params
    keyed = minima.join(F.broadcast(family_table(minima.sparkSession, family)), "rep")
    out = []
    offset = p.densify == "coin_offset"
    for k in range(p.bins):
        by = {right: densify([F.col(f"m{j}") for j in range(p.bins)], [right] * p.bins, offset)[k] for right in (True, False)}
        out.append(F.when(F.col(f"right{k}"), by[True]).otherwise(by[False]).alias(f"d{k}"))
    return keyed.select("word", "rep", "fa", "fb", "fa2", "fb2", *out)


def signatures_relational(vocab: DataFrame, family: Family) -> DataFrame:
    """``word, rep, sig`` in long form, by columns alone."""
    p = family.params
    dense = densified(bin_minima(vocab, family), family)

    def chain(a: str, b: str) -> Column:
        o = F.lit(0).cast("long")
        for k in range(p.bins):
            o = ((F.col(f"d{k}") + o) % F.lit(PRIME) * F.col(a) + F.col(b)) % F.lit(PRIME)
        return o

    sig = chain("fa", "fb") if p.width == 31 else chain("fa", "fb") * F.lit(1 << 31) + chain("fa2", "fb2")
    return dense.select("word", "rep", sig.alias("sig"))


def grams_of(word: str, char_lens: tuple[int, ...] | str) -> set[str]:
    n = len(word)
    lens = range(1, n + 1) if char_lens == "all" else char_lens
    return {word[i : i + k] for k in lens for i in range(n - k + 1)}


class Kernel:
    """Signatures of many words by NumPy; substrings are fingerprinted once each (the memo is bounded)."""

    def __init__(self, family: Family, most: int = 1_000_000):
        self.family, self.most = family, most
        self.memo: dict[str, int] = {}

    def __call__(self, words: list[str]) -> tuple[np.ndarray, np.ndarray]:
        """Indices of words that have substrings, and their signatures (words by repetitions)."""
        p = self.family.params
        if len(self.memo) > self.most:
            self.memo.clear()
        memo, kind = self.memo, p.fingerprint
        values: list[int] = []
        sizes = np.zeros(len(words), dtype=np.int64)
        for i, w in enumerate(words):
            own = grams_of(w, p.char_lens)
            sizes[i] = len(own)
            for g in own:
                x = memo.get(g)
                if x is None:
                    x = memo[g] = fingerprint_of(g, kind)
                values.append(x)
        some = np.flatnonzero(sizes)
        x = np.array(values, dtype=np.int64)
        starts = np.concatenate([[0], np.cumsum(sizes[some])])[:-1].astype(np.int64)
        out = np.zeros((len(some), p.repetitions), dtype=np.int64)
        if len(some):
            for r, rep in enumerate(self.family.repetitions):
                out[:, r] = self._one(x, starts, rep)
        return some, out

    def _one(self, x: np.ndarray, starts: np.ndarray, rep: Repetition) -> np.ndarray:
        p = self.family.params
        empty = np.int64(1) << 62
        if p.scheme == "kperm":
            minima = [np.minimum.reduceat((x * a + b) % PRIME, starts) for a, b in zip(rep.a, rep.b, strict=True)]
        else:
            h = (x * rep.a[0] + rep.b[0]) % PRIME
            at = h * p.bins // p.space
            minima = [np.minimum.reduceat(np.where(at == k, h, empty), starts) for k in range(p.bins)]
        right = sides(rep, p)
        dense = []
        for k in range(p.bins):
            value = np.full(len(starts), empty)
            for i, j in enumerate(probe_order(k, p.bins, right[k])):
                got = (minima[j] + OFFSET * i) % PRIME if p.densify == "coin_offset" and i else minima[j]
                value = np.where((value == empty) & (minima[j] != empty), got, value)
            dense.append(value)

        def chain(a: int, b: int) -> np.ndarray:
            o = np.zeros(len(starts), dtype=np.int64)
            for d in dense:
                o = ((d + o) % PRIME * a + b) % PRIME
            return o

        first = chain(rep.fold_a, rep.fold_b)
        return first if p.width == 31 else (first << 31) + chain(rep.fold2_a, rep.fold2_b)


def signatures(vocab: DataFrame, family: Family, backend: str = "arrow") -> DataFrame:
    """``word, sig`` (an array of one value a repetition) for words that have substrings.

    Signatures of 31 bits are kept as integers, of 62 bits as longs.
    """
    kind = "int" if family.params.width == 31 else "long"
    if backend == "relational":
        long = signatures_relational(vocab, family)
        return long.groupBy("word").agg(F.transform(F.array_sort(F.collect_list(F.struct("rep", "sig"))), lambda s: s["sig"].cast(kind)).alias("sig"))
    ship(vocab.sparkSession)
    value = pa.int32() if kind == "int" else pa.int64()

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        kernel = Kernel(family)
        for b in batches:
            for i in range(0, b.num_rows, 8192):
                words = b.column(0).slice(i, 8192)
                some, sigs = kernel(words.to_pylist())
                flat = pa.array(sigs.ravel()).cast(value)
                offsets = pa.array(np.arange(len(some) + 1, dtype=np.int32) * family.params.repetitions)
                yield pa.RecordBatch.from_arrays([words.take(pa.array(some)), pa.ListArray.from_arrays(offsets, flat)], names=["word", "sig"])

    return vocab.select("word").where("word is not null").mapInArrow(run, f"word string, sig array<{kind}>")
