"""Pairs of words that collide often, met in sparse buckets and weighed on the spot.

Each word is sent to its sparse buckets together with its whole signature, so a
task that holds a bucket knows the exact weight of each pair in it and whether
the pair also meets in an earlier bucket: pairs are never shuffled, joined or
made distinct. Which buckets are sparse is read from an approximate table of
bucket sizes; any order of the buckets gives the same pairs, so errors in that
table cost time only.
"""

from __future__ import annotations

import zlib
from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from lexnorm.operators.components import star_components
from lexnorm.sources.store import discard, materialise, ship

#: The table of sizes has ten cells or more for each word, at most so many (a byte each); fuller cells order buckets less well.
MOST_CELLS = 1 << 25
SPAN = 1 << 16
#: Cells that a task counts at once.
CELLS_HELD = 4_000_000
#: Buckets of more words are cut into blocks of about so many, paired with each other in tasks of their own.
BLOCK_WORDS = 2_000
#: Bytes of one pass over some of the repetitions, and rows of a group of buckets.
PASS_BYTES, GROUP_ROWS = 400_000_000, 100_000
STEP = 1 << 17
#: Repetitions joined first, rows of a group of their buckets, and groups outside the largest one that are sent to all executors.
FIRST, JOINED_ROWS, BROADCAST_NODES = 3, 500_000, 4_000_000
#: Repetitions are bits of a 64-bit number.
MOST_REPETITIONS = 64


def _mixed(sig: np.ndarray) -> np.ndarray:
    """A 64-bit hash of repetition and signature for each cell of a matrix (words by repetitions)."""
    h = sig.astype(np.uint64) + np.arange(1, sig.shape[1] + 1, dtype=np.uint64)[None, :] * np.uint64(0x9E3779B97F4A7C15)
    h = (h ^ (h >> np.uint64(30))) * np.uint64(0xBF58476D1CE4E5B9)
    h = (h ^ (h >> np.uint64(27))) * np.uint64(0x94D049BB133111EB)
    return h ^ (h >> np.uint64(31))


def _matrix(column: pa.Array, repetitions: int) -> np.ndarray:
    return column.flatten().to_numpy(zero_copy_only=False).reshape(-1, repetitions)


def tally(frame: DataFrame, cells_of: Callable[[Iterator[pa.RecordBatch]], Iterator[np.ndarray]], cells: int) -> np.ndarray:
    """About how often tasks name each cell, on a scale of eight steps for each doubling from one on (zero: never)."""
    ship(frame.sparkSession)

    def packed(found: np.ndarray) -> pa.RecordBatch:
        at, n = np.unique(found, return_counts=True)
        spans, first = np.unique(at // SPAN, return_index=True)
        ends = [*first[1:].tolist(), len(at)]
        rows = [((at[i:j] % SPAN).astype("<u2").tobytes(), n[i:j].astype("<u4").tobytes()) for i, j in zip(first.tolist(), ends, strict=True)]
        return pa.RecordBatch.from_arrays([pa.array(spans.astype(np.int64)), pa.array([r[0] for r in rows], pa.binary()), pa.array([r[1] for r in rows], pa.binary())], names=["span", "at", "n"])

    def count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        return map(packed, cells_of(batches))

    def add(span: pa.Table) -> pa.Table:
        total = np.zeros(SPAN, dtype=np.int64)
        for at, n in zip(span.column("at"), span.column("n")):
            total[np.frombuffer(at.as_py(), "<u2")] += np.frombuffer(n.as_py(), "<u4")
        steps = np.where(total > 0, 1 + np.floor(8 * np.log2(np.maximum(total, 1))), 0).astype(np.uint8)
        return pa.table({"span": span.column("span").slice(0, 1), "steps": pa.array([steps.tobytes()], pa.binary())})

    spans = frame.mapInArrow(count, "span long, at binary, n binary").groupBy("span").applyInArrow(add, "span long, steps binary")
    out = np.zeros(max(cells, SPAN), dtype=np.uint8)
    # Written first: the shuffle files go at once.
    spans = materialise(spans, "sizes")
    for r in spans.toLocalIterator():
        out[r.span * SPAN : (r.span + 1) * SPAN] = np.frombuffer(r.steps, np.uint8)
    discard(spans)
    return out


def sizes(sigs: DataFrame, repetitions: int, cells: int) -> np.ndarray:
    """About how many words each bucket holds, as :func:`tally` says it."""
    bits = np.uint64(64 - int(cells).bit_length() + 1)

    def buckets(batches: Iterator[pa.RecordBatch]) -> Iterator[np.ndarray]:
        found, held = [], 0
        for b in batches:
            found.append((_mixed(_matrix(b.column(0), repetitions)) >> bits).ravel().astype(np.int64))
            held += len(found[-1])
            if held > CELLS_HELD:
                yield np.concatenate(found)
                found, held = [], 0
        if held:
            yield np.concatenate(found)

    return tally(sigs.select("sig"), buckets, cells)


def _cells(words: int) -> int:
    return min(MOST_CELLS, max(SPAN, 1 << (10 * max(1, words) - 1).bit_length()))


def _met(group: pa.Table, repetitions: int, least: int, two_sided: bool) -> Iterator[tuple[np.ndarray, np.ndarray, np.ndarray]]:
    """Row indices and weights of the pairs of a group of buckets that meet here first."""
    key = group.column("key").to_numpy()
    order = np.argsort(key, kind="stable")
    key = key[order]
    rep, block, new = (group.column(c).to_numpy()[order] for c in ("rep", "block", "new"))
    wide = len(group.column("sig")[0].as_py()) // repetitions
    # One row for each repetition: neighbours in a bucket lie side by side.
    sig = np.ascontiguousarray(np.frombuffer(b"".join(group.column("sig").to_pylist()), f"<i{wide}").reshape(-1, repetitions)[order].T)
    kept = group.column("kept").to_numpy().view(np.uint64)[order]
    told = np.uint64(1) << rep.astype(np.uint64)
    live, d = np.arange(len(key)), 0
    while True:
        d += 1
        live = live[live + d < len(key)]
        live = live[key[live] == key[live + d]]
        if not len(live):
            return
        for i in range(0, len(live), STEP):
            a = live[i : i + STEP]
            b = a + d
            # Blocks 1 and 2 of a cut bucket meet each other; rows of block 0 meet all rows of it.
            fit = ((block[a] + block[b]) % 3 == 0) & (rep[a] == rep[b])
            if two_sided:
                fit &= new[a] != new[b]
            a, b = a[fit], b[fit]
            same = np.zeros(len(a), dtype=np.uint64)
            for r in range(repetitions):
                same |= (sig[r][a] == sig[r][b]).astype(np.uint64) << np.uint64(r)
            weight = np.bitwise_count(same)
            # The pair is told in the first of the buckets that both words were sent to.
            common = same & kept[a] & kept[b]
            first = (weight >= least) & ((common & (~common + np.uint64(1))) == told[a])
            if first.any():
                yield order[a[first]], order[b[first]], weight[first]


def roots(src: np.ndarray, dst: np.ndarray, n: int) -> np.ndarray:
    """The least index that each of ``n`` indices reaches over the links given."""
    up = np.arange(n)
    while len(src):
        a, b = up[src], up[dst]
        apart = a != b
        src, dst, a, b = src[apart], dst[apart], a[apart], b[apart]
        np.minimum.at(up, np.maximum(a, b), np.minimum(a, b))
        while True:
            further = up[up]
            if np.array_equal(further, up):
                break
            up = further
    return up


def tied(src: pa.Array, dst: pa.Array) -> tuple[pa.Array, pa.Array]:
    """Of linked words, each with the one that stands for its group, but for that one."""
    both = pa.chunked_array([*(src.chunks if isinstance(src, pa.ChunkedArray) else [src]), *(dst.chunks if isinstance(dst, pa.ChunkedArray) else [dst])]).combine_chunks().dictionary_encode()
    both = both.combine_chunks() if isinstance(both, pa.ChunkedArray) else both
    at = both.indices.to_numpy()
    up = roots(at[: len(src)], at[len(src) :], len(both.dictionary))
    moved = np.flatnonzero(up != np.arange(len(up)))
    return both.dictionary.take(pa.array(moved)), both.dictionary.take(pa.array(up[moved]))


def pairs(sigs: DataFrame, repetitions: int, least: int, old: DataFrame | None = None, forest: bool = False, best: bool = False) -> DataFrame:
    """``src, dst, weight`` of all pairs of words of ``sigs`` (``word, sig``) that collide ``least`` times or more, written to the shared folder.

    With ``old``, pairs of a word of ``sigs`` (``src``) and one of ``old`` (``dst``); else src < dst.
    With ``forest``, ``src, dst`` of links that join the same words, fewer of them.
    With ``old`` and ``best``, pairs that are lighter than another one of their ``src`` may be left out.

    A word's ``least - 1`` most crowded buckets are skipped: two words that share
    ``least`` buckets still share another one. Repetitions go in passes, so that
    what is on its way at one time stays near ``PASS_BYTES``.
    """
    if repetitions > MOST_REPETITIONS:
        raise ValueError(f"{repetitions} repetitions are more than the {MOST_REPETITIONS} that a mask holds")
    spark = sigs.sparkSession
    ship(spark)
    two_sided = old is not None
    frames = [sigs] + [old] * two_sided
    counts = [x.count() for x in frames]
    cells = _cells(max(counts))
    bits = np.uint64(64 - int(cells).bit_length() + 1)
    shared = spark.sparkContext.broadcast([sizes(x, repetitions, cells) for x in frames])
    every = sigs.select("word", "sig", F.lit(True).alias("new"))
    if two_sided:
        every = every.unionByName(old.select("word", "sig", F.lit(False).alias("new")))
    wide = 4 if dict(sigs.dtypes)["sig"] == "array<int>" else 8
    sent = sum(counts) * max(1, repetitions - least + 1)
    passes = min(repetitions, max(1, -(-sent * (40 + wide * repetitions) // PASS_BYTES)))
    parts = max(16, sent // passes // GROUP_ROWS)

    def members(of_pass: int):
        def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            steps = shared.value
            for whole in batches:
                for i in range(0, whole.num_rows, 8192):
                    b = whole.slice(i, 8192)
                    sig = np.ascontiguousarray(_matrix(b.column(1), repetitions), dtype=f"<i{wide}")
                    mixed = _mixed(sig)
                    at = (mixed >> bits).astype(np.int64)
                    full = steps[0][at].astype(np.int64)
                    if two_sided:
                        other = steps[1][at]
                        full = np.where((full > 0) & (other > 0), full + other, 0)
                    else:
                        full[full <= 1] = 0
                    crowded = np.argsort(-full, axis=1, kind="stable")
                    rank = np.empty_like(crowded)
                    np.put_along_axis(rank, crowded, np.arange(repetitions)[None, :], axis=1)
                    kept = (full > 0) & (rank >= least - 1)
                    r, c = np.nonzero(kept & (np.arange(repetitions) % passes == of_pass))
                    if not len(r):
                        continue
                    most = steps[0][at[r, c]].astype(np.float64)
                    if two_sided:
                        most = np.maximum(most, steps[1][at[r, c]])
                    blocks = np.ceil(2 ** (most / 8) / BLOCK_WORDS).astype(np.int64)
                    key, block = mixed[r, c], np.zeros(len(r), dtype=np.int64)
                    cut = np.flatnonzero(blocks > 1)
                    if len(cut):
                        own = np.array([zlib.crc32(w.encode()) for w in b.column(0).to_pylist()], dtype=np.int64)[r[cut]] % blocks[cut]
                        many = np.repeat(np.arange(len(cut)), blocks[cut])
                        other = np.arange(len(many)) - np.repeat(np.cumsum(blocks[cut]) - blocks[cut], blocks[cut])
                        mine = own[many]
                        low, high = np.minimum(mine, other), np.maximum(mine, other)
                        rest = np.flatnonzero(blocks <= 1)
                        r, c = np.concatenate([r[rest], r[cut][many]]), np.concatenate([c[rest], c[cut][many]])
                        split = key[cut][many] + (low * 65_521 + high + 1).astype(np.uint64) * np.uint64(0xD6E8FEB86659FD93)
                        key = np.concatenate([key[rest], split ^ (split >> np.uint64(32))])
                        block = np.concatenate([block[rest], np.where(low == high, 0, np.where(mine == low, 1, 2))])
                    flags = (kept.astype(np.uint64) << np.arange(repetitions, dtype=np.uint64)[None, :]).sum(axis=1, dtype=np.uint64).view(np.int64)
                    raw = lambda x: pa.Array.from_buffers(pa.binary(), len(x), [None, pa.py_buffer((np.arange(len(x) + 1, dtype=np.int32) * (x.shape[1] * x.itemsize)).tobytes()), pa.py_buffer(np.ascontiguousarray(x).tobytes())])
                    yield pa.RecordBatch.from_arrays(
                        [pa.array((key % np.uint64(parts)).astype(np.int32)), pa.array(key.view(np.int64)), pa.array(c.astype(np.int16)), pa.array(block.astype(np.int16)), b.column(2).take(pa.array(r)), b.column(0).take(pa.array(r)), pa.array(flags[r]), raw(sig[r])],
                        names=["part", "key", "rep", "block", "new", "word", "kept", "sig"],
                    )

        return run

    def search(group: pa.Table) -> pa.Table:
        found = list(_met(group, repetitions, least, two_sided))
        a, b, w = (np.concatenate(x) for x in zip(*found, strict=True)) if found else (np.zeros(0, np.int64),) * 3
        words, new = group.column("word"), group.column("new").to_numpy()
        if two_sided:
            a, b = np.where(new[a], a, b), np.where(new[a], b, a)
        if best and len(a):
            names = words.combine_chunks().dictionary_encode()
            at = (names.combine_chunks() if isinstance(names, pa.ChunkedArray) else names).indices.to_numpy()[a]
            most = np.zeros(at.max() + 1, dtype=w.dtype)
            np.maximum.at(most, at, w)
            a, b, w = (z[w == most[at]] for z in (a, b, w))
        x, y = words.take(pa.array(a)), words.take(pa.array(b))
        if forest:
            x, y = tied(x, y)
            return pa.table({"src": x, "dst": y})
        if not two_sided:
            x, y = pc.min_element_wise(x, y), pc.max_element_wise(x, y)
        return pa.table({"src": x, "dst": y, "weight": pa.array(w.astype(np.int32))})

    out, written = None, []
    for i in range(passes):
        sent_rows = every.mapInArrow(members(i), "part int, key long, rep short, block short, new boolean, word string, kept long, sig binary")
        one = materialise(sent_rows.groupBy("part").applyInArrow(search, "src string, dst string" + ("" if forest else ", weight int")), "pairs")
        written.append(one)
        out = one if out is None else out.unionByName(one)
    out._passes = written
    return out


def _runs(sig: np.ndarray, node: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Distinct signatures with nodes, in order."""
    order = np.lexsort((node, sig))
    sig, node = sig[order], node[order]
    new = np.ones(len(sig), dtype=bool)
    new[1:] = (sig[1:] != sig[:-1]) | (node[1:] != node[:-1])
    return sig[new], node[new]


def joined(sigs: DataFrame, repetitions: int) -> DataFrame:
    """``node, comp`` for each signature of the first repetition, written to the shared folder: ``comp`` is the least one that its words reach through buckets of any repetition.

    Words of one first signature are one node, so only numbers are on their way.
    Few repetitions join most nodes into one group. The later ones, in passes of
    about ``PASS_BYTES``, see that group as a single node, if the others are not
    too many to be told to all executors.
    """
    spark = sigs.sparkSession
    ship(spark)
    kind = dict(sigs.dtypes)["sig"].removeprefix("array<").removesuffix(">")
    value = np.dtype("<i4" if kind == "int" else "<i8")
    words = sigs.count()
    most, parts = max(1, PASS_BYTES // (max(1, words) * 2 * value.itemsize)), max(4, words // JOINED_ROWS)
    nodes = materialise(sigs.select(F.get("sig", F.lit(0)).alias("node")).distinct().withColumn("comp", F.col("node")), "nodes")
    known, first = None, 1

    def members(first: int, last: int):
        def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            def dealt(held: list[np.ndarray]) -> Iterator[pa.RecordBatch]:
                sig = np.concatenate(held)
                node = sig[:, 0]
                if known is not None:
                    largest, at, comp = known.value
                    i = np.minimum(np.searchsorted(at, node), max(0, len(at) - 1))
                    node = np.where(at[i] == node, comp[i], largest) if len(at) else np.full(len(node), largest, dtype=value)
                for r in range(first, last):
                    s, n = _runs(sig[:, r], node)
                    part = ((s.astype(np.uint64) * np.uint64(0x9E3779B97F4A7C15)) >> np.uint64(33)).astype(np.int64) % parts
                    order = np.argsort(part, kind="stable")
                    some, start = np.unique(part[order], return_index=True)
                    cuts = [(order[i:j]) for i, j in zip(start.tolist(), [*start[1:].tolist(), len(order)], strict=True)]
                    raw = lambda x: pa.array([x[c].astype(value).tobytes() for c in cuts], pa.binary())  # noqa: B023, E731
                    yield pa.RecordBatch.from_arrays([pa.array((some + r * parts).astype(np.int64)), raw(s), raw(n)], names=["part", "sig", "node"])

            held, rows = [], 0
            for b in batches:
                held.append(_matrix(b.column(0), repetitions))
                rows += b.num_rows
                if rows >= 200_000:
                    yield from dealt(held)
                    held, rows = [], 0
            if rows:
                yield from dealt(held)

        return run

    def search(group: pa.Table) -> pa.Table:
        sig, node = _runs(*(np.frombuffer(b"".join(group.column(c).to_pylist()), value) for c in ("sig", "node")))
        same = np.flatnonzero(sig[1:] == sig[:-1])
        every, at = np.unique(np.concatenate([node[same], node[same + 1]]), return_inverse=True)
        up = roots(at[: len(same)], at[len(same) :], len(every))
        moved = np.flatnonzero(up != np.arange(len(up)))
        return pa.table({"src": every[moved], "dst": every[up[moved]]})

    while first < repetitions:
        last = min(repetitions, first + min(most, FIRST if first == 1 else repetitions))
        links = materialise(sigs.select("sig").mapInArrow(members(first, last), "part long, sig binary, node binary").groupBy("part").applyInArrow(search, f"src {kind}, dst {kind}"), "links")
        groups = star_components(links.unionByName(nodes.where("node != comp").select(F.col("node").alias("src"), F.col("comp").alias("dst"))))
        done, nodes = nodes, materialise(nodes.select("node").join(groups, "node", "left").select("node", F.coalesce("comp", "node").alias("comp")), "nodes")
        for x in (done, links, groups):
            discard(x)
        if known is not None:
            known.destroy()
        known, first = None, last
        largest = nodes.groupBy("comp").count().orderBy(F.desc("count"), "comp").first() if first < repetitions else None
        if largest is not None and nodes.count() - largest["count"] <= BROADCAST_NODES:
            rest = nodes.where(F.col("comp") != largest["comp"]).toArrow()
            at, comp = (rest.column(c).to_numpy() for c in ("node", "comp"))
            order = np.argsort(at)
            known = spark.sparkContext.broadcast((largest["comp"], at[order].astype(value), comp[order].astype(value)))
    return nodes


def stars(sigs: DataFrame, repetitions: int) -> DataFrame:
    """``src, dst, weight`` (weight one) that tie all words that buckets of any repetition join, directly or through others, to the least of them; written to the shared folder."""
    nodes = joined(sigs, repetitions)
    named = materialise(sigs.select("word", F.get("sig", F.lit(0)).alias("node")).join(nodes, "node").select("word", "comp"), "groups")
    discard(nodes)
    hubs = named.groupBy("comp").agg(F.min("word").alias("hub"), F.max("word").alias("last")).where("hub < last").drop("last")
    if hubs.count() <= BROADCAST_NODES // 4:
        hubs = F.broadcast(hubs)
    out = materialise(named.join(hubs, "comp").where("word != hub").select(F.col("hub").alias("src"), F.col("word").alias("dst"), F.lit(1).alias("weight")), "edges")
    discard(named)
    out._passes = [out]
    return out


def forget(found: DataFrame) -> None:
    """Delete what :func:`pairs` wrote for ``found``, which nothing reads any more."""
    for one in getattr(found, "_passes", ()):
        discard(one)


def thinned(edges: DataFrame) -> DataFrame:
    """``src, dst`` of links that join the same words as ``edges``: a partition keeps one link less than it has words, at most."""
    ship(edges.sparkSession)
    kind = dict(edges.dtypes)["src"]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        src, dst, held = [], [], 0

        def out() -> tuple[pa.Array, pa.Array]:
            return tied(pa.chunked_array(src), pa.chunked_array(dst))

        for b in batches:
            src.append(b.column(0))
            dst.append(b.column(1))
            held += b.num_rows
            if held > 4_000_000:
                x, y = out()
                src, dst, held = [x], [y], 0
                if len(x) > 2_000_000:
                    yield pa.RecordBatch.from_arrays([x, y], names=["src", "dst"])
                    src, dst = [], []
        if src:
            yield pa.RecordBatch.from_arrays([*out()], names=["src", "dst"])

    return edges.select("src", "dst").where("src is not null and dst is not null").mapInArrow(run, f"src {kind}, dst {kind}")
