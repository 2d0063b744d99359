"""SimHash near-duplicates found with vantage-point trees.

Fingerprints are compared as distinct values: copies meet in one row before any
search. A vantage-point tree, grown on a bounded sample, cuts Hamming space into
shards. Every fingerprint has one home shard; by the triangle inequality a
partner within ``radius`` of it can only lie in a shard whose boundary is within
``radius``, so it also visits those (of two
sides of a boundary, the outer visits the inner). Inside a shard the search goes on splitting by vantage
points and compares what is left, so all pairs are found, and only a spanning
forest of them is sent on.

Three bits of 64 can't reach all near copies: ``near_copies`` adds candidates that
agree in a band of minima over their runs of words, and counts those pairs only
whose exact similarity is high. What these miss is found without chance: of sets
kept in one order, two that are similar enough share a run among their first ones,
so rows of different groups that share such a run are tried as well. The order has
rare runs first, so that what many texts hold nominates few pairs.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from lexnorm.llm.windows import BROADCAST_ROWS
from lexnorm.llm.words import ROLLING, Words, mix, slices
from lexnorm.operators.components import star_components
from lexnorm.sources.store import discard, materialise, ship

RADIUS = 3
SHINGLE = 3
SEED = 42
#: The tree is grown on so many distinct fingerprints at most; all are searched.
SAMPLE = 32768
SHARD = 4096
#: Shards hold this many times the root of the number of fingerprints, and ``SHARD`` at least: each level of
#: the tree sends about half as many rows again, so depth grows half as fast as with shards of one size.
SHARD_GROWTH = 24
DEEPEST = 12
BLOCK = 1 << 20
#: Runs of words of ``near_copies`` and the exact similarity of their sets from which texts are copies, as a fraction.
COPY_SHINGLE, COPY_SHARE = 5, (4, 5)
#: A pair at that similarity shares one of the bands with probability 1 - (1 - 0.8**5)**24 = 0.9999.
BANDS, BAND_ROWS = 24, 5
#: Runs that more rows share come last in the order, those of an eighth of them before these.
CROWD = 64
#: The table of how many rows share a run has twice as many cells as runs, at most so many (two bits each); fuller cells order runs less well.
MOST_CELLS = 1 << 27
SPAN = 1 << 16
#: Rows of one run that are compared at once, and rows of a group of such buckets.
GRID, GROUP = 1024, 1 << 14
#: Bits of a set's parity: sets differ in at least as many runs as their parities in bits.
PARITY_BITS = 2048
SPREAD = np.uint64(0x9E3779B97F4A7C15)


def _fingerprint(words: list[bytes], shingle: int) -> int:
    if not words:
        return 0
    k = min(shingle, len(words))
    hashed = xxhash.xxh64_intdigest
    if k < shingle:
        values = [hashed(b" ".join(words), SEED)]
    elif shingle == 3:
        values = [hashed(b"%b %b %b" % t, SEED) for t in zip(words, words[1:], words[2:])]
    else:
        values = [hashed(b" ".join(words[i : i + shingle]), SEED) for i in range(len(words) - shingle + 1)]
    ones = np.zeros(64, dtype=np.int64)
    h = np.array(values, dtype="<u8")
    for i in range(0, len(h), 65536):
        ones += np.unpackbits(h[i : i + 65536].view(np.uint8).reshape(-1, 8), axis=1, bitorder="little").sum(axis=0, dtype=np.int64)
    return int(np.packbits(2 * ones > len(h), bitorder="little").view("<u8")[0])


def fingerprints(documents: DataFrame, id_col: str = "doc_id", text_col: str = "text", shingle: int = SHINGLE) -> DataFrame:
    """``doc_id, fp`` for every row: 64 bits as a signed long."""
    ship(documents.sparkSession)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            # bytes.lower() and bytes.split() touch ASCII only.
            fps = [_fingerprint((x.as_py() or b"").lower().split(), shingle) for x in b.column(1)]
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array(np.array(fps, dtype=np.uint64).view(np.int64))], names=["doc_id", "fp"])

    return documents.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).cast("binary").alias("text")).mapInArrow(run, "doc_id long, fp long")


@dataclass
class Node:
    """Inside is at distance ``cut`` or less from ``vantage``; a leaf has a shard number and a grid size."""

    vantage: int = 0
    cut: int = 0
    inside: Node | None = None
    outside: Node | None = None
    shard: int = -1
    grid: int = 1


def grow(sample: np.ndarray, total: int, shard: int = SHARD, radius: int = RADIUS, deepest: int = DEEPEST) -> tuple[Node, int]:
    """A vantage-point tree whose leaves hold about ``shard`` of ``total`` fingerprints; also the number of leaves.

    A part that vantage points can't divide (a dense ball, in which nearly all
    lies within ``radius`` of every boundary) stays one leaf, searched as a grid
    of blocks of bounded size.
    """
    leaves = 0
    weight = total / max(1, len(sample))

    def make(points: np.ndarray, depth: int) -> Node:
        nonlocal leaves
        if len(points) * weight > shard and depth < deepest and len(points) > 16:
            best = None
            for v in points[:: max(1, len(points) // 8)][:8]:
                d = np.bitwise_count(points ^ v)
                cut = int(np.median(d))
                for c in (cut, cut - 1):
                    inner = int((d <= c).sum())
                    if 0 < inner < len(points):
                        cost = inner * int((d <= c + radius).sum()) + (len(points) - inner) * int((d > c - radius).sum())
                        if best is None or cost < best[0]:
                            best = (cost, v, c, d)
            if best and best[0] < 0.92 * len(points) ** 2:
                _, v, c, d = best
                return Node(int(v), c, make(points[d <= c], depth + 1), make(points[d > c], depth + 1))
        leaves += 1
        return Node(shard=leaves - 1, grid=max(1, int(np.ceil(len(points) * weight / (16 * shard)))))

    return make(sample, 0), leaves


def routes(tree: Node, fps: np.ndarray, radius: int = RADIUS) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(row, cell, home) for each shard that each fingerprint belongs to or visits.

    A cell is a shard and a pair of its blocks, packed into one number.
    """
    rows, cells, homes = [], [], []

    def go(node: Node, at: np.ndarray, home: np.ndarray) -> None:
        if not len(at):
            return
        if node.shard < 0:
            d = np.bitwise_count(fps[at] ^ np.uint64(node.vantage)).astype(np.int16)
            near, far = d <= node.cut + radius, d > node.cut - radius
            inner = d <= node.cut
            go(node.inside, at[near], home[near] & inner[near])
            # Of two shards the pair is looked for in the inner one: a home row inside doesn't visit the outside.
            far &= ~(inner & home)
            go(node.outside, at[far], home[far])
            return
        block = (fps[at] % np.uint64(node.grid)).astype(np.int64)
        for other in range(node.grid):
            rows.append(at)
            cells.append((node.shard << 40) | (np.minimum(block, other) << 20) | np.maximum(block, other))
            homes.append(home)

    go(tree, np.arange(len(fps)), np.ones(len(fps), dtype=bool))
    if not rows:
        return np.zeros(0, np.int64), np.zeros(0, np.int64), np.zeros(0, bool)
    return np.concatenate(rows), np.concatenate(cells), np.concatenate(homes)


def close(queries: np.ndarray, pool: np.ndarray, radius: int = RADIUS, leaf: int = 64) -> Iterator[tuple[np.ndarray, np.ndarray, np.ndarray]]:
    """For blocks of queries: their indices, pool indices and the matrix of pairs within ``radius``."""
    todo = [(np.arange(len(queries)), np.arange(len(pool)))]
    while todo:
        q, p = todo.pop()
        if not len(q) or not len(p):
            continue
        if len(q) > leaf:
            v = queries[q[len(q) // 2]]
            dq, dp = np.bitwise_count(queries[q] ^ v).astype(np.int16), np.bitwise_count(pool[p] ^ v).astype(np.int16)
            cut = int(np.median(dq))
            cut -= bool((dq <= cut).all())
            inner = dq <= cut
            if inner.any() and ((dp <= cut + radius).sum() * inner.sum() + (dp > cut - radius).sum() * (~inner).sum()) < 0.95 * len(q) * len(p):
                todo += [(q[inner], p[dp <= cut + radius]), (q[~inner], p[dp > cut - radius])]
                continue
        step = max(1, BLOCK // len(p))
        for i in range(0, len(q), step):
            part = q[i : i + step]
            yield part, p, np.bitwise_count(queries[part][:, None] ^ pool[p][None, :]) <= radius


def forest(fps: np.ndarray, home: np.ndarray, radius: int = RADIUS) -> list[tuple[int, int]]:
    """Index pairs that join what links within one shard: at most one for each fingerprint."""
    parent = np.arange(len(fps))

    def root(x: int) -> int:
        while parent[x] != x:
            parent[x] = x = parent[parent[x]]
        return x

    at_home = np.flatnonzero(home)
    for q, p, near in close(fps[at_home], fps, radius):
        for i in np.flatnonzero(near.sum(axis=1) > 1):
            mine = p[near[i]]
            tops = {root(int(x)) for x in np.unique(parent[mine])}
            tops.add(root(int(at_home[q[i]])))
            low = min(tops)
            for t in tops:
                parent[t] = low
            parent[mine] = low
    out = []
    for x in range(len(fps)):
        r = root(x)
        if r != x:
            out.append((x, r))
    return out


def links(distinct: DataFrame, radius: int = RADIUS, sample: int = SAMPLE, shard: int = SHARD) -> DataFrame:
    """Edges ``src, dst`` (ids of ``doc_id, fp`` rows with distinct fp) that connect what lies within ``radius``."""
    spark = distinct.sparkSession
    ship(spark)
    total = distinct.count()
    taken = distinct.select("fp").orderBy(F.xxhash64("fp")).limit(sample)
    shard = max(shard, int(SHARD_GROWTH * total**0.5))
    tree, _ = grow(np.array([r[0] for r in taken.collect()], dtype=np.int64).view(np.uint64), total, shard, radius)

    def route(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            fps = b.column(1).to_numpy(zero_copy_only=False)
            rows, cells, home = routes(tree, fps.view(np.uint64), radius)
            take = pa.array(rows)
            for i in range(0, len(rows), 1 << 17):
                part = take.slice(i, 1 << 17)
                yield pa.RecordBatch.from_arrays([pa.array(cells[i : i + (1 << 17)]), b.column(0).take(part), b.column(1).take(part), pa.array(home[i : i + (1 << 17)])], names=["cell", "doc_id", "fp", "home"])

    def search(cell: pa.Table) -> pa.Table:
        ids = cell.column("doc_id").to_numpy()
        pairs = forest(cell.column("fp").to_numpy().view(np.uint64), cell.column("home").to_numpy(), radius)
        a, b = (np.array(x, dtype=np.int64) for x in zip(*pairs, strict=True)) if pairs else (np.zeros(0, np.int64),) * 2
        return pa.table({"src": ids[a], "dst": ids[b]})

    return distinct.select("doc_id", "fp").mapInArrow(route, "cell long, doc_id long, fp long, home boolean").groupBy("cell").applyInArrow(search, "src long, dst long")


def near_duplicates(documents: DataFrame, id_col: str = "doc_id", text_col: str = "text", radius: int = RADIUS, shingle: int = SHINGLE) -> DataFrame:
    """``doc_id, fingerprint, component_id`` for every row.

    Null and empty texts have fingerprint zero and link to each other like any
    others. Rows with a null id get their fingerprint and a null component, and
    link nothing. Repeated rows are kept. Other columns are ignored; an empty
    table gives an empty result.
    """
    prints = materialise(fingerprints(documents, id_col, text_col, shingle), "prints")
    distinct = materialise(prints.where("doc_id is not null").groupBy("fp").agg(F.min("doc_id").alias("doc_id")).select("doc_id", "fp"), "distinct")
    comps = star_components(links(distinct, radius))
    named = materialise(distinct.join(comps, distinct.doc_id == comps.node, "left").select("fp", F.coalesce("comp", "doc_id").alias("component_id")), "named")
    out = prints.join(named, "fp", "left")
    return out.select("doc_id", F.lower(F.lpad(F.hex("fp"), 16, "0")).alias("fingerprint"), F.when(F.col("doc_id").isNotNull(), F.col("component_id")).alias("component_id"))


def _run_sets(texts: list[bytes], shingle: int) -> list[np.ndarray]:
    """The distinct hashed runs of words of each text, sorted; a shorter text is one run."""
    w = Words(pa.array([x.lower() for x in texts], pa.binary()))
    h = w.hashes()
    g = ROLLING[0](h, shingle)
    out = []
    for at, n in zip(w.first.tolist(), w.counts.tolist(), strict=False):
        if 0 < n < shingle:
            out.append(np.array([xxhash.xxh64_intdigest(h[at : at + n].tobytes(), SEED)], dtype=np.uint64))
        else:
            out.append(np.unique(g[at : at + max(0, n - shingle + 1)]).astype(np.uint64))
    return out


def _bands(sets: list[np.ndarray]) -> np.ndarray:
    """A row of ``BANDS`` hashes for each non-empty set."""
    flat = np.concatenate(sets)
    starts = np.cumsum([0] + [len(x) for x in sets[:-1]])
    rng = np.random.default_rng(SEED)
    out = np.empty((len(sets), BANDS), dtype=np.uint64)
    for b in range(BANDS):
        held = np.full(len(sets), b + 1, dtype=np.uint64)
        for _ in range(BAND_ROWS):
            add, times = rng.integers(0, 1 << 63, 2, dtype=np.uint64)
            low = np.minimum.reduceat((flat ^ add) * (times | np.uint64(1)), starts)
            held = mix(held ^ low)
        out[:, b] = held
    return out


def _levels(table: np.ndarray, runs: np.ndarray) -> np.ndarray:
    """How crowded each run is: zero (one row at most holds it) to three."""
    at = _cell(runs, 4 * len(table))
    return (table[at >> 2] >> (2 * (at & 3)).astype(np.uint8)) & 3


def _cell(runs: np.ndarray, cells: int) -> np.ndarray:
    return ((runs * SPREAD) >> np.uint64(64 - cells.bit_length() + 1)).astype(np.int64)


def _first(runs: np.ndarray, table: np.ndarray) -> np.ndarray:
    """The first runs of a sorted set, the least crowded ones first, without those that no other row holds: similar sets share one of them."""
    top, bottom = COPY_SHARE
    levels = _levels(table, runs)
    first = np.argsort(levels, kind="stable")[: len(runs) + top * len(runs) // -bottom + 1]
    return runs[first[levels[first] > 0]]


def _parities(sets: list[np.ndarray]) -> np.ndarray:
    """A row of ``PARITY_BITS`` bits, as bytes, for each set."""
    rows = np.repeat(np.arange(len(sets)), [len(x) for x in sets])
    bits = (np.concatenate([np.zeros(0, np.uint64), *sets]) * SPREAD) >> np.uint64(65 - PARITY_BITS.bit_length())
    odd = np.bincount(rows * PARITY_BITS + bits.astype(np.int64), minlength=len(sets) * PARITY_BITS) & 1
    return np.packbits(odd.astype(np.uint8)).reshape(len(sets), PARITY_BITS // 8)


def marked(documents: DataFrame, shingle: int = COPY_SHINGLE) -> DataFrame:
    """``doc_id, fp, same, bands, n, parity`` for every row: fingerprint, key, bands, size and parity of the set of runs (no bands for empty texts)."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for whole in batches:
            for b in slices(whole, "text"):
                texts = [x.as_py() or b"" for x in b.column(1)]
                sets = _run_sets(texts, shingle)
                fps = np.array([_fingerprint(t.lower().split(), shingle) for t in texts], dtype=np.uint64).view(np.int64)
                full = [x for x in sets if len(x)]
                bands = iter(_bands(full).view(np.int64).tolist() if full else ())
                rows = [next(bands) if len(x) else [] for x in sets]
                extra = [pa.array([len(x) for x in sets], pa.int64()), pa.array([x.tobytes() for x in _parities(sets)], pa.binary())]
                yield pa.RecordBatch.from_arrays([b.column(0), pa.array(fps), pa.array([xxhash.xxh128_digest(x.tobytes()) for x in sets], pa.binary()), pa.array(rows, pa.list_(pa.int64())), *extra], names=["doc_id", "fp", "same", "bands", "n", "parity"])

    return documents.mapInArrow(run, "doc_id long, fp long, same binary, bands array<long>, n long, parity binary")


def run_sets(documents: DataFrame, shingle: int = COPY_SHINGLE) -> DataFrame:
    """``doc_id, runs`` with the hashed runs of words of each text."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for whole in batches:
            for b in slices(whole, "text"):
                sets = _run_sets([x.as_py() or b"" for x in b.column(1)], shingle)
                yield pa.RecordBatch.from_arrays([b.column(0), pa.array([x.view(np.int64) for x in sets], pa.list_(pa.int64()))], names=["doc_id", "runs"])

    return documents.mapInArrow(run, "doc_id long, runs array<long>")


def _small(frame: DataFrame) -> DataFrame:
    return F.broadcast(frame) if frame.count() <= BROADCAST_ROWS else frame


def _candidates(distinct: DataFrame, radius: int) -> DataFrame:
    """Edges ``src, dst`` to try: each row with its like by fingerprint, and with the least and greatest row of each of its bands."""
    by_print = materialise(distinct.groupBy("fp").agg(F.min("doc_id").alias("doc_id")).select("doc_id", "fp"), "by_print")
    equal = distinct.join(by_print.withColumnRenamed("doc_id", "head"), "fp").select(F.col("doc_id").alias("src"), F.col("head").alias("dst"))
    banded = distinct.select("doc_id", F.explode("bands").alias("band"))
    heads = materialise(banded.groupBy("band").agg(F.min("doc_id").alias("low"), F.max("doc_id").alias("high")).where("low != high"), "heads")
    shared = banded.join(_small(heads), "band").select(F.col("doc_id").alias("src"), F.explode(F.array("low", "high")).alias("dst"))
    pairs = equal.unionByName(links(by_print, radius)).unionByName(shared).where("src != dst")
    return pairs.select(F.least("src", "dst").alias("src"), F.greatest("src", "dst").alias("dst")).distinct()


def _crowds(documents: DataFrame, runs: int, shingle: int) -> np.ndarray:
    """How many of the rows share a run, by cells of runs: four levels, two bits each (zero: one row or none, whatever else shares the cell)."""
    cells = min(MOST_CELLS, max(SPAN, 1 << (2 * max(1, runs) - 1).bit_length()))
    # Cells that many runs share by chance aren't crowded.
    bounds = np.array([1, max(2, CROWD // 8) + 2 * runs // cells, CROWD + 4 * runs // cells])

    def packed(found: list[np.ndarray]) -> Iterator[pa.RecordBatch]:
        at, n = np.unique(np.concatenate(found), return_counts=True)
        n = np.minimum(n, 255).astype(np.uint8)
        spans, first = np.unique(at // SPAN, return_index=True)
        ends = [*first[1:].tolist(), len(at)]
        rows = [((at[i:j] % SPAN).astype("<u2").tobytes(), n[i:j].tobytes()) for i, j in zip(first.tolist(), ends, strict=True)]
        yield pa.RecordBatch.from_arrays([pa.array(spans), pa.array([r[0] for r in rows], pa.binary()), pa.array([r[1] for r in rows], pa.binary())], names=["span", "at", "n"])

    def count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        found, held = [], 0
        for whole in batches:
            for b in slices(whole, "text"):
                found += [_cell(x, cells) for x in _run_sets([x.as_py() or b"" for x in b.column(1)], shingle)]
                held += sum(len(x) for x in found[-b.num_rows :])
                if held > 4_000_000:
                    yield from packed(found)
                    found, held = [], 0
        if held:
            yield from packed(found)

    def add(span: pa.Table) -> pa.Table:
        total = np.zeros(SPAN, dtype=np.int64)
        for at, n in zip(span.column("at"), span.column("n"), strict=True):
            total[np.frombuffer(at.as_py(), "<u2")] += np.frombuffer(n.as_py(), np.uint8)
        level = np.searchsorted(bounds, total).astype(np.uint8).reshape(-1, 4)
        packed = level[:, 0] | level[:, 1] << 2 | level[:, 2] << 4 | level[:, 3] << 6
        return pa.table({"span": span.column("span").slice(0, 1), "levels": pa.array([packed.tobytes()], pa.binary())})

    spans = documents.mapInArrow(count, "span long, at binary, n binary").groupBy("span").applyInArrow(add, "span long, levels binary")
    out = np.zeros(cells // 4, dtype=np.uint8)
    for r in spans.collect():
        out[r.span * SPAN // 4 : (r.span + 1) * SPAN // 4] = np.frombuffer(r.levels, np.uint8)
    return out


def _heads(documents: DataFrame, table, shingle: int) -> DataFrame:
    """``same, heads``: the first runs of each text that has some which other rows may hold."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for whole in batches:
            for b in slices(whole, "text"):
                sets = _run_sets([x.as_py() or b"" for x in b.column(1)], shingle)
                rows = [(xxhash.xxh128_digest(x.tobytes()), y.view(np.int64)) for x in sets if len(y := _first(x, table.value))]
                yield pa.RecordBatch.from_arrays([pa.array([r[0] for r in rows], pa.binary()), pa.array([r[1] for r in rows], pa.list_(pa.int64()))], names=["same", "heads"])

    return documents.mapInArrow(run, "same binary, heads array<long>")


def _mixed(rows: DataFrame) -> DataFrame:
    """``run, rows`` of the first runs that rows of different groups share."""
    held = rows.select("comp", F.explode("heads").alias("run")).groupBy("run").agg(F.count("*").alias("rows"), F.min("comp").alias("low"), F.max("comp").alias("high"))
    return materialise(held.where("low != high").select("run", "rows"), "mixed")


def _near(cells: pa.Table) -> pa.Table:
    """Pairs of rows of one run and cell, of different groups, whose sizes and parities allow the similarity."""
    top, bottom = COPY_SHARE
    run, one, two, block, ids, comp, n = (cells.column(c).to_numpy() for c in ("run", "one", "two", "block", "doc_id", "comp", "n"))
    parity = np.frombuffer(b"".join(cells.column("parity").to_pylist()), dtype=np.uint64).reshape(len(ids), PARITY_BITS // 64)
    order = np.lexsort((two, one, run))
    run, one, two, block, ids, comp, n, parity = (x[order] for x in (run, one, two, block, ids, comp, n, parity))
    new = np.ones(len(run), dtype=bool)
    new[1:] = (run[1:] != run[:-1]) | (one[1:] != one[:-1]) | (two[1:] != two[:-1])
    starts = np.flatnonzero(new)
    end = np.repeat(np.append(starts[1:], len(run)), np.diff(np.append(starts, len(run))))
    # Rows of one block meet in the cell of that block alone.
    apart, at, found, k = one != two, np.arange(len(run)), [], 1
    while len(at := at[at + k < end[at]]):
        i, j = at, at + k
        ok = (comp[i] != comp[j]) & (~apart[i] | (block[i] != block[j])) & (bottom * np.minimum(n[i], n[j]) >= top * np.maximum(n[i], n[j]))
        i, j = i[ok], j[ok]
        ok = (bottom + top) * np.bitwise_count(parity[i] ^ parity[j]).sum(axis=1, dtype=np.int64) <= (bottom - top) * (n[i] + n[j])
        found.append(np.stack([np.minimum(ids[i[ok]], ids[j[ok]]), np.maximum(ids[i[ok]], ids[j[ok]])]))
        k += 1
    pairs = np.unique(np.concatenate(found, axis=1), axis=1) if found else np.zeros((2, 0), np.int64)
    return pa.table({"src": pairs[0], "dst": pairs[1]})


def _missed(docs: DataFrame, distinct: DataFrame, comps: DataFrame, shingle: int) -> DataFrame:
    """Edges ``src, dst`` to try between rows of different groups, with no pair of the wanted similarity left out.

    Any one order of the runs will do: they are ordered by how many rows share them, then
    by hash. Runs of one row only can't be shared and are left out. A crowded run among
    the first is shared by texts that hold little else; its rows are compared block by
    block, whatever their number.
    """
    single = distinct.select("doc_id").distinct()
    copies = materialise(docs.select("doc_id").where("doc_id is not null").distinct().join(single, "doc_id", "left_anti"), "copies")
    texts = docs.where("doc_id is not null").join(_small(copies), "doc_id", "left_anti")
    runs = distinct.agg(F.coalesce(F.sum("n"), F.lit(0))).first()[0]
    table = docs.sparkSession.sparkContext.broadcast(_crowds(texts, runs, shingle))
    heads = materialise(_heads(texts, table, shingle).dropDuplicates(["same"]), "heads")
    table.destroy()
    groups = distinct.select("doc_id", "same", "n", "parity").join(heads, "same").join(_small(comps), F.col("doc_id") == comps.node, "left").select("doc_id", F.coalesce("comp", "doc_id").alias("comp"), "n", "parity", "heads")
    mixed = _mixed(groups)
    total = mixed.agg(F.coalesce(F.sum("rows"), F.lit(0))).first()[0]
    blocks = mixed.select("run", F.ceil(F.col("rows") / GRID).cast("long").alias("blocks"))
    rows = groups.select("doc_id", "comp", "n", "parity", F.explode("heads").alias("run")).join(_small(blocks), "run").withColumn("block", F.pmod(F.xxhash64("doc_id"), F.col("blocks")))
    rows = rows.select("*", F.explode(F.sequence(F.lit(0).cast("long"), F.col("blocks") - 1)).alias("other"))
    rows = rows.select("run", F.least("block", "other").alias("one"), F.greatest("block", "other").alias("two"), "block", "doc_id", "comp", "n", "parity")
    grouped = rows.withColumn("cell", F.pmod(F.xxhash64("run", "one", "two"), F.lit(total // GROUP + 1))).groupBy("cell")
    return grouped.applyInArrow(_near, "src long, dst long").where("src != dst").distinct()


def _wide_parities(documents: DataFrame, shingle: int) -> DataFrame:
    """``doc_id, wide``: parities of as many bits as twice the runs, or more, for each text; a power of two."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for whole in batches:
            for b in slices(whole, "text"):
                wide = []
                for x in _run_sets([x.as_py() or b"" for x in b.column(1)], shingle):
                    power = max(9, (2 * len(x)).bit_length())
                    odd = np.bincount(((x * SPREAD) >> np.uint64(64 - power)).astype(np.int64), minlength=1 << power) & 1
                    wide.append(np.packbits(odd.astype(np.uint8)).tobytes())
                yield pa.RecordBatch.from_arrays([b.column(0), pa.array(wide, pa.binary())], names=["doc_id", "wide"])

    return documents.mapInArrow(run, "doc_id long, wide binary")


def _plausible(tried: DataFrame, docs: DataFrame, distinct: DataFrame, shingle: int) -> DataFrame:
    """Those of the pairs ``src, dst`` that wide parities allow: far less is sent for each pair than its sets."""
    top, bottom = COPY_SHARE
    wanted = materialise(tried.select(F.explode(F.array("src", "dst")).alias("doc_id")).distinct(), "wanted")
    wide = materialise(_wide_parities(docs.join(_small(wanted), "doc_id", "left_semi"), shingle), "wide")
    counts = distinct.groupBy("doc_id").agg(F.max("n").alias("n"))
    wide = wide.join(counts, "doc_id")
    a, b = (wide.select(F.col("doc_id").alias(name), F.col("wide").alias(name + "_wide"), F.col("n").alias(name + "_n")) for name in ("src", "dst"))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            keep = []
            for x, y, n in zip(batch.column(2).to_pylist(), batch.column(3).to_pylist(), batch.column(4).to_pylist(), strict=True):
                x, y = sorted((np.unpackbits(np.frombuffer(z, np.uint8)) for z in (x, y)), key=len)
                y = np.bitwise_xor.reduce(y.reshape(len(x), -1), axis=1)
                keep.append((bottom + top) * int((x ^ y).sum()) <= (bottom - top) * n)
            yield pa.RecordBatch.from_arrays([c.filter(pa.array(keep, pa.bool_())) for c in batch.columns[:2]], names=["src", "dst"])

    both = tried.join(a, "src").join(b, "dst").select("src", "dst", "src_wide", "dst_wide", (F.col("src_n") + F.col("dst_n")).alias("n"))
    return materialise(both.mapInArrow(run, "src long, dst long").distinct(), "plausible")


def _linked(tried: DataFrame, docs: DataFrame, shingle: int) -> DataFrame:
    """Those of the pairs ``src, dst`` whose sets of runs are similar enough, compared exactly."""
    wanted = materialise(tried.select(F.explode(F.array("src", "dst")).alias("doc_id")).distinct(), "wanted")
    sets = materialise(run_sets(docs.join(_small(wanted), "doc_id", "left_semi"), shingle), "sets")
    a, b = (sets.select(F.col("doc_id").alias(name), F.col("runs").alias(name + "_runs")) for name in ("src", "dst"))
    top, bottom = COPY_SHARE
    both, total = F.size(F.array_intersect("src_runs", "dst_runs")), F.size("src_runs") + F.size("dst_runs")
    alike = bottom * F.least(F.size("src_runs"), F.size("dst_runs")) >= top * F.greatest(F.size("src_runs"), F.size("dst_runs"))
    out = materialise(tried.join(a, "src").join(b, "dst").where(F.when(alike, bottom * both >= top * (total - both))).select("src", "dst"), "linked")
    discard(sets)
    return out


def near_copies(documents: DataFrame, id_col: str = "doc_id", text_col: str = "text", radius: int = RADIUS, shingle: int = COPY_SHINGLE) -> DataFrame:
    """``doc_id, component_id`` for every row; linked are texts whose sets of runs of words have a Jaccard similarity of ``COPY_SHARE`` or more.

    Every linked pair is verified exactly and no such pair is left unjoined. A bucket of a
    band tries its rows with two of them, not all pairs, so that groups of any size stay
    linear; pairs that this leaves in different groups are then looked for by the first
    runs of their sets. Null and empty texts are copies of each other. Rows with a null
    id get a null component and link nothing. Repeated rows are kept, other columns are
    ignored.
    """
    ship(documents.sparkSession)
    docs = documents.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).cast("binary").alias("text"))
    marks = materialise(marked(docs, shingle), "marks")
    distinct = materialise(marks.where("doc_id is not null").groupBy("same").agg(F.min("doc_id").alias("doc_id"), F.min("fp").alias("fp"), *(F.first(c).alias(c) for c in ("bands", "n", "parity"))), "distinct")
    marks = marks.select("doc_id", "same")
    linked = _linked(materialise(_candidates(distinct, radius), "tried"), docs, shingle)
    comps = star_components(linked)
    missed = materialise(_missed(docs, distinct, comps, shingle), "missed")
    more = _linked(_plausible(missed, docs, distinct, shingle), docs, shingle)
    if more.limit(1).count():
        comps = star_components(linked.unionByName(more))
    named = materialise(distinct.join(comps, distinct.doc_id == comps.node, "left").select("same", F.coalesce("comp", "doc_id").alias("component_id")), "named")
    discard(distinct)
    return marks.join(named, "same", "left").select("doc_id", F.when(F.col("doc_id").isNotNull(), F.col("component_id")).alias("component_id"))
