"""Connected components of an edge table, without collecting links or groups."""

from __future__ import annotations

from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from lexnorm.sources.store import discard, materialise

#: Edges that one task may join.
TASK_LINKS = 2_000_000


def _state(edges: DataFrame) -> tuple:
    return tuple(edges.agg(F.count("*"), F.expr("bit_xor(xxhash64(u, v))"), F.expr("coalesce(sum(cast(xxhash64(v, u) % 1000003 as bigint)), 0L)")).first())


def _pull(edges: DataFrame, lowest: DataFrame) -> DataFrame:
    """Give each edge the minimum known at its first end.

    ``lowest`` is a written table, so both sides of the join are plain
    exchanges: a hub with many edges is split by AQE's skew join.
    """
    return edges.join(lowest, "u")


def _large_star(edges: DataFrame) -> tuple[DataFrame, DataFrame]:
    """The step's edges, and the written minima they come from."""
    both = edges.unionByName(edges.select(F.col("v").alias("u"), F.col("u").alias("v")))
    lowest = materialise(both.groupBy("u").agg(F.min("v").alias("m")).select("u", F.least("u", "m").alias("m")), "star")
    return _pull(both, lowest).where("v > u").select(F.col("v").alias("u"), F.col("m").alias("v")).distinct(), lowest


def _small_star(edges: DataFrame) -> tuple[DataFrame, DataFrame]:
    lowest = materialise(edges.groupBy("u").agg(F.min("v").alias("m")), "star")
    moved = _pull(edges, lowest).where("v > m").select(F.col("v").alias("u"), F.col("m").alias("v"))
    return moved.unionByName(lowest.select("u", F.col("m").alias("v"))).distinct(), lowest


def star_components(edges: DataFrame, src: str = "src", dst: str = "dst", max_rounds: int = 60) -> DataFrame:
    """``node, comp`` for every node that has an edge; ``comp`` is the smallest node reachable.

    Alternates two contractions: neighbours above a node are tied to the node's
    smallest neighbour, then neighbours below it likewise. Every step keeps the
    components and never adds edges beyond the number it began with. The edge
    set shrinks to one star a component in a logarithmic number of rounds; each
    round is written to the shared folder and the one before deleted. Self-loops, repeated edges and nulls
    are dropped; an empty table gives an empty result.
    """
    pairs = edges.select(F.greatest(src, dst).alias("u"), F.least(src, dst).alias("v")).where(F.col(src).isNotNull() & F.col(dst).isNotNull() & (F.col("u") != F.col("v"))).distinct()
    now = materialise(pairs, "edges")
    before = _state(now)
    for _ in range(max_rounds if before[0] else 0):
        large, low = _large_star(now)
        large = materialise(large, "edges")
        small, lower = _small_star(large)
        last, now = now, materialise(small, "edges")
        for done in (low, lower, large, last):
            discard(done)
        after = _state(now)
        if after == before:
            break
        before = after
    else:
        if before[0]:
            raise RuntimeError(f"components did not settle in {max_rounds} rounds")
    out = now.select(F.col("u").alias("node"), F.col("v").alias("comp")).unionByName(now.select(F.col("v").alias("node"), F.col("v").alias("comp")).distinct())
    out._written_at = now._written_at
    return out


def min_label_components(edges: DataFrame, src: str = "src", dst: str = "dst", max_rounds: int = 200) -> DataFrame:
    """The same result by repeated spreading of the smallest label; rounds follow the diameter."""
    pairs = edges.select(F.col(src).alias("u"), F.col(dst).alias("v")).where("u is not null and v is not null and u != v")
    both = materialise(pairs.unionByName(pairs.select(F.col("v").alias("u"), F.col("u").alias("v"))).distinct(), "edges")
    labels = materialise(both.select(F.col("u").alias("node"), F.col("u").alias("comp")).distinct(), "labels")
    last = labels
    for _ in range(max_rounds):
        heard = both.join(labels.withColumnRenamed("node", "v"), "v").groupBy("u").agg(F.min("comp").alias("heard"))
        after = materialise(labels.join(heard.withColumnRenamed("u", "node"), "node").select("node", F.least("comp", "heard").alias("comp"), (F.col("heard") < F.col("comp")).alias("moved")), "labels")
        discard(last)
        labels, last = after.drop("moved"), after
        if after.where("moved").limit(1).count() == 0:
            discard(both)
            labels._written_at = after._written_at
            return labels
    raise RuntimeError(f"labels did not settle in {max_rounds} rounds")


def driver_components(edges: DataFrame, src: str = "src", dst: str = "dst", limit: int = 2_000_000) -> DataFrame:
    """Union-find on the driver; refuses graphs of more than ``limit`` edges."""
    n = edges.count()
    if n > limit:
        raise ValueError(f"{n} edges are more than the driver limit of {limit}")
    parent: dict = {}

    def root(x):
        while parent.setdefault(x, x) != x:
            parent[x] = x = parent[parent[x]]
        return x

    for a, b in edges.select(src, dst).toLocalIterator():
        if a is None or b is None or a == b:
            continue
        a, b = root(a), root(b)
        parent[max(a, b)] = min(a, b)
    kind = edges.schema[src].dataType.simpleString()
    return edges.sparkSession.createDataFrame([(x, root(x)) for x in list(parent)], f"node {kind}, comp {kind}")


def task_components(edges: DataFrame, src: str = "src", dst: str = "dst", limit: int = TASK_LINKS) -> DataFrame:
    """Union-find in one task for up to ``limit`` edges, star contractions for more: rounds cost more than so few edges."""
    if edges.count() > limit:
        return star_components(edges, src, dst)
    kind = edges.schema[src].dataType.simpleString()

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        parent: dict = {}

        def root(x):
            while parent.setdefault(x, x) != x:
                parent[x] = x = parent[parent[x]]
            return x

        for batch in batches:
            for a, b in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist(), strict=True):
                if a is not None and b is not None and a != b:
                    a, b = root(a), root(b)
                    parent[max(a, b)] = min(a, b)
        nodes = list(parent)
        for i in range(0, len(nodes), 10_000):
            part = nodes[i : i + 10_000]
            yield pa.RecordBatch.from_arrays([pa.array(part, batch.column(0).type), pa.array([root(x) for x in part], batch.column(0).type)], names=["node", "comp"])

    return materialise(edges.select(src, dst).repartition(1).mapInArrow(run, f"node {kind}, comp {kind}"), "components")


METHODS = {"star": star_components, "hash_min": min_label_components, "driver": driver_components, "task": task_components}


def components(edges: DataFrame, vertices: DataFrame | None = None, method: str = "star", **options) -> DataFrame:
    """Label every node; with ``vertices`` (column ``node``), isolated ones label themselves."""
    labelled = METHODS[method](edges, **options)
    if vertices is None:
        return labelled
    return vertices.select("node").distinct().join(labelled, "node", "left").select("node", F.coalesce("comp", "node").alias("comp"))
