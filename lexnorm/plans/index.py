"""The index: from word counts to the normalization vocabulary, stored and restored."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from lexnorm.config import HashParams
from lexnorm.functions import hashing
from lexnorm.operators import graph, infer, matching, vocabulary
from lexnorm.operators.components import components
from lexnorm.sources.store import discard, materialise

#: Share of the vocabulary in one component from which an index reports chaining.
CHAINED_SHARE = 0.25


@dataclass
class Index:
    """Tables of an index. Edges and groups are made when first asked for; groups need no table of edges."""

    params: HashParams
    vocab: DataFrame  # word, freq
    sigs: DataFrame  # word, sig
    made_edges: DataFrame | None = None
    made_norm: DataFrame | None = None
    strategy: str | None = None
    method: str = "star"
    verify_jaccard: float | None = None
    made_links: DataFrame | None = None

    @property
    def edges(self) -> DataFrame:
        """``src, dst, weight``"""
        if self.made_edges is None:
            p = self.params
            found = weighed = graph.edge_weights(self.sigs, p.repetitions, p.index_min, self.strategy or graph.strategy_for(p.index_min, p.repetitions))
            if self.verify_jaccard is not None:
                found = graph.verified(found, p.char_lens, self.verify_jaccard)
            found = found.select("src", "dst", F.col("weight").cast("int").alias("weight"))
            if hasattr(weighed, "_passes") and self.verify_jaccard is None:
                # Pairs are written as they are found: a second copy would double the disk.
                self.made_edges = found
            else:
                self.made_edges = materialise(found, "edges")
                matching.forget(weighed)
        return self.made_edges

    @property
    def links(self) -> DataFrame:
        """``src, dst`` of links that join the same words as the edges, fewer of them where they can be."""
        if self.made_links is None:
            p = self.params
            if self.made_edges is None and self.verify_jaccard is None and (self.strategy or graph.strategy_for(p.index_min, p.repetitions)) == "prefix":
                found = matching.pairs(self.sigs, p.repetitions, p.index_min, forest=True)
            else:
                found = self.edges
            self.made_links = materialise(matching.thinned(found), "links")
            if found is not self.made_edges:
                matching.forget(found)
        return self.made_links

    @property
    def norm(self) -> DataFrame:
        """``word, freq, comp, rep_word, rep_freq, size``"""
        if self.made_norm is None:
            links = self.links
            groups = components(links, method=self.method)
            self.made_norm = materialise(vocabulary.build(self.vocab, groups), "norm")
            # Groups say what the links said.
            self.made_links = self.made_norm.where("word != comp").select(F.col("comp").alias("src"), F.col("word").alias("dst"))
            for done in (links, groups):
                if hasattr(done, "_written_at"):
                    discard(done)
        return self.made_norm

    @property
    def family(self) -> hashing.Family:
        return hashing.Family.draw(self.params)

    def save(self, path: str) -> None:
        """Write all tables and the parameters; signatures are laid out by word."""
        for name in ("vocab", "sigs", "edges", "norm"):
            getattr(self, name).write.mode("overwrite").parquet(f"{path}/{name}")
        self.vocab.sparkSession.createDataFrame([(self.params.to_json(),)], "params string").coalesce(1).write.mode("overwrite").text(f"{path}/params")

    @staticmethod
    def load(spark: SparkSession, path: str) -> Index:
        params = HashParams.from_json(spark.read.text(f"{path}/params").first()[0])
        return Index(params, *(spark.read.parquet(f"{path}/{n}") for n in ("vocab", "sigs", "edges", "norm")))

    def stats(self) -> DataFrame:
        """Internal counters as rows ``counter, value``."""
        spark = self.vocab.sparkSession
        from lexnorm.operators import buckets

        b = buckets.profiles(self.sigs, self.params.repetitions).agg(F.coalesce(F.sum("buckets"), F.lit(0)).alias("buckets"), F.max("largest").alias("largest_bucket"), F.sum("pairs").alias("pairs"))
        n = self.norm.agg(F.count("*").alias("words"), F.countDistinct("comp").alias("components"), F.max("size").alias("largest_component"))
        e = self.edges.agg(F.count("*").alias("edges"))
        s = self.sigs.agg(F.count("*").alias("hashed_words"))
        row = b.crossJoin(F.broadcast(n)).crossJoin(F.broadcast(e)).crossJoin(F.broadcast(s))
        names = row.columns
        return row.select(F.explode(F.array(*(F.struct(F.lit(c).alias("counter"), F.col(c).cast("long").alias("value")) for c in names))).alias("x")).select("x.*") if spark else row

    def chained(self) -> bool:
        """Whether one component holds over ``CHAINED_SHARE`` of the words."""
        largest, words = self.norm.agg(F.max("size"), F.count("*")).first()
        return bool(words) and (largest or 0) > CHAINED_SHARE * words

    def extend(self, more: DataFrame) -> Index:
        """Add words (``word, freq``) to the index: only pairs with a new word are looked for.

        Old edges stay; counts of known words add up.
        """
        vocab = materialise(self.vocab.unionByName(more.select("word", "freq")).groupBy("word").agg(F.sum("freq").alias("freq")), "vocab")
        fresh = more.select("word").distinct().join(self.vocab.select("word"), "word", "left_anti")
        new = materialise(hashing.signatures(fresh, self.family), "sigs")
        least = self.params.index_min
        across = infer.collisions(new, self.sigs, self.params.repetitions, least).select(F.least("word", "indexed").alias("src"), F.greatest("word", "indexed").alias("dst"), "weight")
        among = graph.edge_weights(new, self.params.repetitions, least, "pairs" if least <= 1 else "prefix")
        edges = self.edges.unionByName(across).unionByName(among)
        return Index(self.params, vocab, self.sigs.unionByName(new), edges)


def build_index(vocab: DataFrame, params: HashParams = HashParams(), backend: str = "arrow", strategy: str | None = None, method: str = "star", verify_jaccard: float | None = None, split_star: bool = False) -> Index:
    """Index a word list (``word, freq``).

    Words and signatures are written once to the shared folder, edges and groups
    when asked for. With ``verify_jaccard`` edges also need that exact similarity;
    ``split_star`` keeps a word only with its representative's direct neighbours.
    """
    family = hashing.Family.draw(params)
    vocab = materialise(vocab.select("word", F.col("freq").cast("long").alias("freq")), "vocab")
    sigs = materialise(hashing.signatures(vocab, family, backend), "sigs")
    index = Index(params, vocab, sigs, strategy=strategy, method=method, verify_jaccard=verify_jaccard)
    if not split_star:
        return index
    return Index(params, vocab, sigs, materialise(graph.star_split(index.edges, index.norm), "edges"), method=method)
