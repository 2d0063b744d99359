"""Functions and views for SQL users."""

from __future__ import annotations

from collections.abc import Callable, Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from lexnorm.config import HashParams
from lexnorm.functions.hashing import Family, Kernel, grams_of
from lexnorm.functions.tokens import vocabulary
from lexnorm.plans.index import Index
from lexnorm.sources.store import ship, table

#: Word maps of at most so many words travel inside ``lex_normalize``.
MOST_WORDS = 2_000_000


@F.udtf(returnType="gram string, n int")
class WordGrams:
    """``SELECT * FROM lex_grams('word')``: distinct substrings of lengths 1, 3 and 5."""

    def eval(self, word: str) -> Iterator[tuple[str, int]]:
        for g in sorted(grams_of(word or "", (1, 3, 5))):
            yield g, len(g)


@F.udtf(returnType="variant string")
class WordDeletions:
    """``SELECT * FROM lex_deletions('word', 2)``: the word and what up to k deletions leave."""

    def eval(self, word: str, k: int) -> Iterator[tuple[str]]:
        out = layer = {word or ""}
        for _ in range(k):
            layer = {w[:i] + w[i + 1 :] for w in layer for i in range(len(w))}
            out = out | layer
        for w in sorted(out):
            yield (w,)


def register(spark: SparkSession, index: Index | None = None, params: HashParams = HashParams()) -> None:
    """Create ``lex_signature(word)``, ``lex_jaccard(a, b)``, ``lex_grams``, ``lex_deletions``; with an index also
    ``lex_normalize(text)`` and the views ``lex_vocab``, ``lex_map``, ``lex_edges``."""
    ship(spark)
    family = Family.draw(index.params if index else params)

    @F.pandas_udf("array<long>")
    def signature(words: pd.Series) -> pd.Series:
        kernel = Kernel(family)
        out: list = [None] * len(words)
        some, sigs = kernel([w or "" for w in words])
        for i, s in zip(some.tolist(), sigs.tolist(), strict=True):
            out[i] = s
        return pd.Series(out)

    @F.pandas_udf("double")
    def similarity(a: pd.Series, b: pd.Series) -> pd.Series:
        def one(x: str | None, y: str | None) -> float:
            p, q = grams_of(x or "", (1, 3, 5)), grams_of(y or "", (1, 3, 5))
            return len(p & q) / len(p | q) if p or q else 0.0

        return pd.Series([one(x, y) for x, y in zip(a, b)], dtype="float64")

    spark.udf.register("lex_signature", signature)
    spark.udf.register("lex_jaccard", similarity)
    spark.udtf.register("lex_grams", WordGrams)
    spark.udtf.register("lex_deletions", WordDeletions)
    if index is None:
        return
    index.norm.createOrReplaceTempView("lex_vocab")
    changed = index.norm.where("word != rep_word").select("word", "rep_word")
    changed.createOrReplaceTempView("lex_map")
    index.edges.createOrReplaceTempView("lex_edges")
    if changed.count() > MOST_WORDS:
        raise ValueError("the map is too large for a function; use rewrite.apply with its join strategy")
    rows = changed.toArrow()
    mapping = spark.sparkContext.broadcast(dict(zip(rows.column(0).to_pylist(), rows.column(1).to_pylist(), strict=True)))

    @F.pandas_udf("string")
    def normalize(texts: pd.Series) -> pd.Series:
        import re

        word, own = re.compile(r"[^\W_]+"), mapping.value
        return texts.map(lambda t: None if t is None else word.sub(lambda m: own.get(m[0], m[0]), t.lower()))

    spark.udf.register("lex_normalize", normalize)


def udtf_grams(spark: SparkSession, d: str) -> DataFrame:
    """Substrings of the benchmark's words, through the SQL table function."""
    register(spark)
    vocabulary(table(spark, d, "benchmark")).createOrReplaceTempView("lex_words")
    return spark.sql("SELECT word, gram, cast(n as bigint) AS n FROM lex_words, LATERAL lex_grams(word)")


def udtf_deletions(spark: SparkSession, d: str) -> DataFrame:
    register(spark)
    vocabulary(table(spark, d, "benchmark")).createOrReplaceTempView("lex_words")
    return spark.sql("SELECT word, variant FROM lex_words, LATERAL lex_deletions(word, 1)")


def sql_similarity(spark: SparkSession, d: str) -> DataFrame:
    """Each nation's name against its region's, through the SQL function."""
    register(spark)
    for t in ("nation", "region"):
        table(spark, d, t).createOrReplaceTempView(f"lex_{t}")
    return spark.sql("SELECT n_name, r_name, round(lex_jaccard(lower(n_name), lower(r_name)), 8) AS similarity FROM lex_nation JOIN lex_region ON n_regionkey = r_regionkey")


def sql_signatures(spark: SparkSession, d: str) -> DataFrame:
    register(spark)
    vocabulary(table(spark, d, "benchmark")).createOrReplaceTempView("lex_words")
    return spark.sql("SELECT word, array_join(lex_signature(word), ',') AS sig FROM lex_words")


QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {f.__name__: f for f in (udtf_grams, udtf_deletions, sql_similarity, sql_signatures)}


def _oracles() -> dict[str, str]:
    from lexnorm.plans import oracle as sql

    p = HashParams()
    words = f"vocab AS ({sql.vocab('benchmark')})"
    grams = lambda w: sql.gram_list(w, p.char_lens)
    shared = f"len(list_intersect({grams('lower(n_name)')}, {grams('lower(r_name)')}))"
    return {
        "udtf_grams": f"WITH {words} SELECT word, gram, length(gram) AS n FROM (SELECT word, unnest({grams('word')}) AS gram FROM vocab)",
        "udtf_deletions": f"WITH {words} SELECT DISTINCT word, variant FROM (SELECT word, word AS variant FROM vocab UNION ALL SELECT word, unnest([substr(word, 1, i - 1) || substr(word, i + 1) FOR i IN range(1, length(word) + 1)]) FROM vocab)",
        "sql_similarity": f"SELECT n_name, r_name, round({shared} / (len({grams('lower(n_name)')}) + len({grams('lower(r_name)')}) - {shared}), 8) AS similarity FROM nation JOIN region ON n_regionkey = r_regionkey",
        "sql_signatures": f"WITH {words}, {sql.sigs(p)} SELECT word, string_agg(sig, ',' ORDER BY rep) AS sig FROM sigs GROUP BY word",
    }


ORACLES = _oracles()
