"""Rewriting texts with a word map."""

from __future__ import annotations

import re
from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from lexnorm.functions import tokens
from lexnorm.sources.store import ship

#: Maps of at most so many changed words (about 200 MB) go to every executor; larger ones are joined.
BROADCAST_WORDS = 2_000_000


def _narrow(df: DataFrame, id_cols: list[str], text_col: str, mapping: DataFrame, keep_case: bool, protect: str | None, mode: str) -> DataFrame:
    spark = df.sparkSession
    ship(spark)
    rows = mapping.select("word", "rep_word").toArrow()
    shared = spark.sparkContext.broadcast(dict(zip(rows.column(0).to_pylist(), rows.column(1).to_pylist(), strict=True)))
    word = {"word": r"[^\W_]+", "whitespace": r"\S+"}[mode]
    kinds = ", ".join(f"`{c}` {k}" for c, k in df.select(*id_cols).dtypes)
    split = df.select(*id_cols, *([F.col(text_col).alias("_text")] if keep_case or protect else [tokens.split_lossless(F.col(text_col), mode)["gaps"].alias("_gaps"), tokens.split_lossless(F.col(text_col), mode)["words"].alias("_words")]))

    def cased(old: str, new: str) -> str:
        if old.isupper() and len(old) > 1:
            return new.upper()
        return new[:1].upper() + new[1:] if old[:1].isupper() else new

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        own = shared.value
        whole = re.compile(f"({protect})|{word}" if protect else word)
        for b in batches:
            n = len(id_cols)
            texts, changed = [], []
            if keep_case or protect:
                for text in b.column(n).to_pylist():
                    count = 0

                    def swap(m: re.Match) -> str:
                        nonlocal count
                        old = m[0]
                        if protect and m[1] is not None:
                            return old
                        new = own.get(old.lower())
                        if new is None:
                            return old if keep_case else old.lower()
                        count += 1
                        return cased(old, new) if keep_case else new

                    texts.append(whole.sub(swap, text or ""))
                    changed.append(count)
            else:
                for gaps, found in zip(b.column(n).to_pylist(), b.column(n + 1).to_pylist(), strict=True):
                    new = [own.get(w, w) for w in found]
                    changed.append(sum(a != c for a, c in zip(found, new, strict=True)))
                    texts.append("".join(x for pair in zip(gaps, [*new, ""]) for x in pair))
            yield pa.RecordBatch.from_arrays([*b.columns[:n], pa.array(texts, pa.string()), pa.array(changed, pa.int32())], names=[*id_cols, "text", "n_changed"])

    return split.mapInArrow(run, f"{kinds}, text string, n_changed int")


def _joined(df: DataFrame, id_cols: list[str], text_col: str, mapping: DataFrame, mode: str) -> DataFrame:
    """Words are replaced by a join and texts put together again by row."""
    keyed = df.select(F.monotonically_increasing_id().alias("_row"), *id_cols, tokens.split_lossless(F.col(text_col), mode).alias("_s"))
    flat = keyed.select("_row", F.posexplode("_s.words").alias("_pos", "word"))
    new = flat.join(mapping.select("word", "rep_word"), "word")
    swaps = new.groupBy("_row").agg(F.map_from_entries(F.collect_list(F.struct("_pos", "rep_word"))).alias("_new"))
    out = keyed.join(swaps, "_row", "left")
    replaced = F.transform("_s.words", lambda w, i: F.coalesce(F.element_at("_new", i), w))
    text = tokens.join_lossless(F.col("_s.gaps"), F.when(F.col("_new").isNull(), F.col("_s.words")).otherwise(replaced))
    return out.select(*id_cols, text.alias("text"), F.coalesce(F.size("_new"), F.lit(0)).alias("n_changed"))


def apply(df: DataFrame, id_cols: list[str], text_col: str, mapping: DataFrame, strategy: str = "auto", keep_case: bool = False, protect: str | None = None, mode: str = "word") -> DataFrame:
    """``id_cols, text, n_changed``: lower-cased texts with mapped words replaced, all else kept.

    ``mapping`` holds changed words (``word, rep_word``). ``broadcast`` rewrites in
    one pass without moving texts; ``join`` is for maps beyond ``BROADCAST_WORDS``;
    ``auto`` counts the map and chooses. ``keep_case`` gives new words the old
    one's case and leaves other text as it is; ``protect`` is a pattern of
    stretches to leave alone (both with ``broadcast``). A null text becomes empty.
    """
    if strategy == "auto":
        strategy = "broadcast" if mapping.count() <= BROADCAST_WORDS else "join"
    if strategy == "broadcast":
        return _narrow(df, id_cols, text_col, mapping, keep_case, protect, mode)
    if keep_case or protect:
        raise ValueError("keep_case and protect need the broadcast strategy")
    return _joined(df, id_cols, text_col, mapping, mode)
