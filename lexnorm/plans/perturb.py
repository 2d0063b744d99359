"""Synthetic misspellings with draws that depend on keys alone, never on the plan."""

from __future__ import annotations

import hashlib

import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from lexnorm.functions import tokens
from lexnorm.sources.store import ship

LETTERS = "abcdefghijklmnopqrstuvwxyz"
#: Kinds of change: the first two as in the experiments, the others for structured spellings.
OPS = ("delete", "replace", "elongate", "prefix", "accent")
_ACCENTS = ("aeiou", "áéíóú")


def draw(*parts: Column) -> Column:
    """32 bits from the MD5 of the parts."""
    return F.conv(F.substring(F.md5(F.concat_ws("|", *(p.cast("string") for p in parts))), 1, 8), 16, 10).cast("long")


def selected(key: Column, rate: int, seed: int) -> Column:
    """Whether a sentence is perturbed: with ``rate`` percent chance."""
    return draw(F.lit(seed), key, F.lit("s")) % 100 < rate


def _draw(text: str) -> int:
    """:func:`draw` of joined parts."""
    return int.from_bytes(hashlib.md5(text.encode(), usedforsecurity=False).digest()[:4], "big")


def change(word: str, start: str, ops: tuple[str, ...] = ("delete", "replace")) -> str:
    """One change at a drawn character; a word of one letter is never deleted. ``start`` begins the text of all draws."""
    at = _draw(start + "p") % len(word)
    op = ops[_draw(start + "o") % len(ops)]
    if op == "delete" and len(word) > 1:
        return word[:at] + word[at + 1 :]
    if op == "elongate":
        return word + word[-1]
    if op == "accent":
        return word[:at] + word[at].translate(str.maketrans(*_ACCENTS)) + word[at + 1 :]
    letter = LETTERS[_draw(start + "c") % 26]
    return letter + word if op == "prefix" else word[:at] + letter + word[at + 1 :]


def noisy_words(words: Column, key: Column, seed: int, ops: tuple[str, ...]) -> Column:
    """One or two changes in every word of an array; null for null. In Arrow batches, as a word takes up to seven draws."""

    @F.arrow_udf("array<string>")
    def run(lists: pa.Array, keys: pa.Array) -> pa.Array:
        out = []
        for found, k in zip(lists.to_pylist(), keys.to_pylist(), strict=True):
            start = f"{seed}|" if k is None else f"{seed}|{k}|"
            once = None if found is None else [change(w, f"{start}{i}|1|", ops) for i, w in enumerate(found)]
            out.append(None if once is None else [change(w, f"{start}{i}|2|", ops) if _draw(f"{start}{i}|n") % 2 else w for i, w in enumerate(once)])
        return pa.array(out, pa.list_(pa.string()))

    return run(words, key.cast("string"))


def noise(df: DataFrame, id_col: str, text_col: str, rate: int, seed: int = 13, ops: tuple[str, ...] = ("delete", "replace")) -> DataFrame:
    """``id, clean, noisy, selected, clean_words, noisy_words``; texts are lower-cased, gaps between words stay.

    A null text counts as empty; rows without a change have ``noisy`` equal to ``clean``.
    """
    cut = df.select(F.col(id_col).alias("id"), F.lower(F.coalesce(F.col(text_col), F.lit(""))).alias("clean")).select("id", "clean", tokens.split_lossless(F.col("clean"), lower=False).alias("s"), selected(F.col("id"), rate, seed).alias("selected"))
    ship(df.sparkSession)
    new = F.coalesce(noisy_words(F.when(F.col("selected"), F.col("s.words")), F.col("id"), seed, ops), F.col("s.words"))
    out = cut.select("id", "clean", "selected", F.col("s.gaps").alias("gaps"), F.col("s.words").alias("clean_words"), new.alias("noisy_words"))
    return out.select("id", "clean", tokens.join_lossless(F.col("gaps"), F.col("noisy_words")).alias("noisy"), "selected", "clean_words", "noisy_words", "gaps")


def aligned(noised: DataFrame) -> DataFrame:
    """``id, pos, clean_word, noisy_word`` of all words."""
    return noised.select("id", F.posexplode(F.arrays_zip("clean_words", "noisy_words")).alias("pos", "w")).select("id", "pos", F.col("w.clean_words").alias("clean_word"), F.col("w.noisy_words").alias("noisy_word"))
