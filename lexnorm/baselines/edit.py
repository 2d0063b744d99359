"""Edit-distance baselines: distances, a deletion-neighbourhood index, enumeration, sound codes."""

from __future__ import annotations

import pandas as pd
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

#: Letters an edit may insert or put in place, unless others are given (fixed values).
ALPHABET = "abcdefghijklmnopqrstuvwxyz0123456789"
#: Distinct letters that a dictionary may have for enumeration.
MOST_LETTERS = 4096
#: Rows of a keyboard, for the cost of substituting neighbours (fixed values).
KEY_ROWS = ("1234567890", "qwertyuiop", "asdfghjkl", "zxcvbnm")
NEIGHBOURS = frozenset(
    (a, b)
    for r, row in enumerate(KEY_ROWS)
    for c, a in enumerate(row)
    for rr in (r - 1, r, r + 1)
    if 0 <= rr < len(KEY_ROWS)
    for b in KEY_ROWS[rr][max(0, c - 1) : c + 2]
    if a != b
)
#: Groups of letters that sound alike, for the phonetic cost (fixed values).
SOUND_GROUPS = ("aeiouy", "bp", "ckq", "dt", "fv", "gj", "mn", "sz")


def damerau(a: str, b: str) -> int:
    """Least number of insertions, deletions, substitutions and swaps of neighbours, edits within a swap included."""
    last: dict[str, int] = {}
    top = len(a) + len(b)
    d = [[top] * (len(b) + 2) for _ in range(len(a) + 2)]
    for i in range(len(a) + 1):
        d[i + 1][1] = i
    for j in range(len(b) + 1):
        d[1][j + 1] = j
    for i, x in enumerate(a, 1):
        match = 0
        for j, y in enumerate(b, 1):
            k, m = last.get(y, 0), match
            if x == y:
                match = j
            d[i + 1][j + 1] = min(d[i][j] + (x != y), d[i + 1][j] + 1, d[i][j + 1] + 1, d[k][m] + (i - k - 1) + 1 + (j - m - 1))
        last[x] = i
    return d[-1][-1]


def jaro_winkler(a: str, b: str, scale: float = 0.1, from_: float = 0.7) -> float:
    """Similarity in [0, 1]; a common start of up to four characters raises values above ``from_``."""
    if not a and not b:
        return 1.0
    reach = max(0, max(len(a), len(b)) // 2 - 1)
    taken = [False] * len(b)
    mine = []
    for i, x in enumerate(a):
        for j in range(max(0, i - reach), min(len(b), i + reach + 1)):
            if not taken[j] and b[j] == x:
                taken[j] = True
                mine.append(x)
                break
    m = len(mine)
    if not m:
        return 0.0
    theirs = [y for y, t in zip(b, taken, strict=True) if t]
    swaps = sum(x != y for x, y in zip(mine, theirs, strict=True)) // 2
    sim = (m / len(a) + m / len(b) + (m - swaps) / m) / 3
    if sim <= from_:
        return sim
    start = 0
    for x, y in zip(a[:4], b[:4]):
        if x != y:
            break
        start += 1
    return sim + start * scale * (1 - sim)


def weighted(a: str, b: str, model: str = "keyboard") -> float:
    """Levenshtein distance with substitutions at half cost between keyboard neighbours or similar sounds."""
    if model == "unit":
        cheap = lambda x, y: False
    elif model == "keyboard":
        cheap = lambda x, y: (x, y) in NEIGHBOURS
    elif model == "phonetic":
        cheap = lambda x, y: any(x in g and y in g for g in SOUND_GROUPS)
    else:
        raise ValueError(model)
    row = list(map(float, range(len(b) + 1)))
    for i, x in enumerate(a, 1):
        above, row = row, [float(i)]
        for j, y in enumerate(b, 1):
            row.append(min(above[j] + 1, row[-1] + 1, above[j - 1] + (0.0 if x == y else 0.5 if cheap(x, y) else 1.0)))
    return row[-1]


def distance(a: Column, b: Column, kind: str = "lev") -> Column:
    """``lev`` built in; ``dl``, ``jw`` (a similarity), ``keyboard`` and ``phonetic`` in Arrow batches. Null if either is."""
    if kind == "lev":
        return F.levenshtein(a, b)
    pair = {"dl": damerau, "jw": jaro_winkler, "keyboard": lambda x, y: weighted(x, y, "keyboard"), "phonetic": lambda x, y: weighted(x, y, "phonetic")}[kind]

    @F.pandas_udf("double")
    def run(x: pd.Series, y: pd.Series) -> pd.Series:
        return pd.Series([None if p is None or q is None else float(pair(p, q)) for p, q in zip(x, y)], dtype="float64")

    return run(a, b)


def deletions(word: Column, k: int) -> Column:
    """The word and all strings left by up to ``k`` deletions, each once."""
    out = F.array(word)
    layer = out
    for _ in range(k):
        one = lambda w: F.when(F.length(w) > 0, F.transform(F.sequence(F.lit(1), F.length(w)), lambda i: F.concat(F.substring(w, F.lit(1), i - 1), F.substring(w, i + 1, F.length(w))))).otherwise(F.array().cast("array<string>"))
        layer = F.array_distinct(F.flatten(F.transform(layer, one)))
        out = F.array_union(out, layer)
    return out


def _best(asked: DataFrame, pairs: DataFrame) -> DataFrame:
    """Least distance, then highest score, then least word; a word without candidates stays."""
    pick = pairs.groupBy("word").agg(F.min(F.struct("distance", (-F.col("score")).alias("s"), F.col("candidate").alias("c"))).alias("b"))
    return asked.join(pick, "word", "left").select("word", F.coalesce("b.c", "word").alias("corrected"), F.col("b.distance").alias("distance"))


def _known(words: DataFrame, dictionary: DataFrame) -> tuple[DataFrame, DataFrame]:
    asked = words.select("word").where("word is not null").distinct()
    known = asked.join(dictionary.select("word"), "word", "left_semi").select("word", F.col("word").alias("corrected"), F.lit(0).alias("distance"))
    return known, asked.join(dictionary.select("word"), "word", "left_anti")


def deletion_index(words: DataFrame, dictionary: DataFrame, k: int = 2, kind: str = "lev") -> DataFrame:
    """First baseline: ``word, corrected, distance``, by meeting in common deletions of word and dictionary word.

    Words within ``k`` edits share a string left by at most ``k`` deletions of
    each, so an equi-join finds all of them; the distance is verified.
    """
    known, asked = _known(words, dictionary)
    left = asked.select("word", F.explode(deletions(F.col("word"), k)).alias("key"))
    right = dictionary.select(F.col("word").alias("candidate"), "score", F.explode(deletions(F.col("word"), k)).alias("key"))
    near = left.join(right, "key").where(F.abs(F.length("word") - F.length("candidate")) <= k).select("word", "candidate", "score").distinct()
    pairs = near.withColumn("distance", distance(F.col("word"), F.col("candidate"), kind).cast("int")).where(F.col("distance") <= k)
    return known.unionByName(_best(asked, pairs))


def edits(word: Column, alphabet: str = ALPHABET) -> Column:
    """All strings one deletion, swap, substitution or insertion away, and the word itself."""
    n = F.length(word)
    letters = F.array(*map(F.lit, alphabet))
    head = lambda i: F.substring(word, F.lit(1), i)
    tail = lambda i: F.substring(word, i + 1, n)
    at = lambda lo, hi: F.when(hi >= lo, F.sequence(lo, hi)).otherwise(F.array().cast("array<int>"))
    drop = F.transform(at(F.lit(1), n), lambda i: F.concat(head(i - 1), tail(i)))
    swap = F.transform(at(F.lit(1), n - 1), lambda i: F.concat(head(i - 1), F.substring(word, i + 1, F.lit(1)), F.substring(word, i, F.lit(1)), tail(i + 1)))
    put = F.flatten(F.transform(at(F.lit(1), n), lambda i: F.transform(letters, lambda c: F.concat(head(i - 1), c, tail(i)))))
    add = F.flatten(F.transform(at(F.lit(0), n), lambda i: F.transform(letters, lambda c: F.concat(head(i), c, tail(i)))))
    return F.array_distinct(F.concat(F.array(word), drop, swap, put, add))


def letters_of(dictionary: DataFrame) -> str:
    """All characters of a dictionary's words, in order: at most ``MOST_LETTERS``."""
    rows = dictionary.select(F.explode(F.split("word", "")).alias("c")).where("c != ''").distinct().orderBy("c").limit(MOST_LETTERS + 1).collect()
    if len(rows) > MOST_LETTERS:
        raise ValueError(f"the dictionary has over {MOST_LETTERS} letters: give an alphabet")
    return "".join(r.c for r in rows)


def _one_edit(asked: DataFrame, dictionary: DataFrame, alphabet: str | None) -> DataFrame:
    """``word, candidate, score, distance`` of the dictionary words that :func:`edits` lists for a word, with all letters tried at a place at once.

    A dictionary word is looked up under itself and under each place with the letter there left out, which
    stands for any letter put in or in place. Without an alphabet every letter is tried.
    """
    n = F.length("word")
    cut = lambda w, i: F.concat(F.substring(w, F.lit(1), i - 1), F.substring(w, i + 1, F.length(w)))
    places = lambda w, hi: F.when(hi >= 1, F.sequence(F.lit(1), hi)).otherwise(F.array().cast("array<int>"))
    swapped = lambda w, i: F.concat(F.substring(w, F.lit(1), i - 1), F.substring(w, i + 1, F.lit(1)), F.substring(w, i, F.lit(1)), F.substring(w, i + 2, F.length(w)))
    word = F.col("word")
    key = lambda text, place, whole: F.struct(text.alias("key"), place.alias("place"), F.lit(whole).alias("whole"))
    left_out = F.transform(places(word, n), lambda i: key(cut(word, i), i, False))
    # Place 0: put in anywhere.
    mine = F.concat(
        left_out,
        F.array(key(word, F.lit(0), False)),
        F.transform(places(word, n), lambda i: key(cut(word, i), F.lit(0), True)),
        F.transform(places(word, n - 1), lambda i: key(swapped(word, i), F.lit(0), True)),
    )
    theirs = F.concat(left_out, F.array(key(word, F.lit(0), True)))
    flat = lambda frame, keys, *more: frame.select("word", *more, F.explode(F.array_distinct(keys)).alias("k")).select("word", *more, "k.*")
    near = flat(asked, mine).join(flat(dictionary.select("word", "score"), theirs, "score").select(F.col("word").alias("candidate"), "score", "key", F.col("place").alias("at"), "whole"), ["key", "whole"])
    near = near.where("whole or place = 0 or place = at")
    if alphabet is not None:
        put = F.when(F.col("at") > 0, F.substring("candidate", F.col("at"), F.lit(1)))
        near = near.where(F.col("whole") | F.lit(alphabet).contains(put))
    return near.select("word", "candidate", "score", F.lit(1).alias("distance"))


def enumerate_edits(words: DataFrame, dictionary: DataFrame, k: int = 2, alphabet: str | None = None) -> DataFrame:
    """Second baseline: ``word, corrected, distance``; a known word wins, then one edit, then two, then the highest score.

    One edit: the word's neighbours are looked up. Two: every edit can be undone
    by one, so two words two edits apart share a neighbour of both; enumerating
    one step on either side replaces the square of the alphabet by a join.
    Exact if the alphabet holds all letters of the dictionary, as it does unless another is given.
    For two edits those of the words are added.
    """
    known, asked = _known(words, dictionary)
    if k < 2:
        return known.unionByName(_best(asked, _one_edit(asked, dictionary, alphabet)))
    if alphabet is None:
        alphabet = letters_of(dictionary.select("word").unionByName(words.select("word").where("word is not null")))
    near = asked.select("word", F.explode(edits(F.col("word"), alphabet)).alias("key"))
    one = near.join(dictionary.select(F.col("word").alias("key"), "score"), "key").select("word", F.col("key").alias("candidate"), "score", F.lit(1).alias("distance"))
    far = near.join(one.select("word").distinct(), "word", "left_anti")
    lengths = far.agg(F.min(F.length("word")), F.max(F.length("word"))).first()
    around = dictionary.where(F.length("word").between((lengths[0] or 0) - 2, (lengths[1] or 0) + 2))
    theirs = around.select(F.col("word").alias("candidate"), "score", F.explode(edits(F.col("word"), alphabet)).alias("key"))
    two = far.join(theirs, "key").select("word", "candidate", "score").distinct().withColumn("distance", F.lit(2))
    return known.unionByName(_best(asked, one.unionByName(two)))


def phonetic(words: DataFrame, dictionary: DataFrame, k: int = 2) -> DataFrame:
    """Dictionary words of the same sound code within ``k`` edits, best score first."""
    known, asked = _known(words, dictionary)
    left = asked.withColumn("code", F.soundex("word"))
    right = dictionary.select(F.col("word").alias("candidate"), "score", F.soundex("word").alias("code"))
    pairs = left.join(right, "code").where(F.abs(F.length("word") - F.length("candidate")) <= k).withColumn("distance", F.levenshtein("word", "candidate")).where(F.col("distance") <= k)
    return known.unionByName(_best(asked, pairs.select("word", "candidate", "score", "distance")))


def identity(words: DataFrame) -> DataFrame:
    """The control: every word stays."""
    return words.select("word").distinct().select("word", F.col("word").alias("corrected"))
