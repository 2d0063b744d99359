"""Substring de-duplication over a sparse suffix array.

Of all suffixes only those at minimiser positions are kept: of every run of
``size`` words, the one whose first ``gram`` words have the smallest hash. Two
documents that share ``size`` words keep the suffix at the same place of the
shared part. The kept suffixes are ordered by their first ``gram`` words;
neighbours that agree there, from different documents, are matches to extend. A
match of ``size`` words reaches ``l`` words to the left of the suffix and the
rest to its right, for some ``l``: for each ``l`` the extended suffixes are
ordered and neighbours compared again, so every match of ``size`` words is found
and a longer one is the union of these.

Order and comparison run as aggregation over hashes of the words: a class of equal
prefixes needs just its smallest document, and partial aggregation bounds what a
passage that many documents share sends to one task. Equal hashes of prefixes only
nominate matches; the extended ones are compared by BLAKE2b of their words.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from lexnorm.llm.windows import BROADCAST_ROWS, GRAM, SIZE, extend, first_seen, keyed, later_copies, remove_covered, retained, without
from lexnorm.llm.words import carried, restored
from lexnorm.sources.store import materialise, ship


def shared_prefixes(suffixes: DataFrame) -> DataFrame:
    """Prefixes that suffixes of two documents or more have."""
    return suffixes.groupBy("prefix").agg(F.min("doc_id").alias("lowest"), F.max("doc_id").alias("highest")).where("lowest < highest").select("prefix")


def remove_repeats(documents: DataFrame, id_col: str = "doc_id", text_col: str = "text", size: int = SIZE, gram: int = GRAM, with_text: bool = True, broadcast_rows: int = BROADCAST_ROWS, carry: tuple[str, ...] = ()) -> DataFrame:
    """Remove every word inside a match of ``size`` words or more with a smaller document.

    Returns ``doc_id, n_words, n_removed, kept_sha256, kept_text`` for each input
    row. Null, empty and short texts keep all their words; a null id is never
    smaller than another and its text is kept whole. Rows that repeat id and text
    get the same result. Columns named in ``carry`` come along, others are ignored;
    an empty table gives an empty result. What a document repeats within itself stays.
    """
    ship(documents.sparkSession)
    extra, kinds = carried(documents, carry)
    docs = keyed(documents, id_col, text_col, extra)
    copies = later_copies(docs)
    compared = without(docs.where("doc_id is not null"), copies)
    prefixes = materialise(shared_prefixes(retained(compared, size, gram)), "prefixes")
    windows = materialise(extend(compared, prefixes, size, gram, broadcast_rows), "windows")
    return restored(remove_covered(docs, first_seen(windows), copies, size, with_text, kinds), carry)
