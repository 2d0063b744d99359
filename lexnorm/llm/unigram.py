"""SentencePiece encoding and decoding with a unigram model.

Pieces with log scores are laid out in a double-array trie over UTF-8 bytes. The
best segmentation is found by Viterbi over the trie, many words at a time: one
NumPy step advances every word of a batch by one byte. A piece that starts with
the space marker starts a word, and no piece holds the marker after another
character, so the best segmentation of a text is that of its words, and each
distinct word is segmented once. Characters that no piece covers fall back to
byte pieces. Decoding joins pieces and byte pieces and turns markers into spaces.
"""

from __future__ import annotations

import re
import zlib
from collections.abc import Iterable, Iterator
from dataclasses import dataclass, replace

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from lexnorm.llm.memo import Memo
from lexnorm.sources.store import ship

MARKER = "▁"
_MARK = MARKER.encode()
#: Log score by which an uncovered character trails the worst piece.
UNKNOWN_PENALTY = 10.0


class DoubleArray:
    """A trie in two arrays: from state ``s`` byte ``c`` leads to ``base[s] + c`` if ``check`` there is ``s``."""

    def __init__(self, keys: list[bytes], values: list[int]):
        children: list[dict[int, int]] = [{}]
        ends = [-1]
        for key, value in zip(keys, values, strict=True):
            at = 0
            for c in key:
                nxt = children[at].get(c)
                if nxt is None:
                    nxt = children[at][c] = len(children)
                    children.append({})
                    ends.append(-1)
                at = nxt
            ends[at] = value
        used = bytearray(b"\x01") + bytearray(2 * len(children) + 1024)
        base, check, value = {}, {}, {}
        first = hint = 1
        todo = [(0, 0)]  # trie node, state
        while todo:
            node, state = todo.pop()
            value[state] = ends[node]
            if not children[node]:
                continue
            codes = sorted(children[node])
            # The first free cell for the lowest code that leaves the others' cells free; parents of
            # many skip a crowded stretch, which parents of one fill later.
            at, tries = used.find(0, max(first if len(codes) == 1 else hint, codes[0] + 1)), 0
            while any(used[at - codes[0] + c] for c in codes):
                at = used.find(0, at + 1)
                tries += 1
            if tries > 32:
                hint = at
            b = at - codes[0]
            base[state] = b
            for c, kid in children[node].items():
                used[b + c] = 1
                check[b + c] = state
                todo.append((kid, b + c))
            first = used.find(0, first)
            if len(used) - b < 2048:
                used.extend(bytes(len(used)))
        size = max(check, default=0) + 257
        self.base, self.check, self.value = (np.full(size, fill, dtype=np.int32) for fill in (size - 257, -1, -1))
        for array, cells in ((self.base, base), (self.check, check), (self.value, value)):
            array[list(cells)] = list(cells.values())
        self.depth = max(map(len, keys), default=0)

    def step(self, states: np.ndarray, codes: np.ndarray) -> np.ndarray:
        """Next states, -1 where there is none; states must be live."""
        to = self.base[states] + codes
        return np.where(self.check[to] == states, to, -1)


@dataclass(frozen=True)
class Pieces:
    """A vocabulary: ``text`` of ordinary pieces by id, their log scores, byte pieces by byte, the unknown id."""

    text: dict[int, str]
    scores: dict[int, float]
    bytes_: dict[int, int]
    unknown: int
    dummy_prefix: bool = True

    @staticmethod
    def load(path: str) -> Pieces:
        import sentencepiece

        model = sentencepiece.SentencePieceProcessor(model_file=path)
        text, scores, by = {}, {}, {}
        for i in range(model.get_piece_size()):
            if model.is_byte(i):
                by[int(model.id_to_piece(i)[3:5], 16)] = i
            elif not (model.is_control(i) or model.is_unknown(i) or model.is_unused(i)):
                text[i], scores[i] = model.id_to_piece(i), model.get_score(i)
        return Pieces(text, scores, by, model.unk_id())

    def with_rank_scores(self) -> Pieces:
        """Log probabilities by rank, for a file whose scores are merge ranks.

        Sums of ranks are no likelihoods: they would favour two frequent pieces
        over the word they spell. Frequency falls about as one over the rank, so
        piece ``r`` gets the log of ``1 / (r + 2.7)``, scaled to sum to one.
        """
        order = sorted(self.scores, key=lambda i: (-self.scores[i], i))
        share = 1 / (np.arange(len(order)) + 2.7)
        return replace(self, scores=dict(zip(order, np.log(share / share.sum()).tolist(), strict=True)))


class Unigram:
    """Encoder and decoder over a vocabulary."""

    def __init__(self, pieces: Pieces, most: int = 150_000):
        usable = {i: t for i, t in pieces.text.items() if t.strip(MARKER).find(MARKER) < 0 and (t.startswith(MARKER) or MARKER not in t)}
        if len(usable) != len(pieces.text):
            raise ValueError("a piece holds the space marker after another character")
        self.pieces = pieces
        self.trie = DoubleArray([t.encode() for t in usable.values()], list(usable))
        top = max([*pieces.text, *pieces.bytes_.values(), pieces.unknown]) + 1
        self.score = np.full(top, -np.inf)
        self.score[list(pieces.scores)] = list(pieces.scores.values())
        self.least = min(pieces.scores.values(), default=0.0) - UNKNOWN_PENALTY
        self.byte_id = np.array([pieces.bytes_.get(b, pieces.unknown) for b in range(256)], dtype=np.int32)
        self.surface = {i: t.encode() for i, t in pieces.text.items()}
        self.surface |= {i: bytes([b]) for b, i in pieces.bytes_.items()}
        self.memo = Memo(self._made, most)

    def segment(self, words: list[bytes]) -> list[np.ndarray]:
        """Ids of each word: Viterbi over all words at once, shorter words first done.

        Of equally good paths the one whose last piece starts first wins, at every end.
        """
        if not words:
            return []
        order = sorted(range(len(words)), key=lambda i: -len(words[i]))
        sizes = np.array([len(words[i]) for i in order])
        n, longest = len(words), int(sizes[0])
        grid = np.zeros((longest + 1, n), dtype=np.uint8)
        flat = np.frombuffer(b"".join(words[i] for i in order), np.uint8)
        row = np.arange(len(flat)) - np.repeat(np.concatenate([[0], np.cumsum(sizes)[:-1]]), sizes)
        grid[row, np.repeat(np.arange(n), sizes)] = flat
        best = np.full((longest + 1, n), -np.inf)
        best[0] = 0
        origin = np.zeros((longest + 1, n), dtype=np.int32)
        used = np.full((longest + 1, n), -1, dtype=np.int32)
        lead = (grid & 0xC0) != 0x80
        width = np.where(grid < 0x80, 1, np.where(grid < 0xE0, 2, np.where(grid < 0xF0, 3, 4)))
        live = np.searchsorted(-sizes, -np.arange(1, longest + 1), side="right")  # words longer than a start
        for start in range(longest):
            cols = np.flatnonzero(lead[start, : live[start]])
            if not len(cols):
                continue
            here = best[start, cols]
            # A character no piece covers: as many byte pieces as it has bytes.
            w = np.minimum(width[start, cols], sizes[cols] - start)
            for k in range(1, 5):
                c = cols[w == k]
                if len(c):
                    self._offer(best, origin, used, start, start + k, c, best[start, c] + self.least, np.full(len(c), -2, np.int32))
            states = np.zeros(len(cols), dtype=np.int64)
            for end in range(start + 1, min(longest, start + self.trie.depth) + 1):
                inside = sizes[cols] >= end
                cols, states, here = cols[inside], states[inside], here[inside]
                to = self.trie.step(states, grid[end - 1, cols])
                on = to >= 0
                cols, states, here = cols[on], to[on], here[on]
                if not len(cols):
                    break
                ids = self.trie.value[states]
                hit = ids >= 0
                self._offer(best, origin, used, start, end, cols[hit], here[hit] + self.score[ids[hit]], ids[hit])
        out: list[np.ndarray] = [None] * n  # type: ignore[list-item]
        for j, i in enumerate(order):
            ids, at = [], int(sizes[j])
            while at:
                k, frm = int(used[at, j]), int(origin[at, j])
                if k == -2:
                    raw = words[i][frm:at]
                    ids += [int(self.byte_id[b]) for b in reversed(raw)] if self.pieces.bytes_ else [self.pieces.unknown]
                else:
                    ids.append(k)
                at = frm
            out[i] = np.array(ids[::-1], dtype="<u4")
        return out

    @staticmethod
    def _offer(best: np.ndarray, origin: np.ndarray, used: np.ndarray, start: int, end: int, cols: np.ndarray, value: np.ndarray, ids: np.ndarray) -> None:
        win = value > best[end, cols]
        c = cols[win]
        best[end, c] = value[win]
        origin[end, c] = start
        used[end, c] = ids[win]

    def words(self, text: str) -> list[bytes]:
        """A text with markers, cut before each run of markers."""
        if not text:
            return []
        marked = (MARKER if self.pieces.dummy_prefix else "") + text.replace(" ", MARKER)
        parts = marked.encode().split(_MARK)
        if b"" not in parts[1:]:
            return [*parts[:1], *map(_MARK.__add__, parts[1:])] if parts[0] else list(map(_MARK.__add__, parts[1:]))
        return [m.encode() for m in re.findall(f"{MARKER}+[^{MARKER}]*|[^{MARKER}]+", marked)]

    def encode(self, texts: list[str]) -> list[np.ndarray]:
        """Ids of each text."""
        return [np.frombuffer(x, dtype="<u4") for x in self.memo.joined([self.words(t) for t in texts])]

    def _made(self, fresh: list[bytes]) -> list[bytes]:
        """Ids of words as bytes; words of like length together, about 4 MB of cells."""
        order = sorted(range(len(fresh)), key=lambda k: len(fresh[k]))
        out: list[bytes] = [b""] * len(fresh)
        i = 0
        while i < len(order):
            j = i + 1
            while j < len(order) and (j - i + 1) * (len(fresh[order[j]]) + 1) <= 250_000:
                j += 1
            for k, ids in zip(order[i:j], self.segment([fresh[k] for k in order[i:j]]), strict=True):
                out[k] = ids.tobytes()
            i = j
        return out

    def decode(self, ids: Iterable[int]) -> str:
        """The text of ids; bytes that form no character become U+FFFD."""
        raw = b"".join([self.surface.get(i, b"") for i in ids])
        text = raw.decode("utf-8", "replace").replace(MARKER, " ")
        return text[1:] if self.pieces.dummy_prefix and text.startswith(" ") else text


_loaded: dict[tuple[str, bool], Unigram] = {}


def loaded(path: str, rank_scores: bool) -> Unigram:
    if (path, rank_scores) not in _loaded:
        pieces = Pieces.load(path)
        _loaded[path, rank_scores] = Unigram(pieces.with_rank_scores() if rank_scores else pieces)
    return _loaded[path, rank_scores]


def encode_documents(documents: DataFrame, model: str, id_col: str = "doc_id", text_col: str = "text", with_ids: bool = True, rank_scores: bool = False) -> DataFrame:
    """``doc_id, n_ids, ids_crc32, decoded, ids`` for every row.

    ``ids_crc32`` is the CRC-32 of the ids as little-endian unsigned 32-bit
    integers; ``rank_scores`` reads the model's scores as ranks; ``decoded`` tells whether decoding gives the text back (a text that
    holds the marker character itself doesn't: it decodes to a space). A null or
    empty text has no ids and decodes to the empty text. Null ids and repeated
    rows are encoded like any other; other columns are ignored.
    """
    ship(documents.sparkSession)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        unigram = loaded(model, rank_scores)
        for whole in batches:
            for i in range(0, whole.num_rows, 512):
                b = whole.slice(i, 512)
                texts = b.column(1).to_pylist()
                ids = unigram.encode(texts)
                sums = [zlib.crc32(x.tobytes()) for x in ids]
                same = [unigram.decode(x.tolist()) == t for x, t in zip(ids, texts, strict=True)]
                flat = pa.ListArray.from_arrays(pa.array(np.concatenate([[0], np.cumsum([len(x) if with_ids else 0 for x in ids])]).astype(np.int32)), pa.array(np.concatenate(ids).astype(np.int32) if with_ids and ids else np.zeros(0, np.int32)))
                yield pa.RecordBatch.from_arrays([b.column(0), pa.array([len(x) for x in ids], pa.int64()), pa.array(sums, pa.int64()), pa.array(same), flat], names=["doc_id", "n_ids", "ids_crc32", "decoded", "ids"])

    rows = documents.select(F.col(id_col).cast("long").alias("doc_id"), F.coalesce(F.col(text_col).cast("string"), F.lit("")).alias("text"))
    return rows.mapInArrow(run, "doc_id long, n_ids long, ids_crc32 long, decoded boolean, ids array<int>")
