"""Licence families of paragraphs by a trained classifier, confirmed by templates.

A multinomial logistic regression over sparse word n-grams is trained in NumPy on
combined wordings of public notices, sentences of licences, notices of licences of
no family, and ordinary sentences. Every sentence of a text is scored; neighbours
that speak of the same family are one paragraph. It gets the family if its
calibrated probability passes a threshold, fitted on leads, names, sentences and
licences that training never saw, and a template of the family agrees; otherwise it
is ``unknown`` (it talks like a licence) or nothing at all.
"""

from __future__ import annotations

import re
from collections.abc import Iterator
from dataclasses import dataclass
from functools import lru_cache

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from lexnorm.llm.html_extract import STOP_WORDS
from lexnorm.llm.license_templates import FILLERS, IDENTIFIERS, LEADS, MIDDLES, NAMES, ORDINARY, SENTENCES, TAILS, UNFAMILIAR
from lexnorm.llm.words import LOWER, mix, slices, span_hashes
from lexnorm.sources.store import ship

#: Combined wordings of each name, and noisy copies of each sentence, that train and calibrate.
COMBINED, COPIES = 40, 60
#: Rows of other words without a notice.
PLAIN = 1200
ROUNDS, RATE = 120, 0.5
SEED = 5
#: Share of word pairs that a paragraph and a licence sentence must share, of the smaller of the two.
AGREEMENT = 0.6
#: Wrong acceptances allowed among calibration paragraphs of no family.
FALSE_SHARE = 0.005
NONE, UNKNOWN = "none", "unknown"
FAMILIES = (NONE, UNKNOWN, *NAMES)
#: Words without which a paragraph is not called an unknown licence.
SPEAKS = re.compile(r"licen[cs]|lizenz|copyright|redistribut")
_IS_WORD = np.zeros(256, dtype=bool)
_IS_WORD[[*range(48, 58), *range(97, 123), *range(128, 256)]] = True
_ORDER = tuple(np.uint64(x) for x in (0x9E3779B97F4A7C15, 0xD6E8FEB86659FD93, 0xA0761D6478BD642F))


@dataclass
class Sentences:
    """Words of a batch of texts in lower case, cut into sentences at line ends and stops."""

    data: np.ndarray
    starts: np.ndarray
    ends: np.ndarray
    owner: np.ndarray  # sentence of each word, numbered through the batch
    text: np.ndarray  # text of each sentence
    line: np.ndarray  # line of each sentence within its text
    grams: np.ndarray  # hashes of runs of one to three words in a sentence
    holder: np.ndarray  # sentence of each run

    @staticmethod
    def of(raws: list[bytes]) -> Sentences:
        blob = b"\n".join(raws) + b"\n"
        data = LOWER[np.frombuffer(blob, dtype=np.uint8)]
        word = _IS_WORD[data]
        before, after = np.zeros_like(word), np.zeros_like(word)
        before[1:], after[:-1] = word[:-1], word[1:]
        word |= (data == 46) & before & after  # "." inside words
        edge = np.diff(np.concatenate([[0], word.view(np.int8), [0]]))
        starts, ends = np.flatnonzero(edge == 1), np.flatnonzero(edge == -1)
        newline = data == 10
        stop = newline.copy()
        blank = newline | (data == 32)
        stop[:-1] |= np.isin(data[:-1], (33, 46, 59, 63)) & blank[1:]  # ! . ; ? before a blank
        stops = np.cumsum(stop)[starts]
        fresh = np.ones(len(starts), dtype=bool)
        fresh[1:] = stops[1:] != stops[:-1]
        owner = np.cumsum(fresh) - 1
        off = np.cumsum([0, *(len(r) + 1 for r in raws)])
        heads = starts[fresh]
        text = np.searchsorted(off, heads, side="right") - 1
        lines = np.cumsum(newline)
        line = lines[heads] - np.where(off[text] > 0, lines[off[text] - 1], 0)
        h = span_hashes(data, starts, ends - starts)
        runs, holder = [mix(h * _ORDER[0])], [owner]
        code = h
        for n in (2, 3):
            if len(h) < n:
                break
            code = mix(code[: len(h) - n + 1] * _ORDER[n - 1] + h[n - 1 :])
            whole = owner[: len(h) - n + 1] == owner[n - 1 :]
            runs.append(code[whole])
            holder.append(owner[: len(h) - n + 1][whole])
        return Sentences(data, starts, ends, owner, text, line, np.concatenate(runs), np.concatenate(holder))

    def words(self, first: int, last: int) -> list[str]:
        """Words of the sentences from ``first`` to ``last``."""
        lo, hi = np.searchsorted(self.owner, [first, last + 1])
        return [self.data[s:e].tobytes().decode("utf-8", "replace") for s, e in zip(self.starts[lo:hi].tolist(), self.ends[lo:hi].tolist())]


def pairs_of(words: list[str]) -> frozenset[tuple[str, str]]:
    return frozenset(zip(words, words[1:]))


@dataclass(frozen=True)
class Scanner:
    """A fitted model: known runs of words (sorted hashes), weights by class, temperature, threshold, and word pairs of sentences."""

    keys: np.ndarray
    weights: np.ndarray
    bias: np.ndarray
    temperature: float
    threshold: float
    pairs: dict[str, tuple[frozenset[tuple[str, str]], ...]]

    def sums(self, s: Sentences) -> tuple[np.ndarray, np.ndarray]:
        """Summed weights, and the number of known runs, of each sentence."""
        n = len(s.text)
        if not len(s.grams):
            return np.zeros((n, len(FAMILIES))), np.zeros(n)
        at = np.minimum(np.searchsorted(self.keys, s.grams), len(self.keys) - 1)
        hit = self.keys[at] == s.grams
        at, holder = at[hit], s.holder[hit]
        return np.stack([np.bincount(holder, w[at], n) for w in self.weights.T], axis=1), np.bincount(holder, minlength=n).astype(float)

    def probabilities(self, sums: np.ndarray, known: np.ndarray) -> np.ndarray:
        return softmax((self.bias + sums / np.sqrt(np.maximum(known, 1))[:, None]) / self.temperature)

    def agreement(self, words: list[str], family: str) -> float:
        """1 if the family is named, else the largest share of word pairs in common with one of its sentences."""
        if re.search(IDENTIFIERS[family], " ".join(words)):
            return 1.0
        mine = pairs_of(words)
        return max((len(mine & t) / max(1, min(len(mine), len(t))) if len(mine & t) >= 2 else 0.0) for t in self.pairs[family])

    def paragraphs(self, s: Sentences) -> Iterator[tuple[int, int, str, float, float]]:
        """Text, line, family (or ``unknown``), probability and agreement of the paragraphs found."""
        sums, known = self.sums(s)
        p = self.probabilities(sums, known)
        hot = np.flatnonzero((p[:, 0] < 0.5) & (known > 0))
        kind = p[hot, 1:].argmax(axis=1)
        apart = np.ones(len(hot), dtype=bool)
        apart[1:] = (np.diff(hot) != 1) | (kind[1:] != kind[:-1]) | (s.text[hot[1:]] != s.text[hot[:-1]])
        cuts = np.append(np.flatnonzero(apart), len(hot))
        for a, b in zip(cuts[:-1].tolist(), cuts[1:].tolist()):
            rows = hot[a:b]
            first, last = int(rows[0]), int(rows[-1])
            whole = self.probabilities(sums[rows].sum(axis=0)[None, :], known[rows].sum()[None])[0]
            words = s.words(first, last)
            k = int(whole[2:].argmax()) + 2
            agrees = self.agreement(words, FAMILIES[k])
            if whole[k] >= self.threshold and agrees >= AGREEMENT:
                yield int(s.text[first]), int(s.line[first]), FAMILIES[k], float(whole[k]), agrees
            elif whole[0] < 0.5 and SPEAKS.search(" ".join(words)):
                yield int(s.text[first]), int(s.line[first]), UNKNOWN, float(1 - whole[0]), agrees


def softmax(x: np.ndarray) -> np.ndarray:
    e = np.exp(x - x.max(axis=1, keepdims=True))
    return e / e.sum(axis=1, keepdims=True)


def _noisy(rng: np.random.Generator, text: str, filler: list[str]) -> str:
    """A crop of a sentence with some words dropped, changed or added around it."""
    w = text.split()
    size = int(rng.integers(min(6, max(2, n // 2)), n + 1)) if (n := len(w)) > 2 else n
    lo = int(rng.integers(0, n - size + 1))
    out = []
    for x in w[lo : lo + size]:
        r = rng.random()
        if r >= 0.04:
            out.append(str(rng.choice(filler)) if r < 0.08 else x)
    for _ in range(int(rng.integers(0, 4))):
        out.insert(0 if rng.random() < 0.5 else len(out), str(rng.choice(filler)))
    return " ".join(out or w)


def _combined(rng: np.random.Generator, names: list[str], leads: list[str], tails: list[str]) -> str:
    pick = lambda x: str(x[rng.integers(len(x))])
    middle = pick(MIDDLES) if rng.random() < 0.7 else ""
    lead, tail = pick(leads) if rng.random() < 0.75 else "", pick(tails) if rng.random() < 0.5 else ""
    if lead and rng.random() < 0.2:  # as in "the tool comes under ..."
        lead = " ".join(lead.split()[-1:])
    return " ".join(x for x in (lead, middle, pick(names), tail) if x)


def training_rows(seed: int, held_out: bool) -> list[tuple[str, int]]:
    """Wordings with their class. Leads, tails, sentences, unfamiliar licences and ordinary sentences of one half never occur in the other; names do."""
    rng = np.random.default_rng([seed, held_out])
    mine = lambda items, every: [x for i, x in enumerate(items) if (i % every == every - 1) == held_out]
    filler = sorted(STOP_WORDS) + ["river", "table", "green", "paper", "2019", "project", "file", "notes", "version", "2.0", "terms"]
    leads, tails = mine(LEADS, 4), mine(TAILS, 4)
    rows: list[tuple[str, int]] = []
    for k, family in enumerate(FAMILIES[2:], 2):
        names = list(NAMES[family])
        rows += [(_combined(rng, [x], leads, tails), k) for x in names for _ in range(COMBINED)]
        for text in mine(SENTENCES[family], 4):
            rows += [(text, k), *((_noisy(rng, text, filler), k) for _ in range(COPIES))]
    strange = mine(UNFAMILIAR, 2)
    rows += [(_combined(rng, [x], leads, tails), 1) for x in strange for _ in range(COMBINED)]
    for text in mine(ORDINARY, 3):
        for x in FILLERS:
            rows += [(text.format(x), 0), (_noisy(rng, text.format(x), filler), 0)]
    rows += [(" ".join(rng.choice(filler, int(rng.integers(1, 7) ** rng.integers(1, 3)))), 0) for _ in range(PLAIN)]
    return rows


def _sums(weights: np.ndarray, at: np.ndarray, holder: np.ndarray, scale: np.ndarray, n: int) -> np.ndarray:
    return np.stack([np.bincount(holder, w[at], n) for w in weights.T], axis=1) * scale[:, None]


@lru_cache(maxsize=1)
def fitted(seed: int = SEED) -> Scanner:
    """Train and calibrate; the data are the built-in wordings, so the fit is the same anywhere."""

    def tabled(rows: list[tuple[str, int]], keys: np.ndarray | None) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
        s = Sentences.of([re.sub(r"[.;!?](?=\s)", ",", t).encode() for t, _ in rows])  # one sentence a row
        label = np.array([k for _, k in rows])[s.text]
        if keys is None:
            keys = np.unique(s.grams)
        at = np.minimum(np.searchsorted(keys, s.grams), len(keys) - 1)
        hit = keys[at] == s.grams
        known = np.bincount(s.holder[hit], minlength=len(label))
        return keys, at[hit], s.holder[hit], 1 / np.sqrt(np.maximum(known, 1)), label

    keys, at, holder, scale, label = tabled(training_rows(seed, False), None)
    n, c = len(label), len(FAMILIES)
    weights, bias = np.zeros((len(keys), c)), np.zeros(c)
    square = np.full_like(weights, 1e-3), np.full_like(bias, 1e-3)
    target = np.eye(c)[label]
    for _ in range(ROUNDS):
        g = softmax(_sums(weights, at, holder, scale, n) + bias) - target
        spread = g * scale[:, None]
        dw = np.stack([np.bincount(at, spread[holder, j], len(keys)) for j in range(c)], axis=1) / n + 1e-5 * weights
        for x, d, q in ((weights, dw, square[0]), (bias, g.mean(axis=0), square[1])):
            q += d * d
            x -= RATE * d / np.sqrt(q)
    _, at, holder, scale, label = tabled(training_rows(seed, True), keys)
    raw = _sums(weights, at, holder, scale, len(label)) + bias
    temperature = float(min(np.linspace(0.25, 4, 31), key=lambda t: -np.log(softmax(raw / t)[np.arange(len(label)), label] + 1e-12).mean()))
    wrong = np.sort(softmax(raw / temperature)[label < 2][:, 2:].max(axis=1))
    # Templates confirm what passes, so the share of wrong acceptances in the end is far smaller.
    threshold = float(np.clip(wrong[min(len(wrong) - 1, int(np.ceil((1 - FALSE_SHARE) * len(wrong))))], 0.3, 0.6))
    known = {f: tuple(pairs_of((s := Sentences.of([t.encode()])).words(0, len(s.text))) for t in texts) for f, texts in SENTENCES.items()}
    return Scanner(keys, weights, bias, temperature, threshold, known)


def classify(text: str, scanner: Scanner | None = None) -> list[str]:
    """Families (or ``unknown``) of the paragraphs of one text, in order."""
    return [family for _, _, family, _, _ in (scanner or fitted()).paragraphs(Sentences.of([text.encode()]))]


def scan(documents: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """Licences of every row: ``doc_id, n_licences, n_unknown, families, found``.

    ``families`` lists distinct families in order; ``found`` has each paragraph's
    line, family, probability and template agreement. Null and empty texts have
    none. Null ids and repeated rows are scanned like any other; other columns
    are ignored; an empty table gives an empty result.
    """
    ship(documents.sparkSession)
    shared = documents.sparkSession.sparkContext.broadcast(fitted())
    kind = pa.list_(pa.struct([("line", pa.int64()), ("family", pa.string()), ("probability", pa.float64()), ("agreement", pa.float64())]))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        own = shared.value
        for whole in batches:
            for b in slices(whole, "text"):
                rows: list[list[dict]] = [[] for _ in range(b.num_rows)]
                for i, line, family, p, agrees in own.paragraphs(Sentences.of([x.as_py() or b"" for x in b.column(1)])):
                    rows[i].append({"line": line, "family": family, "probability": p, "agreement": agrees})
                named = [[f["family"] for f in r if f["family"] != UNKNOWN] for r in rows]
                yield pa.RecordBatch.from_arrays(
                    [b.column(0), pa.array(map(len, named), pa.int64()), pa.array([len(r) - len(n) for r, n in zip(rows, named, strict=True)], pa.int64()), pa.array([sorted(set(n)) for n in named], pa.list_(pa.string())), pa.array(rows, kind)],
                    names=["doc_id", "n_licences", "n_unknown", "families", "found"],
                )

    rows = documents.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).cast("binary").alias("text"))
    return rows.mapInArrow(run, "doc_id long, n_licences long, n_unknown long, families array<string>, found array<struct<line: long, family: string, probability: double, agreement: double>>")
