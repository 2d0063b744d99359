"""DuckDB SQL of the methods, built from the same constants as the Spark plans."""

from __future__ import annotations

from lexnorm.config import PRIME, HashParams
from lexnorm.functions.hashing import OFFSET, Family, probe_order, sides

WORD = r"[\p{L}\p{N}]+"


def words_of(source: str, text: str = "text") -> str:
    return f"SELECT unnest(regexp_extract_all(lower({text}), '{WORD}')) AS word FROM {source}"


#: Letters beyond ASCII in the given texts, each with a stand-in of one byte (no word holds capitals): DuckDB's distances count bytes.
WIDE, STAND_INS = "éóèñüçêäößíáúàâîôûïëœæ", "ABCDEFGHIJKLMNOPQRSTUV"


def single(word: str) -> str:
    return f"translate({word}, '{WIDE}', '{STAND_INS}')"


def vocab(source: str = "documents") -> str:
    return f"SELECT word, count(*) AS freq FROM ({words_of(source)}) GROUP BY word"


def gram_list(word: str, char_lens: tuple[int, ...] | str) -> str:
    """Distinct substrings as a list."""
    run = lambda k: f"[substr({word}, i, {k}) FOR i IN range(1, greatest(length({word}) - {k} + 2, 1))]"
    if char_lens == "all":
        return f"list_distinct(flatten(list_transform(range(1, length({word}) + 1), lambda k: list_transform(range(1, length({word}) - k + 2), lambda i: substr({word}, i, k)))))"
    return "list_distinct(list_concat(" + ", ".join(map(run, char_lens)) + "))" if len(char_lens) > 1 else f"list_distinct({run(char_lens[0])})"


def fingerprint(gram: str) -> str:
    return f"(('0x' || substr(md5({gram}), 1, 8))::BIGINT % {PRIME})"


def minima(params: HashParams, words: str = "vocab", tag: str = "") -> str:
    """CTEs ``fam, x, mins`` over a relation with ``word``."""
    rows = ", ".join(f"({i}, {r.a[0]}, {r.b[0]}, {r.fold_a}, {r.fold_b}, {', '.join(str(x).lower() for x in sides(r, params))})" for i, r in enumerate(Family.draw(params).repetitions))
    rights = ", ".join(f"right{k}" for k in range(params.bins))
    mins = ", ".join(f"min(h) FILTER (h * {params.bins} // {params.space} = {k}) AS m{k}" for k in range(params.bins))
    return (
        f"fam{tag}(rep, a, b, fa, fb, {rights}) AS (VALUES {rows}), "
        f"x{tag} AS (SELECT word, {fingerprint('g')} AS x FROM (SELECT word, unnest({gram_list('word', params.char_lens)}) AS g FROM {words})), "
        f"mins{tag} AS (SELECT word, rep, {mins} FROM (SELECT word, rep, (a * x + b) % {PRIME} AS h FROM x{tag}, fam{tag}) GROUP BY word, rep)"
    )


def dense(params: HashParams, tag: str = "") -> str:
    """CTE ``dense`` after ``mins``."""
    out = []
    for k in range(params.bins):
        by = {}
        for right in (True, False):
            order = probe_order(k, params.bins, right)
            by[right] = "coalesce(" + ", ".join(f"(m{j} + {OFFSET * i}) % {PRIME}" if params.densify == "coin_offset" and i else f"m{j}" for i, j in enumerate(order)) + ")"
        out.append(f"CASE WHEN right{k} THEN {by[True]} ELSE {by[False]} END AS d{k}")
    return f"dense{tag} AS (SELECT word, rep, fa, fb, {', '.join(out)} FROM mins{tag} JOIN fam{tag} USING (rep))"


def sigs(params: HashParams, words: str = "vocab", tag: str = "") -> str:
    """CTEs up to ``sigs(word, rep, sig)``."""
    chain = "0"
    for k in range(params.bins):
        chain = f"((d{k} + {chain}) % {PRIME} * fa + fb) % {PRIME}"
    return f"{minima(params, words, tag)}, {dense(params, tag)}, sigs{tag} AS MATERIALIZED (SELECT word, rep, {chain} AS sig FROM dense{tag})"


def edges(params: HashParams, least: int | None = None) -> str:
    """CTEs up to ``edges(src, dst, weight)`` over the vocabulary of documents."""
    w = params.index_min if least is None else least
    return f"vocab AS MATERIALIZED ({vocab()}), {sigs(params)}, edges AS MATERIALIZED (SELECT a.word AS src, b.word AS dst, count(*) AS weight FROM sigs a JOIN sigs b ON a.rep = b.rep AND a.sig = b.sig AND a.word < b.word GROUP BY ALL HAVING count(*) >= {w})"


def components(source: str = "edges", name: str = "cc") -> str:
    """CTE ``cc(node, comp)``: the least word reachable, by spreading minima along links."""
    return (
        f"sym_{name} AS MATERIALIZED (SELECT src AS u, dst AS v FROM {source} UNION ALL SELECT dst, src FROM {source}), "
        f"{name}(node, comp) USING KEY (node) AS (SELECT word, word FROM vocab UNION "
        f"SELECT x.v, x.m FROM (SELECT e.v, min(c.comp) AS m FROM {name} c JOIN sym_{name} e ON c.node = e.u GROUP BY e.v) x JOIN recurring.{name} r ON r.node = x.v AND x.m < r.comp)"
    )


def norm() -> str:
    """CTE ``norm`` after ``vocab`` and ``cc``."""
    return (
        "norm AS MATERIALIZED (SELECT word, freq, comp, first_value(word) OVER w AS rep_word, first_value(freq) OVER w AS rep_freq, count(*) OVER (PARTITION BY comp) AS size "
        "FROM vocab JOIN cc ON node = word WINDOW w AS (PARTITION BY comp ORDER BY freq DESC, word))"
    )


def index(params: HashParams) -> str:
    """All CTEs up to ``norm``; the caller starts with WITH RECURSIVE."""
    return f"{edges(params)}, {components()}, {norm()}"


def attach(params: HashParams, asked: str, inclusive: bool = False, grouped: bool = False) -> str:
    """CTEs after :func:`index` up to ``attached``; ``asked`` is a relation with distinct ``word``."""
    only = " AND s.word IN (SELECT word FROM norm WHERE size > 1)" if grouped else ""
    return (
        f"asked AS ({asked}), unseen AS (SELECT word FROM asked WHERE word NOT IN (SELECT word FROM vocab)), {sigs(params, 'unseen', '_u')}, "
        f"weighed AS (SELECT u.word, s.word AS indexed, count(*) AS weight FROM sigs_u u JOIN sigs s ON u.rep = s.rep AND u.sig = s.sig{only} GROUP BY ALL HAVING count(*) >= {params.infer_min(inclusive)}), "
        "best AS (SELECT w.word, indexed, weight, rep_word FROM weighed w JOIN norm n ON n.word = indexed QUALIFY row_number() OVER (PARTITION BY w.word ORDER BY weight DESC, freq DESC, indexed) = 1), "
        "attached AS (SELECT word, word AS matched, NULL::INT AS weight, rep_word, 'known' AS status FROM asked JOIN norm USING (word) "
        "UNION ALL SELECT u.word, indexed, weight::INT, coalesce(rep_word, u.word), CASE WHEN indexed IS NULL THEN 'unmatched' ELSE 'attached' END FROM unseen u LEFT JOIN best b ON b.word = u.word)"
    )


def draw(*parts: str) -> str:
    return "(('0x' || substr(md5(concat_ws('|', " + ", ".join(parts) + ")), 1, 8))::BIGINT)"


def noise(source: str, key: str, rate: int, seed: int = 13, text: str = "text") -> str:
    """CTE body: ``id, pos, clean_word, noisy_word, gap, last_gap, selected`` for each word (``pos`` from 0), or one row without words."""

    def change(w: str, step: int) -> str:
        at = f"({draw(str(seed), 'id', 'pos', str(step), chr(39) + 'p' + chr(39))} % length({w}) + 1)"
        letter = f"substr('abcdefghijklmnopqrstuvwxyz', ({draw(str(seed), 'id', 'pos', str(step), chr(39) + 'c' + chr(39))} % 26 + 1), 1)"
        cut = f"substr({w}, 1, {at} - 1)", f"substr({w}, {at} + 1)"
        drop = f"{draw(str(seed), 'id', 'pos', str(step), chr(39) + 'o' + chr(39))} % 2 = 0 AND length({w}) > 1"
        return f"CASE WHEN {drop} THEN {cut[0]} || {cut[1]} ELSE {cut[0]} || {letter} || {cut[1]} END"

    return (
        f"SELECT id, pos, w AS clean_word, CASE WHEN NOT selected THEN w WHEN {draw(str(seed), 'id', 'pos', chr(39) + 'n' + chr(39))} % 2 = 1 THEN {change('w1', 2)} ELSE w1 END AS noisy_word, selected "
        f"FROM (SELECT *, {change('w', 1)} AS w1 FROM (SELECT id, selected, unnest(ws) AS w, unnest(range(len(ws))) AS pos FROM "
        f"(SELECT {key} AS id, regexp_extract_all(lower({text}), '{WORD}') AS ws, {draw(str(seed), key, chr(39) + 's' + chr(39))} % 100 < {rate} AS selected FROM {source})))"
    )
