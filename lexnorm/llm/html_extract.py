"""Main text of web pages by two-pass block rules.

A page is cut into blocks at block-level tags. Pass one classifies each block by
its stop-word density, length and link density. Tags, roles and class words move
the thresholds only: a block inside an article needs half as much, one inside an
element marked as navigation, footer, advert, comment or the like a multiple. Pass two
gives every undecided block the label of its nearest decided neighbours, found by
one sweep from either end. A heading opens a section: neighbours are looked for in
the block's own section first.
"""

from __future__ import annotations

import html as entities
import re
from collections.abc import Iterator
from dataclasses import dataclass

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from lexnorm.llm.words import slices
from lexnorm.sources.store import ship

# Common function words of several languages.
STOP_WORDS = frozenset(
    (
        "the of and to in a is that for it as was with be by on not he his but at are this have from or had an they which one you were all her she there would their we him been has when who will no more if out so up said what its about than into them can only other time new some could these two may first then do any like my now over such our man me even most made after also did many off before must well back through years where much your way "
        "le la les de des du un une et est en que qui dans pour par sur pas au aux avec ce cette ces il elle ils elles son sa ses ne se plus ou mais nous vous leur leurs on être avoir fait comme tout si sont été deux même sans entre aussi peut donc où "
        "der die das und ist in den von zu mit sich des auf für nicht ein eine einer eines einem einen als auch es an werden aus er hat dass daß sie nach wird bei um am sind noch wie über so zum zur haben nur oder aber vor bis mehr durch man dem im war wenn kann "
        "el los las y del se lo por con para una su al como más pero sus ya o este sí porque esta entre cuando muy sin sobre también me hasta hay donde quien desde todo nos durante todos uno les ni contra otros ese eso ante ellos esto antes algunos qué unos yo otro otras "
        "il gli di che per con non una sono della nel alla si dei anche più het een van en dat niet zijn op voor met aan um uma não os com da do na dos das"
    ).split()
)
#: Elements whose content is never text.
SILENT = frozenset(("script", "style", "noscript", "template", "svg", "math", "iframe", "object", "canvas", "audio", "video", "head", "title", "textarea", "select", "option", "datalist"))
#: Elements that seldom hold an article.
OUTSIDE = frozenset(("nav", "footer", "aside", "form", "button", "menu", "dialog", "fieldset", "label", "legend"))
#: ``header`` is a site banner unless an article holds it.
BANNER = "header"
ARTICLE = frozenset(("article", "main"))
VOID = frozenset(("area", "base", "br", "col", "embed", "hr", "img", "input", "link", "meta", "param", "source", "track", "wbr"))
BREAKS = frozenset(
    "address article aside blockquote body br button caption center col colgroup dd details dialog dir div dl dt fieldset figcaption figure footer form frameset h1 h2 h3 h4 h5 h6 head header hgroup hr html legend li main menu nav ol optgroup option p pre section summary table tbody td tfoot th thead title tr ul".split()
)
ROLES = frozenset(("navigation", "banner", "contentinfo", "complementary", "search", "dialog", "alertdialog", "form", "menu", "menubar", "toolbar", "alert"))
#: Words of class and id names that mark boilerplate; a name is cut at non-letters and at capitals.
MARKS = frozenset(
    "ad ads adv advert adverts advertisement advertising sponsor sponsored promo promotion banner cookie cookies consent gdpr notice notices newsletter subscribe subscription popup modal overlay sidebar side rail card teaser widget widgets related recommended recommendations share sharing social breadcrumb breadcrumbs nav navbar navigation menu footer masthead comment comments disqus reply replies respond pagination pager login signup search toolbar copyright legal disclaimer".split()
)
#: Words that clear a name of the above: the body of an article may be called so.
CLEARS = frozenset(("article", "content", "post", "entry", "story", "main", "body"))

#: A quote opens a quoted value right after "=" only; elsewhere it is a character like any other.
TAG = re.compile(r"<!--.*?(?:-->|\Z)|<!\[CDATA\[.*?(?:\]\]>|\Z)|<[!?][^>]*(?:>|\Z)|<(/?)([A-Za-z][A-Za-z0-9:-]*)((?:[^>=]++|=\s*+(?:\"[^\"]*+\"|'[^']*+')|=)*+)(?:>|\Z)", re.S)
ATTR = re.compile(r"([A-Za-z_:][-\w:.]*)(?:\s*=\s*(\"[^\"]*\"|'[^']*'|[^\s>]+))?")
RAW_END = {t: re.compile(rf"</{t}\s*(?:>|\Z)", re.I) for t in ("script", "style", "textarea", "title", "noscript", "template", "iframe")}
NAME_PART = re.compile(r"[A-Z]?[a-z]+|[A-Z]+(?![a-z])")
WORD = re.compile(r"[^\W\d_]+")
SPACES = re.compile(r"\s+")


@dataclass(frozen=True)
class Rules:
    """Thresholds of the first pass, in characters and shares of words.

    ``article_ease`` multiplies them inside an article, ``marked_need`` the length
    inside an element marked as boilerplate.
    """

    length_low: int = 70
    length_high: int = 200
    density_low: float = 0.12
    density_high: float = 0.25
    most_links: float = 0.35
    article_ease: float = 0.5
    marked_need: float = 4.0


@dataclass
class Block:
    text: str
    linked: int = 0
    marked: bool = False
    in_article: bool = False
    heading: bool = False


def _mark(attrs: str) -> tuple[bool, bool]:
    """Whether an element's attributes mark it as boilerplate, and as not shown at all."""
    marked = False
    if not attrs.strip():
        return False, False
    for m in ATTR.finditer(attrs):
        name, value = m[1].lower(), (m[2] or "").strip("\"'")
        if name == "hidden" or (name == "style" and re.search(r"display\s*:\s*none|visibility\s*:\s*hidden", value, re.I)):
            return True, True
        if (name == "aria-hidden" and value.lower() == "true") or (name == "role" and value.lower() in ROLES):
            marked = True
        if name in ("class", "id"):
            for one in value.split():
                parts = {p.lower() for p in NAME_PART.findall(one)}
                if parts & MARKS and not (parts & CLEARS and not parts & {"ad", "ads", "comment", "comments", "sidebar", "related"}):
                    marked = True
    return marked, False


def blocks(page: str) -> list[Block]:
    """Blocks of text in page order; tolerant of unclosed, stray and truncated tags."""
    out: list[Block] = []
    stack: list[tuple[str, bool, bool, bool]] = []  # tag, marked, in an article, not shown
    parts: list[str] = []
    linked = links = 0
    heading = False
    bottom = ("", False, False, False)

    def flush() -> None:
        nonlocal linked
        _, marked, article, silent = stack[-1] if stack else bottom
        text = "" if silent else SPACES.sub(" ", entities.unescape("".join(parts))).strip()
        if text:
            out.append(Block(text, min(linked, len(text)), marked, article, heading))
        parts.clear()
        linked = 0

    at, size = 0, len(page)
    while at < size:
        lt = page.find("<", at)
        m = TAG.match(page, lt) if lt >= 0 else None
        end = lt if lt >= 0 else size
        if m is None and lt >= 0:
            end = lt + 1  # a lone "<" is text
        if end > at:
            piece = page[at:end]
            parts.append(piece)
            if links:
                linked += len(piece.strip())
        if m is None:
            at = end
            continue
        at = m.end()
        if m[2] is None:
            continue
        tag, closing = m[2].lower(), bool(m[1])
        if tag in RAW_END and not closing:
            stop = RAW_END[tag].search(page, at)
            at = stop.end() if stop else size
            if tag in BREAKS:
                flush()
            continue
        if tag == "a":
            links = max(0, links - 1) if closing else 1
            continue
        if tag in BREAKS:
            flush()
            links = 0
            heading = not closing and len(tag) == 2 and tag[0] == "h" and tag[1].isdigit()
        if tag in VOID:
            continue
        if closing:
            for i in range(len(stack) - 1, -1, -1):
                if stack[i][0] == tag:
                    if tag not in BREAKS:
                        flush()
                    del stack[i:]
                    break
        elif tag in BREAKS or tag in SILENT or tag in OUTSIDE:
            if tag == "p" or tag == "li":  # these end at the next of their kind
                while stack and stack[-1][0] == tag:
                    stack.pop()
            above = stack[-1] if stack else bottom
            marked, unseen = _mark(m[3]) if tag not in ("body", "html") else (False, False)
            marked = marked or tag in OUTSIDE or (tag == BANNER and not above[2])
            stack.append((tag, above[1] or marked, above[2] or tag in ARTICLE, above[3] or unseen or tag in SILENT))
        elif m[3] and any(mark := _mark(m[3])):
            flush()
            above = stack[-1] if stack else bottom
            stack.append((tag, above[1] or mark[0], above[2], above[3] or mark[1]))
    flush()
    return out


GOOD, BAD, NEAR, SHORT = "good", "bad", "near", "short"


def density(text: str) -> float:
    """Share of stop words."""
    words = WORD.findall(text.lower())
    return sum(w in STOP_WORDS for w in words) / len(words) if words else 0.0


def first_pass(b: Block, rules: Rules = Rules(), marks: bool = True) -> str:
    """``good`` or ``bad`` if the block's own numbers decide, else ``near`` (text like an article's, if not much) or ``short`` (little text, or few stop words)."""
    n, share = len(b.text), density(b.text)
    if b.linked > rules.most_links * n:
        return BAD
    if marks and b.marked:
        return NEAR if n >= rules.marked_need * rules.length_high and share >= rules.density_high else BAD
    ease = rules.article_ease if b.in_article else 1.0
    if n < ease * rules.length_low:
        return SHORT if not b.linked or b.in_article else BAD
    if share >= ease * rules.density_high and n >= ease * rules.length_high:
        return GOOD
    return NEAR if share >= ease * rules.density_low or b.in_article else SHORT


def neighbours(found: list[Block], labels: list[str], step: int, sections: bool) -> list[str | None]:
    """The nearest decided label before (``step`` -1) or after (1) each block, by one sweep.

    The page's ends, and an article's, count as bad; what is marked as boilerplate
    tells nothing of the text around it. With ``sections`` the sweep
    forgets what it saw at every heading: nothing is decided beyond it.
    """
    out: list[str | None] = [None] * len(found)
    last: str | None = BAD
    order = range(len(found)) if step < 0 else range(len(found) - 1, -1, -1)
    before = None
    for i in order:
        if before is not None and found[before].in_article != found[i].in_article:
            last = BAD
        if sections and found[i].heading and step < 0:
            last = None
        out[i] = last
        if labels[i] in (GOOD, BAD) and not found[i].marked:
            last = labels[i]
        if sections and found[i].heading and step > 0:
            last = None
        before = i
    return out


def inherit(b: Block, label: str, sides: tuple[str | None, str | None], wide: tuple[str | None, str | None]) -> str:
    """The label of an undecided block from its neighbours' in its section, or in the page if its section has none."""
    left, right = sides if any(sides) else wide
    if b.marked and label == NEAR:
        return GOOD if left == right == GOOD else BAD
    if BAD not in (left, right):
        return GOOD
    if GOOD not in (left, right):
        return BAD
    return GOOD if left == GOOD or label == NEAR or b.in_article or b.heading else BAD


def second_pass(found: list[Block], first: list[str]) -> list[str]:
    """All labels decided."""
    sides = [list(zip(neighbours(found, first, -1, s), neighbours(found, first, 1, s), strict=True)) for s in (True, False)]
    return [x if x in (GOOD, BAD) else inherit(b, x, near, wide) for b, x, near, wide in zip(found, first, *sides, strict=True)]


def main_text(page: str | None, rules: Rules = Rules()) -> str:
    """The article of one page; empty for null, empty or text-free pages.

    Where nothing outside marked elements looks like an article, the marks are
    taken to be wrong and left aside. Where no block is good by its own numbers,
    the longest undecided one is, first of those in an article.
    """
    found = blocks(page or "")
    first = [first_pass(b, rules) for b in found]
    if GOOD not in first and NEAR not in first:
        bare = [first_pass(b, rules, False) for b in found]
        if GOOD in bare:
            first = bare
    if GOOD not in first:
        open_ = [i for i, x in enumerate(first) if x != BAD and not found[i].heading]
        if open_:
            best = max(open_, key=lambda i: (found[i].in_article, len(found[i].text), density(found[i].text), -i))
            first[best] = GOOD
    return " ".join(b.text for b, x in zip(found, second_pass(found, first), strict=True) if x == GOOD)


def extract(pages: DataFrame, id_col: str = "page_id", url_col: str = "url", html_col: str = "html", rules: Rules = Rules()) -> DataFrame:
    """``page_id, url, text, n_chars`` for every row of ``pages``.

    Null and empty html give an empty text with ``n_chars`` 0. Repeated rows are
    kept and treated alike, other columns are ignored, null ids and urls pass
    through, and an empty table gives an empty result. No length limit applies.
    """
    ship(pages.sparkSession)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for whole in batches:
            for b in slices(whole, "html", 1 << 23):
                texts = [main_text(x.as_py(), rules) for x in b.column(2)]
                yield pa.RecordBatch.from_arrays([b.column(0), b.column(1), pa.array(texts, pa.string()), pa.array(map(len, texts), pa.int64())], names=["page_id", "url", "text", "n_chars"])

    rows = pages.select(F.col(id_col).cast("long").alias("page_id"), F.col(url_col).cast("string").alias("url"), F.col(html_col).cast("string").alias("html"))
    return rows.mapInArrow(run, "page_id long, url string, text string, n_chars long")
