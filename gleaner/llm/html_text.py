"""Main text of web pages by line-block distribution.

Markup is stripped, which leaves one line for each block of a page with the length of its text outside links; menus,
notices, forms and the like leave none. Sums over sliding windows of lines show where the text surges and where it dives;
what lies between is kept. Where a page says which element is its article, that is a hint: lines inside weigh at least
``INSIDE``, those outside only a part of their length, so that outside none but long running text surges.
"""

from __future__ import annotations

import html
import re
from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import DataFrame

from gleaner.llm.common import text_column

#: Parameters: lines a window, sum at which text surges, least weight of a line inside an article, part of its length that one outside weighs.
WINDOW, SURGE, INSIDE, OUTSIDE = 3, 80, 200, 0.1
#: Elements by what they mean for a reader.
BLOCKS = frozenset(
    "address article aside blockquote body br caption center dd details dialog dir div dl dt fieldset figcaption figure footer form h1 h2 h3 h4 h5 h6 "
    "head header hgroup hr html legend li main menu nav ol option p pre section summary table tbody td tfoot th thead title tr ul".split()
)
SILENT = frozenset("script style noscript template svg math iframe object embed canvas audio video head title select textarea".split())
ASIDE = frozenset("nav footer aside form menu button dialog fieldset".split())
VOID = frozenset("area base br col embed hr img input link meta param source track wbr".split())
HOLDS = frozenset("article main".split())
MARKED = re.compile(
    r"(?:^|[\s_-])(?:ads?|advert\w*|banner|sponsor\w*|promo\w*|cookies?\w*|consent|gdpr|notices?|alert|comments?|disqus\w*|repl(?:y|ies)|sidebar|side|widget|"
    r"menu|nav\w*|breadcrumbs?|pagination|pager|footer|masthead|topbar|share|sharing|social|related|recommend\w*|newsletter|subscribe|signup|login|popup|modal|overlay|skip)(?:$|[\s_-])",
    re.IGNORECASE,
)
#: Inside an article a name alone tells little: only these, and only on elements that hold others.
MARKED_INSIDE = re.compile(r"(?:^|[\s_-])(?:ads?|advert\w*|sponsor\w*|promo|cookies?|consent|gdpr|comments?|disqus\w*|repl(?:y|ies)|sidebar|share|sharing|social|newsletter|subscribe|signup|popup|modal)(?:$|[\s_-])", re.IGNORECASE)
CONTAINERS = frozenset("div section aside ul ol dl table details".split())
ROLES = re.compile(r"\brole\s*=\s*[\"']?(?:navigation|banner|contentinfo|complementary|search|form|dialog|alert)\b|\bhidden\b(?!-)|aria-hidden\s*=\s*[\"']?true|display\s*:\s*none", re.IGNORECASE)
NAMES = re.compile(r"\b(?:class|id)\s*=\s*(?:\"([^\"]*)\"|'([^']*)'|([^\s>]+))", re.IGNORECASE)
TAG = re.compile(r"<!--.*?(?:-->|\Z)|<!\[CDATA\[.*?(?:\]\]>|\Z)|<[!?][^>]*>|<(/?)([a-zA-Z][^\s/>]*)((?:[^>\"']|\"[^\"]*\"|'[^']*')*)>", re.DOTALL)


def lines(page: str) -> list[tuple[str, int, bool]]:
    """(text, weight, inside an article) of each block of a page, in order."""
    out: list[tuple[str, int, bool]] = []
    text: list[str] = []
    linked = 0
    links = holds = 0
    skip: tuple[str, int] | None = None  # element whose content is dropped, and how deep it is nested in itself
    at = 0

    def close() -> None:
        nonlocal text, linked
        words = " ".join(html.unescape("".join(text)).split())
        if words:
            out.append((words, max(0, len(words) - 2 * linked), holds > 0))
        text, linked = [], 0

    def add(part: str) -> None:
        nonlocal linked
        text.append(part)
        linked += len(part.strip()) if links else 0

    pos = 0
    while m := TAG.search(page, pos):
        if skip is None and m.start() > at:
            add(page[at : m.start()])
        at = pos = m.end()
        if not m[2]:
            continue
        name, end = m[2].lower(), m[1] == "/"
        if skip:
            if name == skip[0] and name not in VOID:
                depth = skip[1] + (-1 if end else 1 if not m[3].endswith("/") else 0)
                skip = (name, depth) if depth else None
            continue
        if name in BLOCKS:
            close()
            if end or name in HOLDS:  # a link left open ends with its block
                links = 0
        if end:
            if name == "a":
                links = max(0, links - 1)
            elif name in HOLDS:
                holds = max(0, holds - 1)
            continue
        if name in ("script", "style", "textarea", "title") or name in SILENT:
            stop = re.compile(rf"</{re.escape(name)}\s*>", re.IGNORECASE).search(page, pos)
            if stop:
                at = pos = stop.end()
            elif name not in VOID:
                at = pos = len(page) if name in ("script", "style") else pos
            continue
        attributes = m[3]
        dropped = name in ASIDE or name == "header" and not holds
        if not dropped and attributes and name not in ("html", "body", *HOLDS):
            marked = MARKED if not holds else MARKED_INSIDE if name in CONTAINERS else None
            dropped = bool(ROLES.search(attributes)) or marked is not None and any(marked.search(f"{a}{b}{c}") for a, b, c in NAMES.findall(attributes))
        if dropped and name not in VOID and not attributes.endswith("/") and re.compile(rf"</{re.escape(name)}\s*>", re.IGNORECASE).search(page, pos):
            close()
            skip = (name, 1)
        elif name == "a":
            links += 1
        elif name in HOLDS:
            holds += 1
    if skip is None and at < len(page):
        add(page[at:])
    close()
    return out


def kept(weight: list[float], surge: float) -> list[int]:
    """The lines between each surge and the dive that follows it, but for those that weigh nothing.

    The text surges where the sum of a window reaches ``surge``, and dives where it falls below at a line without weight, or
    where a whole window has none.
    """
    sums = [sum(weight[i : i + WINDOW]) for i in range(len(weight))]
    start, out = None, []
    for i in range(len(weight) + 1):
        if i == len(weight) or start is not None and not weight[i] and (sums[i] < surge or not sums[i]):
            if start is not None:
                out += [k for k in range(start, i) if weight[k]]
            start = None
        elif start is None and weight[i] and sums[i] >= surge:
            start = i
    return out


def main_text(page: str) -> str:
    """The text of every stretch between a surge and a dive, blocks joined by blanks. On a page where nothing surges, the heaviest window does."""
    rows = lines(page)
    if any(inside for *_, inside in rows):
        told = [float(max(w, INSIDE)) if inside else 0.0 for _, w, inside in rows]
        around = [w * OUTSIDE if w >= SURGE and not inside else 0.0 for _, w, inside in rows]
        chosen = sorted([*kept(told, SURGE), *kept(around, SURGE)])
    else:
        plain = [float(w) for _, w, _ in rows]
        heaviest = max((sum(plain[i : i + WINDOW]) for i in range(len(plain))), default=0.0)
        chosen = kept(plain, min(SURGE, heaviest))
    return " ".join(rows[i][0] for i in chosen)


def extract(pages: DataFrame) -> DataFrame:
    """(page_id, url, text, n_chars) for every row of ``pages`` (page_id, url, html), from whole pages.

    Null html is empty and gives an empty text; so does a page without text. Markup left open ends with the page.
    Repeated rows each get a row, null keys stay null, other columns are not read, an empty table gives an empty one.
    """

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            texts = [main_text(p) for p in text_column(batch, "html")]
            yield pa.RecordBatch.from_arrays([batch.column("page_id"), batch.column("url"), pa.array(texts, pa.string()), pa.array([len(t) for t in texts], pa.int64())], ["page_id", "url", "text", "n_chars"])

    return pages.selectExpr("cast(page_id as long) page_id", "cast(url as string) url", "html").mapInArrow(run, "page_id long, url string, text string, n_chars long")
