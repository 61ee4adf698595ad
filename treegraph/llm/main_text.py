"""HTML extraction by the distribution of text over lines.

Markup is stripped to lines, one a block; lengths of text outside links are summed over a sliding window of lines, lines of
menus, adverts and the like counting as empty. The text surges where a sum passes a threshold and dives where it falls to
nothing. The elements (article, main) that hold a stretch between surge and dive are the article, all such stretches of them;
what these elements hold besides (headings, short lines) is kept. On a page without such elements all that is no menu, advert
or the like is the article, but for lines of links outside the stretches.
"""

from __future__ import annotations

import html
import re
from collections import Counter
from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import table

#: Lines in a window, and characters in one that count as a surge.
WINDOW, SURGE = 3, 86

# Names of elements, roles and classes.
SKIPPED = "script style noscript template iframe object svg math canvas audio video head title select option button textarea datalist"
PERIPHERAL = "nav footer aside form dialog menu"
BLOCKS = "address article aside blockquote body caption center dd details dialog dir div dl dt fieldset figcaption figure footer form frameset h1 h2 h3 h4 h5 h6 header hgroup hr html legend li main menu nav ol p pre search section summary table tbody td tfoot th thead tr ul"
CONTAINERS = "article aside blockquote body details dialog div fieldset figure footer form header main menu nav search section table td th ul ol dl"
VOID = "area base br col embed hr img input link meta param source track wbr"
ROLES = "navigation banner contentinfo complementary search dialog alertdialog alert form menu menubar toolbar"
CLASSES = (
    "ad ads adv advert adverts advertisement advertising banner breadcrumb breadcrumbs byline-social comment comments commentlist consent cookie cookies copyright cta discussion disqus "
    "footer gdpr header legal login masthead menu modal nav navbar navigation newsletter notice notices overlay pager pagination popup promo promoted promotion recommended recommendations related "
    "replies reply respond responses rail search share sharing sidebar signup skip social sponsor sponsored subscribe teaser toolbar widget widgets"
)

#: First parts of classes that speak of a state of the page, and last parts of those of its frame.
STATES, WRAPPERS = "has no with without is not", "page main content wrapper container layout article post body free text"

_skipped, _peripheral, _blocks, _containers, _void = (frozenset(x.split()) for x in (SKIPPED, PERIPHERAL, BLOCKS, CONTAINERS, VOID))
_roles, _classes, _states, _wrappers = (frozenset(x.split()) for x in (ROLES, CLASSES, STATES, WRAPPERS))
_marked = frozenset("p li h1 h2 h3 h4 h5 h6 dd dt tr".split())
_TAG = re.compile(r"<!--.*?(?:-->|\Z)|<!\[CDATA\[.*?(?:\]\]>|\Z)|<[!?][^>]*(?:>|\Z)|<(/?)([a-zA-Z][a-zA-Z0-9:-]*)((?:[^>\"']|\"[^\"]*\"|'[^']*')*)(?:>|\Z)", re.S)
_ATTRIBUTE = re.compile(r"(?<![\w-])(class|id|role|hidden|aria-hidden|style)(?:\s*=\s*(?:\"([^\"]*)\"|'([^']*)'|([^\s\"'>]+)))?", re.I)
_PARTS = re.compile(r"[A-Z]?[a-z0-9]+|[A-Z]+")
_HIDDEN = re.compile(r"display\s*:\s*none|visibility\s*:\s*hidden", re.I)
_SPAN = re.compile(r"</span\s*>", re.I)
_END = {name: re.compile(rf"</{name}\s*[^>]*>", re.I) for name in _skipped}


def tells(token: str, inside: bool) -> bool:
    """Whether a class or id names what is none of the article's: by its first or last part, unless it speaks of the page around it."""
    parts = [x.lower() for x in _PARTS.findall(token)]
    if not parts or parts[0] in _states or len(parts) > 1 and parts[-1] in _wrappers:
        return False
    found = {parts[0], parts[-1]} & _classes
    return bool(found - {"header", "banner", "legal"} if inside else found)


def is_peripheral(name: str, attributes: str, inside: bool) -> int:
    """2 for an element that is none of the article's by its own name, role or being hidden, 1 by a class or id, else 0."""
    if name in _peripheral or name == "header" and not inside:
        return 2
    if not attributes or name in ("body", "html", "main"):
        return 0
    told = 0
    for m in _ATTRIBUTE.finditer(attributes):
        key, value = m[1].lower(), m[2] or m[3] or m[4] or ""
        if key == "hidden" or key == "aria-hidden" and value.lower() == "true" or key == "style" and _HIDDEN.search(value):
            return 2
        if key == "role" and value.lower() in _roles:
            return 2
        if key in ("class", "id") and any(tells(x, inside) for x in value.split()):
            told = 1
    return told


@dataclass
class Page:
    """Lines of text, how much of each is outside links, the container of each; and of containers name, parent and is_peripheral."""

    lines: list[str] = field(default_factory=list)
    size: list[int] = field(default_factory=list)
    where: list[int] = field(default_factory=list)
    names: list[str] = field(default_factory=lambda: [""])
    parents: list[int] = field(default_factory=lambda: [-1])
    told: list[int] = field(default_factory=lambda: [0])


def blocks(page: str) -> Page:
    """The blocks of a page. Every tag is looked at once; open elements are counted by name, so that depth costs nothing."""
    out = Page()
    stack = [0]  # open containers
    opened: Counter = Counter()
    text: list[str] = []
    linked = [0]  # characters of the block inside links
    links = 0

    def flush() -> None:
        if text:
            line = " ".join(html.unescape("".join(text)).split())
            text.clear()
            if line:
                out.lines.append(line)
                own = max(0, len(line) - linked[0])
                out.size.append(own if 5 * own > len(line) else 0)  # a line of links and what stands between them
                out.where.append(stack[-1])
            linked[0] = 0

    def add(part: str) -> None:
        text.append(part)
        if links:
            linked[0] += len(part)

    at, end = 0, len(page)
    while at < end:
        m = _TAG.search(page, at)
        if not m:
            add(page[at:])
            break
        if m.start() > at:
            add(page[at : m.start()])
        at = m.end()
        name = (m[2] or "").lower()
        if not name:
            continue
        closing = bool(m[1])
        if name in _skipped:
            if not closing and not m[3].endswith("/"):
                stop = _END[name].search(page, at)
                at = stop.end() if stop else (end if name in ("script", "style", "title", "textarea") else at)
            continue
        if name == "br":
            text.append(" ")
            continue
        if name == "a":
            links = 0 if closing else 1
            continue
        if name not in _blocks:
            if name == "span" and not closing and m[3] and is_peripheral(name, m[3], True):
                stop = _SPAN.search(page, at)
                at = stop.end() if stop else at
            continue
        flush()
        if name not in _containers and name not in _marked:
            continue
        if not closing:
            if name in _void or m[3].endswith("/"):
                continue
            if name in ("p", "li") and out.names[stack[-1]] == name:
                opened[name] -= 1
                stack.pop()
            out.names.append(name)
            out.parents.append(stack[-1])
            out.told.append(is_peripheral(name, m[3], opened["article"] + opened["main"] > 0))
            stack.append(len(out.names) - 1)
            opened[name] += 1
        elif opened[name]:
            while True:
                last = out.names[stack.pop()]
                opened[last] -= 1
                if last == name:
                    break
    flush()
    return out


def away(page: Page) -> list[bool]:
    """Whether each container is none of the article's: it or one around it is told to be.

    One that only its class tells of stays if an article or main inside it is not told to be: it is the frame of the page.
    """
    holds = [name in ("article", "main") and not told for name, told in zip(page.names, page.told)]
    told = list(page.told)
    for c in range(len(holds) - 1, 0, -1):
        if holds[c] and told[c] < 2:
            told[c] = 0
            holds[page.parents[c]] = True
    out = [False]
    for c in range(1, len(told)):
        out.append(told[c] > 0 or out[page.parents[c]])
    return out


def main_text(page: str | None) -> str:
    """The article of a page, its blocks joined by line feeds; empty for a null or textless page."""
    p = blocks(page or "")
    gone = away(p)
    lost = np.array([gone[c] for c in p.where], dtype=bool)
    size = np.where(lost, 0, p.size)
    if not len(size) or lost.all():
        return ""
    total = np.convolve(size, np.ones(WINDOW, dtype=np.int64))[WINDOW - 1 :]  # of a line and the next ones
    live = total > 0
    edge = np.flatnonzero(np.diff(np.concatenate([[False], live, [False]]).astype(np.int8)))
    surged = np.zeros(len(size), dtype=bool)  # between a surge and the dive after it
    for a, b in zip(edge[::2], edge[1::2]):
        surged[a:b] = total[a:b].max() >= SURGE
    home = [0]  # the article or main that is nearest around each container
    for c in range(1, len(p.names)):
        home.append(c if p.names[c] in ("article", "main") else home[p.parents[c]])
    homes = {home[p.where[i]] for i in np.flatnonzero(surged & (size > 0))} - {0}
    if homes:
        inside = [False]
        for c in range(1, len(p.names)):
            inside.append(c in homes or inside[p.parents[c]])
        keep = [inside[c] for c in p.where] & ~lost
    else:
        keep = ~lost & (surged | (size > 0) | (not size.any()))
    return "\n".join([x for x, k in zip(p.lines, keep) if k])


def extract(pages: DataFrame, *, html_col: str = "html", out: str = "text") -> DataFrame:
    """pages with the main text of html_col in column out (replaced if there), all other columns as they are.

    A null or empty html gives an empty text; equal pages give equal texts; the time is linear in the length and the depth of
    a page. An empty table gives an empty result.
    """

    @F.arrow_udf("string")
    def run(column: pa.Array) -> pa.Array:
        return pa.array([main_text(x.as_py()) for x in column], pa.string())

    return pages.withColumn(out, run(F.col(html_col)))


def op7_html_extraction(spark: SparkSession, sf_dir: str) -> DataFrame:
    pages = table(spark, sf_dir, "pages").select("page_id", "url", "html")
    return extract(pages).select("page_id", "url", "text", F.length("text").cast("long").alias("n_chars"))


QUERIES = {"op7_html_extraction": op7_html_extraction}
ORACLES: dict[str, str] = {}
