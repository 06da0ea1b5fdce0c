"""Main text of web pages by line-block distribution.

The markup is stripped into lines, one per block element, in groups: the lines of one article or main element, else those
of one structural element.  A line's weight is its text length, raised in articles and top headings, lowered where an
element is named like an advert, and nothing in parts that are never article text (menus, headers, footers, sidebars,
notices, forms, scripts, styles, reader comments).  Weights are summed over a sliding window of lines that does not
cross groups.  Where the sum surges above a threshold a group is text, until the last one dives below it: all between the
first and the last group that surge is kept, short lines and short groups included; lines of lowered weight only
if they surge themselves.

Defined results: a null or empty page gives an empty text; unclosed and cut-off markup ends with the page; nested
articles belong to the outer one; equal pages give equal texts; other columns are never read, so their names cannot clash.
"""

from __future__ import annotations

import html
import re
from collections import Counter

from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from .arrowmap import map_texts

WINDOW = 3
SURGE = 80  # characters in a window
SURGE_SHARE = 0.5  # of the fullest window, if that is less
VOUCHED, DOUBTED = 4.0, 0.1  # weight of a character in an article or top heading, and in a part that may be an advert

# Elements of HTML by the part they play here.
RAW = {"script", "style", "textarea", "title", "noscript", "template", "iframe", "noembed", "noframes", "xmp"}
DROPPED = RAW | {"head", "nav", "header", "footer", "aside", "form", "button", "select", "svg", "math", "object", "audio", "video", "canvas", "dialog", "menu", "datalist"}
VOID = {"area", "base", "br", "col", "embed", "hr", "img", "input", "link", "meta", "param", "source", "track", "wbr"}
INLINE = {"a", "abbr", "acronym", "b", "bdi", "bdo", "big", "cite", "code", "data", "del", "dfn", "em", "font", "i", "ins", "kbd", "label", "mark", "meter", "output", "progress", "q", "rp", "rt", "ruby", "s", "samp", "small", "span", "strike", "strong", "sub", "sup", "time", "tt", "u", "var", "wbr", "img"}
CLOSES_P = {"address", "article", "aside", "blockquote", "center", "details", "dialog", "dir", "div", "dl", "fieldset", "figcaption", "figure", "footer", "form", "h1", "h2", "h3", "h4", "h5", "h6", "header", "hgroup", "hr", "main", "menu", "nav", "ol", "p", "pre", "search", "section", "summary", "table", "ul"}
CONTAINERS = ("article", "main")
ROLES = {"navigation", "banner", "contentinfo", "complementary", "search", "form", "dialog", "alert", "alertdialog", "menu", "menubar", "toolbar"}
GROUPS = {"article", "main", "div", "section", "ul", "ol", "dl", "table", "td", "blockquote", "figure", "details", "fieldset", "center", "body"} | {"nav", "header", "footer", "aside", "form"}
NOISE_WORDS = {
    "nav", "navbar", "navigation", "menu", "breadcrumb", "breadcrumbs", "sidebar", "footer", "header", "masthead", "cookie", "cookies", "consent",
    "notice", "popup", "modal", "newsletter", "subscribe", "signup", "login", "comment", "comments", "disqus", "respond", "reply", "replies", "pager",
    "pagination", "toolbar", "gdpr", "alert",
}
DOUBTED_WORDS = {
    "ad", "ads", "adv", "advert", "adverts", "advertisement", "advertising", "adsense", "sponsor", "sponsored", "promo", "promotion", "banner",
    "share", "sharing", "social", "related", "recommended", "widget",
}

_TAG = re.compile(r"<!--.*?(?:-->|\Z)|<[!?][^>]*(?:>|\Z)|<(/?)([a-zA-Z][^\s/>]*)((?:[^>\"']|\"[^\"]*\"|'[^']*')*)(?:>|\Z)|<(/?)([a-zA-Z][^\s/>]*)([^>]*)(?:>|\Z)", re.S)
_ATTRIBUTE = re.compile(r"([^\s=\"'/]+)(?:\s*=\s*(?:\"([^\"]*)\"|'([^']*)'|([^\s\"'>]+)))?")
_SPLIT = re.compile(r"[^a-z0-9]+")


def _weight(name: str, attributes: str, vouched: bool) -> float:
    """What an element multiplies the weight of its lines by.  An article's own header is part of it."""
    if name in DROPPED and not (name == "header" and vouched):
        return 0.0
    out = 1.0
    if attributes and name not in ("html", "body"):
        for k, a, b, c in _ATTRIBUTE.findall(attributes):
            k, v = k.lower(), (a or b or c).lower()
            if k in ("class", "id"):
                words = _SPLIT.split(v)
                if not NOISE_WORDS.isdisjoint(words) and not (name == "header" and vouched):
                    return 0.0
                if not DOUBTED_WORDS.isdisjoint(words):
                    out = DOUBTED
            if k == "role" and v in ROLES or k == "hidden" or k == "aria-hidden" and v == "true" or k == "style" and re.search(r"display\s*:\s*none|visibility\s*:\s*hidden", v):
                return 0.0
    return out


def lines_of(page: str) -> list[tuple[str, float, int]]:
    """Lines of text in page order: the text, the weight of a character, and the group."""
    lines: list[tuple[str, float, int]] = []
    stack: list[tuple[str, float, int, bool]] = [("", 1.0, 0, False)]  # name, weight, group, whether in an article
    open_: Counter[str] = Counter()
    buffer: list[str] = []
    groups = 0

    def flush() -> None:
        if buffer:
            text = " ".join(html.unescape("".join(buffer)).split())
            buffer.clear()
            if text:
                lines.append((text, *stack[-1][1:3]))

    def cut(at: int) -> None:
        for x in stack[at:]:
            open_[x[0]] -= 1
        del stack[at:]

    def close(name: str) -> None:
        if not open_[name]:
            return
        for i in range(len(stack) - 1, 0, -1):
            if stack[i][0] == name:
                if any(x[0] not in INLINE for x in stack[i:]) or stack[i][1] != stack[i - 1][1]:
                    flush()
                return cut(i)
            if name in INLINE and stack[i][0] not in INLINE and stack[i][0] != "p":
                return

    def close_sibling(names: tuple[str, ...], stops: tuple[str, ...] | set[str]) -> None:
        """The nearest open element of ``names``, if no ``stops`` lies above it."""
        if any(open_[n] for n in names):
            for i in range(len(stack) - 1, 0, -1):
                if stack[i][0] in names:
                    return cut(i)
                if stack[i][0] in stops:
                    return

    at, n = 0, len(page)
    while at < n:
        lt = page.find("<", at)
        if lt < 0:
            buffer.append(page[at:])
            break
        if lt > at:
            buffer.append(page[at:lt])
        m = _TAG.match(page, lt)
        if not m:
            buffer.append("<")
            at = lt + 1
            continue
        at = m.end()
        name = (m[2] or m[5] or "").lower()
        if not name:
            continue
        if m[1] or m[4]:
            if name not in INLINE:
                flush()
            close(name)
            continue
        attributes = m[3] or m[6] or ""
        if name == "br" or name in VOID and name not in INLINE:
            flush()
            continue
        if name in VOID:
            continue
        if name in CLOSES_P and open_["p"]:
            flush()
            for i in range(len(stack) - 1, 0, -1):
                if stack[i][0] == "p":
                    cut(i)
                    break
                if stack[i][0] not in INLINE:
                    break
        if name not in INLINE:
            flush()
        if name in ("li", "dt", "dd", "option", "tr", "td", "th"):
            close_sibling((name,), ("ul", "ol", "dl", "table", "select"))
        if name in RAW:
            end = re.compile(rf"</{name}[\s/>]", re.I).search(page, at)
            at = end.start() if end else n
            if end:
                gt = page.find(">", at)
                at = gt + 1 if gt >= 0 else n
            continue
        if attributes.endswith("/") and name in ("path", "use", "circle", "rect"):
            continue
        _, weight, group, vouched = stack[-1]
        own = _weight(name, attributes, vouched)
        if own == 1.0 and not vouched and weight == 1.0 and (name in CONTAINERS or name == "h1"):
            own = VOUCHED
        if name in GROUPS and not vouched or own == DOUBTED:  # a part that may be an advert must surge by itself
            groups += 1
            group = groups
        if own != 1.0:
            flush()
        open_[name] += 1
        stack.append((name, min(weight, DOUBTED) if own == DOUBTED else weight * own, group, vouched or name in CONTAINERS and own > DOUBTED))
    flush()
    return lines


def kept_lines(lines: list[tuple[str, float, int]]) -> list[int]:
    """The lines from the first group that surges to the last one, before it dives for good."""
    weights: list[float] = []
    at: list[int] = []  # place of each line among the weights; groups are apart by a window
    for i, (text, weight, group) in enumerate(lines):
        if i and group != lines[i - 1][2]:
            weights += [0.0] * (WINDOW - 1)
        at.append(len(weights))
        weights.append(weight * len(text))
    sums = [sum(weights[i : i + WINDOW]) for i in range(len(weights))]
    if not sums or max(sums) <= 0:
        return []
    limit = min(SURGE, SURGE_SHARE * max(sums))
    surging = [max(sums[max(0, p - WINDOW + 1) : p + 1]) > limit for p in at]
    groups = {lines[i][2] for i, s in enumerate(surging) if s and weights[at[i]]}
    inside = [i for i, (_, weight, group) in enumerate(lines) if group in groups and weight]
    if not inside:
        return []
    return [i for i in range(inside[0], inside[-1] + 1) if lines[i][1] >= 1 or lines[i][1] and surging[i]]


def main_text(page: str | None) -> str:
    """The text between the first surge and the last dive of the page's lines."""
    lines = lines_of(page) if page else []
    return " ".join(lines[i][0] for i in kept_lines(lines))


def extract(pages: DataFrame, key: str = "page_id", url: str = "url", page: str = "html") -> DataFrame:
    """``key``, ``url``, ``text`` and its length in code points, one row per page."""
    src = pages.select(F.col(key).alias("_key"), F.col(url).alias("_url"), F.col(page).alias("_page"))
    schema = T.StructType([*src.schema.fields[:2], T.StructField("text", T.StringType()), T.StructField("n_chars", T.LongType())])

    def make(cols: list[list]) -> dict[str, list]:
        texts = [main_text(p) for p in cols[2]]
        return {"_key": cols[0], "_url": cols[1], "text": texts, "n_chars": [len(t) for t in texts]}

    return map_texts(src, 2, schema, make).withColumnsRenamed({"_key": key, "_url": url})
