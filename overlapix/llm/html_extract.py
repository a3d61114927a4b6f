"""Main text of web pages by the distribution of text over lines.

Markup is stripped into lines: block elements and ``<br>`` end one.  Tags only
weigh: text of menus, forms, notices, comments and the like weighs nothing, nor
does text outside the article (or the main element) of a page that names one;
where a page names none, lines that are mostly links, and lines that read like
a foot note, weigh nothing either.  Weights are summed over windows of ``WINDOW``
lines.  A surge is where the sums rise from nothing, a dive where they fall back
to nothing; between them stands running text if some window reaches the page's
level.  What lies between such a surge and dive is kept whole, but for elements
that are not the article's.
"""

from __future__ import annotations

import re
from collections.abc import Iterator
from html import unescape

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

WINDOW = 3
#: A region is running text if some window of it holds this many characters, or half the page's best window.
SURGE = 80
#: Elements that what starts next closes, if nothing else does.
SHORT = frozenset("p li span a".split())

TAG = re.compile(r"<!--.*?(?:-->|\Z)|<[!?][^>]*+>|<(/?)([a-zA-Z][a-zA-Z0-9:-]*+)((?:[^<>\"']++|\"[^\"]*+\"|'[^']*+')*+)>|<(/?)([a-zA-Z][a-zA-Z0-9:-]*+)([^<>]*+)>", re.S)
ATTRIBUTE = re.compile(r"([a-zA-Z_:-]+)\s*=\s*(?:\"([^\"]*)\"|'([^']*)'|([^\s\"'>]+))")
RAW = frozenset("script style textarea title noscript template iframe svg math object canvas xmp noembed".split())
BLOCK = frozenset("address article aside blockquote body br button caption center dd details dialog dir div dl dt fieldset figcaption figure footer form frameset h1 h2 h3 h4 h5 h6 head header hgroup hr html legend li main menu nav ol optgroup option p pre search section select summary table tbody td tfoot th thead tr ul video audio".split())
VOID = frozenset("area base br col embed hr img input link meta param source track wbr".split())
#: Elements whose text is never the article's.
ASIDE = frozenset("nav footer aside form button select menu dialog head datalist search".split())
#: Words of class, id and role that mark such elements.
ASIDE_WORDS = frozenset("ad ads adv advert adverts advertisement advertising banner promo promotion promoted sponsor sponsored sponsors sidebar sidebars cookie cookies consent notice notices gdpr popup modal overlay newsletter subscribe subscription signup comment comments commentlist disqus respond replies reply menu menus nav navbar navigation breadcrumb breadcrumbs pagination pager footer masthead topbar toolbar share sharing social related recommended recommendations teaser teasers widget widgets login search contentinfo complementary alert hidden".split())
#: Words that mark a layout element, whatever stands beside them.
LAYOUT_WORDS = frozenset("has with without no content main article layout wrapper container page body grid row".split())
FOOT_NOTE = re.compile(r"^\s*(?:©|\(c\)|copyright\b|all rights reserved|cookie|privacy policy)", re.I)


def _marked(name: str, attributes: str, in_article: bool) -> bool:
    """Whether an opening tag starts an element that is not the article's."""
    if name in ASIDE or (name == "header" and not in_article):
        return True
    if not attributes or name in ("html", "body", "main"):
        return False
    for key, *values in ATTRIBUTE.findall(attributes):
        key, value = key.lower(), "".join(values).lower()
        if key in ("class", "id", "role"):
            for label in value.split():
                parts = set(re.split(r"[^a-z]+", label))
                if parts & ASIDE_WORDS and not parts & LAYOUT_WORDS:
                    return True
                if label == "header" and not in_article:
                    return True
        elif (key == "aria-hidden" and value == "true") or (key == "style" and re.search(r"display\s*:\s*none|visibility\s*:\s*hidden", value)):
            return True
    return bool(re.search(r"(?:^|\s)hidden(?:\s|=|/?$)", ATTRIBUTE.sub(" ", attributes)))


class Tag:
    __slots__ = ("attributes", "close", "closing", "end", "name", "start")

    def __init__(self, start: int, end: int, name: str, closing: bool, attributes: str) -> None:
        self.start, self.end, self.name, self.closing, self.attributes = start, end, name, closing, attributes
        self.close: int | None = None  # number of the tag that closes this one


def tags_of(html: str) -> list[Tag]:
    """Tags in page order, each opening one with its closing one.  What ``RAW``
    elements and comments hold is part of one long tag without a name.  One pass."""
    tags: list[Tag] = []
    open_: dict[str, list[int]] = {}
    pos = 0
    while m := TAG.search(html, pos):
        pos = m.end()
        name = (m[2] or m[5] or "").lower()
        closing, attributes = bool(m[1] or m[4]), m[3] or m[6] or ""
        if name in RAW and not closing and not attributes.endswith("/"):
            close = re.compile(rf"</{name}\s*>", re.I).search(html, pos)
            pos = close.end() if close else len(html)
            name = ""
        tag = Tag(m.start(), pos, name, closing, attributes)
        if name and closing:
            if open_.get(name):
                tags[open_[name].pop()].close = len(tags)
        elif name and name not in VOID and not attributes.endswith("/"):
            open_.setdefault(name, []).append(len(tags))
        tags.append(tag)
    return tags


class Line:
    """A line's text, how much of it is linked, the number of its article from 1,
    and whether it is in a main element.  A line without text stands for an element
    that is not the article's, or for the start of an article."""

    __slots__ = ("article", "linked", "main", "text")

    def __init__(self, text: str, linked: int = 0, article: int = 0, main: bool = False) -> None:
        self.text, self.linked, self.article, self.main = text, linked, article, main


def lines_of(html: str) -> list[Line]:
    """Lines in page order.  Elements that are never closed exclude nothing."""
    tags = tags_of(html)
    lines: list[Line] = []
    parts: list[str] = []
    linked = article = main = links = number = pos = i = 0

    def flush() -> None:
        nonlocal linked
        text = " ".join(unescape("".join(parts)).split()) if parts else ""
        parts.clear()
        if text:
            lines.append(Line(text, linked, number if article else 0, main > 0))
        linked = 0

    def gap() -> None:
        flush()
        if lines and lines[-1].text:
            lines.append(Line("", 0, number if article else 0, main > 0))

    blocks = [len(tags)] * (len(tags) + 1)  # from each tag on, the next that starts or ends a block
    for n in range(len(tags) - 1, -1, -1):
        blocks[n] = n if tags[n].name in BLOCK else blocks[n + 1]

    while i < len(tags):
        tag = tags[i]
        if tag.start > pos:
            parts.append(html[pos : tag.start])
            if links:
                linked += tag.start - pos
        pos = tag.end
        i += 1
        name = tag.name
        if not name:
            continue
        if not tag.closing and name not in VOID and not tag.attributes.endswith("/") and _marked(name, tag.attributes, article > 0):
            stop = tag.close
            if name in SHORT:  # closed by the block that starts or ends next, too
                j = blocks[i]
                while j < len(tags) and tags[j].name == name and tags[j].closing and j != stop:
                    j = blocks[j + 1]
                if j < len(tags) and (stop is None or j < stop):
                    gap()
                    pos, i = tags[j].start, j
                    continue
            if stop is not None:
                gap()
                pos, i = tags[stop].end, stop + 1
                continue
        if name in BLOCK:
            flush()
        if name == "article":
            if not tag.closing:
                if not article:
                    number += 1
                    lines += [Line("") for _ in range(WINDOW)]
                article += 1
            else:
                article = max(0, article - 1)
        elif name == "main":
            main = max(0, main + (-1 if tag.closing else 1))
        elif name == "a":
            links = 0 if tag.closing else 1
    if len(html) > pos:
        parts.append(html[pos:])
    flush()
    return lines


def weights(lines: list[Line]) -> list[int]:
    """What each line adds to the window sums; see the module."""
    if any(x.article and x.text for x in lines):
        return [len(x.text) if x.article else 0 for x in lines]
    within = any(x.main and x.text for x in lines)
    return [len(x.text) if (x.main or not within) and 2 * x.linked <= len(x.text) and not FOOT_NOTE.match(x.text) else 0 for x in lines]


def main_text(html: str | None) -> str:
    """The article's text; empty for null, empty or article-less pages."""
    lines = lines_of(html or "")
    named = any(x.article and x.text for x in lines)
    if not named:  # elements that are not the article's divide a page that names none
        lines = [y for x in lines for y in ([x] if x.text else [x] * WINDOW)]
    sizes = weights(lines)
    sums = [sum(sizes[max(0, i - WINDOW + 1) : i + 1]) for i in range(len(sizes))]
    level = min(SURGE, max(sums, default=0) / 2)
    keep: list[str] = []
    for start, end in regions(sizes, level):
        keep += [x.text for x in lines[start:end] if x.text and (x.article or not named)]
    return " ".join(keep)


def regions(sizes: list[int], level: float) -> Iterator[tuple[int, int]]:
    """Surge and dive points ``(first line, line after the last)``: runs of lines
    whose window sums stay above nothing and somewhere reach ``level``."""
    start, last, best = None, 0, 0
    for i in range(len(sizes) + WINDOW):
        inside = sum(sizes[max(0, i - WINDOW + 1) : i + 1])
        if i < len(sizes) and sizes[i]:
            start, last = (i, i) if start is None else (start, i)
        if start is None:
            continue
        if inside:
            best = max(best, inside)
            continue
        if best >= level > 0:
            yield start, last + 1
        start, best = None, 0


def _batches(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        texts = [main_text(x.as_py()) for x in batch.column(2)]
        yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), pa.array(texts, pa.string()), pa.array([len(t) for t in texts], pa.int64())], names=["page_id", "url", "text", "n_chars"])


def extract(pages: DataFrame, html: str = "html") -> DataFrame:
    """``page_id, url, text, n_chars``, one row per input row.  Null html counts as
    empty and gives an empty text; null ids and urls pass through; repeated rows
    stay; further columns are not read."""
    return pages.select("page_id", F.col("url").cast("string"), F.col(html).cast("string").alias("html")).mapInArrow(_batches, f"page_id {pages.schema['page_id'].dataType.simpleString()}, url string, text string, n_chars bigint")
