"""Main text of web pages by the distribution of text over line blocks.

A page's markup is stripped and each block-level element becomes a line. A line counts its characters outside links, or
nothing if links are more than half of it. Over sliding windows of lines the counts are summed: where the sum surges to
the threshold text begins, and where the lines dive to nothing and no window surges again it ends. What stands between
is kept whole, linked lines too. This decides on every page; the markup only weighs in:

* Elements that are no article by their kind, role or style (menus, forms, footers, ...) and containers that a class word
  calls so count nothing and are left out. A word is a hint only: it is told by the first or last part of a class name
  (`left-sidebar`, not `has-sidebar`), and an element around an article, or around a first heading with text, is no menu
  whatever it is called. If the words leave no text at all, they are not believed.
* Lines in an article or main element weigh four times as much. If the highest surge of the page is theirs, each of them
  counts as a surge and lines elsewhere count nothing; otherwise the element is not believed and its lines count like others.

Without any surge, all lines that count are kept. Null and empty pages have empty text. Unclosed, misnested and cut-off
markup is read much as browsers do: an element ends at its parent's end, and what is not a tag is text. Time grows
in proportion to the page, whatever its nesting."""

from __future__ import annotations

import html
import re
from collections.abc import Iterator
from itertools import accumulate
from typing import NamedTuple

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import types as T

#: Lines summed together, characters at which a window surges, and the weight of lines in an article or main element.
WINDOW, SURGE, MARKED = 3, 80, 4

#: Elements that end a line; hold no text whatever is in them; are no article by their kind; have raw content; never have an end.
_BLOCKS = frozenset("address article aside blockquote body br center dd details dialog dir div dl dt fieldset figcaption figure footer form h1 h2 h3 h4 h5 h6 header hgroup hr html legend li main menu nav ol option p pre section summary table tbody td tfoot th thead tr ul".split())
_NEVER = frozenset("script style noscript template svg math iframe object embed canvas audio video head title textarea select button label input".split())
_ASIDE = frozenset("form nav footer aside dialog menu header".split())
_RAW = frozenset("script style textarea title iframe".split())
_VOID = frozenset("area base br col embed hr img input link meta param source track wbr".split())
#: Containers, the only elements in an article that class words tell of.
_CONTAINERS = frozenset("div section ul ol dl table center article aside header footer details fieldset".split())
#: Words of class names for what is no article, anywhere and outside articles alone; first words that turn the meaning.
_WORDS = frozenset(
    "ad ads advert adverts advertisement advertisements advertising adsense sponsor sponsors sponsored promo promos promotion promotions cookie cookies consent gdpr notice notices popup modal overlay banner newsletter "
    "subscribe subscription signup share sharing sharebar social related recommend recommended recommendations sidebar sidebars widget widgets menu menus nav navbar navigation breadcrumb breadcrumbs pagination pager "
    "toolbar footer comment comments commentlist respond reply replies disqus".split()
)
_OUTER = _WORDS | frozenset("alert alerts login header masthead topbar copyright disclaimer discussion search tags hidden skip".split())
_TURNS = frozenset("has no not non with without is hide show".split())
_OF_TEXT = frozenset("post entry article story content page news section".split())
_NOISY_ROLES = frozenset("navigation banner contentinfo complementary search form dialog alert menu menubar toolbar".split())
_TOKEN = re.compile(r"<!--.*?(?:-->|\Z)|<[!?][^>]*(?:>|\Z)|<(/?)([a-zA-Z][a-zA-Z0-9:-]*+)((?>=\s*+\"[^\"]*+\"|=\s*+'[^']*+'|[^>])*+)(>|\Z)", re.S)
_ATTRIBUTE = re.compile(r"(?:^|[\s/\"'])(class|id|role|hidden|aria-hidden|style)(?:\s*=\s*(?:\"([^\"]*)\"|'([^']*)'|([^\s>]+)))?(?=[\s/>\"']|$)", re.I | re.S)
_UNSEEN = re.compile(r"display\s*:\s*none|visibility\s*:\s*hidden", re.I)
_PARTS = re.compile(r"[A-Z]?[a-z]+|[A-Z]+(?![a-z])")
_RIGHTS = re.compile(r"(?:©|\(c\)|copyright\b|all rights reserved)", re.I)
_WHITE = re.compile(r"\s+")
_HEADINGS = frozenset("h1 h2 h3 h4 h5 h6".split())
#: Elements that a start tag of the same kind ends, and those beyond which it does not look.
_SIBLINGS = {"p": ("p",), "li": ("li",), "dt": ("dt", "dd"), "dd": ("dt", "dd"), "tr": ("td", "th", "tr"), "td": ("td", "th"), "th": ("td", "th"), "option": ("option",)}
_SCOPES = frozenset("article main section div body html table ul ol dl td th blockquote nav aside footer header form".split())
_WALLS = frozenset("article main td nav aside footer header".split())


class Line(NamedTuple):
    """A block with text: its characters in links, whether an article or main element holds it, whether the
    markup calls it no article, and whether it does so by nothing but a class word."""

    text: str
    linked: int
    marked: bool = False
    aside: bool = False
    worded: bool = False


def _named(value: str, words: frozenset) -> bool:
    """Whether a class name's first or last part is one of the words."""
    for name in value.split():
        parts = [p.lower() for p in _PARTS.findall(name)]
        if parts and parts[0] not in _TURNS:
            if parts[0] in words or parts[-1] in words and not (parts[-1] == "header" and parts[0] in _OF_TEXT):
                return True
    return False


def _hints(tag: str, attributes: str, marked: bool) -> tuple[bool, bool, bool]:
    """(holds no text, no article by its kind, no article by a class word)."""
    never, kind, word = tag in _NEVER, tag in _ASIDE and not (marked and tag == "header"), False
    for name, *values in _ATTRIBUTE.findall(attributes) if attributes else ():
        name, value = name.lower(), next(filter(None, values), "")
        if name in ("class", "id"):
            word |= tag not in ("html", "body", "main") and (not marked or tag in _CONTAINERS) and _named(value, _WORDS if marked or tag == "article" else _OUTER)
        elif name == "role":
            kind |= value.lower() in _NOISY_ROLES
        else:
            never |= name == "hidden" or name == "aria-hidden" and value.lower() == "true" or name == "style" and bool(_UNSEEN.search(value))
    return never and tag not in ("html", "body"), kind, word


class _Reader:
    """Open elements of a page as a stack, with the places of each kind in it, and all elements that are hinted or marked."""

    def __init__(self):
        self.stack: list[tuple[str, int, bool]] = []  # kind, box, holds no text
        self.places: dict[str, list[int]] = {}
        self.scopes: list[int] = []
        self.walls: list[int] = []
        # boxes: the page, and elements that are hinted or marked; each with the box around it
        self.around, self.marked, self.kind, self.word, self.holds, self.first = [-1], [False], [False], [False], [False], [False]
        self.rows: list[tuple[str, int, int, bool]] = []  # text, linked, box, heading
        self.parts: list[str] = []
        self.linked_parts: list[str] = []

    def top(self) -> tuple[str, int, bool]:
        return self.stack[-1] if self.stack else ("", 0, False)

    def push(self, tag: str, box: int, never: bool) -> None:
        at = len(self.stack)
        self.stack.append((tag, box, never))
        self.places.setdefault(tag, []).append(at)
        if tag in _SCOPES:
            self.scopes.append(at)
        if tag in _WALLS:
            self.walls.append(at)

    def cut(self, at: int) -> None:
        while len(self.stack) > at:
            tag = self.stack.pop()[0]
            self.places[tag].pop()
            for held in (self.scopes, self.walls):
                if held and held[-1] == len(self.stack):
                    held.pop()

    def last(self, tag: str) -> int:
        found = self.places.get(tag)
        return found[-1] if found else -1

    def opens(self, tag: str) -> bool:
        return bool(self.places.get(tag))

    def end_line(self) -> None:
        if self.parts:
            text = _WHITE.sub(" ", "".join(self.parts)).strip()
            if text:
                linked = len(_WHITE.sub(" ", "".join(self.linked_parts)).strip())
                self.rows.append((text, min(linked, len(text)), self.top()[1], any(map(self.opens, _HEADINGS))))
            self.parts.clear()
            self.linked_parts.clear()

    def add(self, raw: str) -> None:
        if raw and not self.top()[2]:
            text = html.unescape(raw) if "&" in raw else raw
            self.parts.append(text)
            if self.opens("a"):
                self.linked_parts.append(text)

    def start(self, tag: str, attributes: str) -> None:
        for other in _SIBLINGS.get(tag, ()):
            if (at := self.last(other)) >= max(0, self.scopes[-1] if self.scopes else 0):
                self.cut(at)
        if tag in _BLOCKS and tag != "br" and (at := self.last("p")) > (self.scopes[-1] if self.scopes else -1):
            self.cut(at)  # a paragraph ends where the next block begins
        if tag in _VOID or attributes.endswith("/") and tag not in _BLOCKS:
            return
        _, box, above = self.top()
        never, kind, word = _hints(tag, attributes, self.marked[box])
        mark = tag in ("article", "main") and not word and not kind
        if mark or kind or word:
            self.around.append(box)
            self.marked.append(self.marked[box] or mark)
            self.kind.append(kind)
            self.word.append(word)
            self.holds.append(False)
            self.first.append(False)
            box = len(self.around) - 1
        if mark and not above:
            self.up(self.holds, box)
        if tag == "h1":
            self.up(self.first, box)
        self.push(tag, box, above or never)

    def up(self, flags: list[bool], box: int) -> None:
        while box >= 0 and not flags[box]:
            flags[box] = True
            box = self.around[box]

    def close(self, tag: str) -> None:
        at = self.last(tag)
        if at >= 0 and (tag in _SCOPES or at >= (self.walls[-1] if self.walls else -1)):
            self.cut(at)

    def lines(self) -> list[Line]:
        """The lines, once it is known what each element holds."""
        boxes = len(self.around)
        size = [0] * boxes
        for text, linked, box, heading in self.rows:
            if not heading:
                size[box] += _count(text, linked)
        for box in range(boxes - 1, 0, -1):
            size[self.around[box]] += size[box]
        aside, worded = [False] * boxes, [False] * boxes
        for box in range(1, boxes):
            up = self.around[box]
            # an element around an article, or around a first heading with text, is no menu whatever it is called
            around = self.holds[box] or self.first[box] and size[box] >= SURGE
            worded[box] = worded[up] or self.word[box] and not around
            aside[box] = aside[up] or self.kind[box] and not around
        out = []
        for text, linked, box, _ in self.rows:
            rights = not self.marked[box] and len(text) <= 2 * SURGE and bool(_RIGHTS.match(text))
            out.append(Line(text, linked, self.marked[box], aside[box] or worded[box] or rights, worded[box] and not aside[box]))
        return out


def lines(page: str) -> list[Line]:
    """Each block with text, in page order."""
    reader, at, size = _Reader(), 0, len(page)
    while at < size:
        tag = reader.top()[0]
        if tag in _RAW:
            close = re.compile(rf"</{tag}\s*(?:>|\Z)", re.I).search(page, at)
            at = close.end() if close else size
            reader.cut(len(reader.stack) - 1)
            continue
        here = page.find("<", at)
        if here < 0:
            reader.add(page[at:])
            break
        reader.add(page[at:here])
        token = _TOKEN.match(page, here)
        if not token:
            if page.startswith("</", here):
                end = page.find(">", here)
                at = size if end < 0 else end + 1
            else:
                reader.add("<")
                at = here + 1
            continue
        at = token.end()
        tag = (token[2] or "").lower()
        if not tag:
            continue
        if tag in _BLOCKS:
            reader.end_line()
        if token[1]:
            reader.close(tag)
        else:
            reader.start(tag, token[3])
    reader.end_line()
    return reader.lines()


def _count(text: str, linked: int) -> int:
    """Characters outside links; nothing where links are more than half."""
    return len(text) - linked if 2 * linked <= len(text) else 0


def surges(counts: list[int], window: int = WINDOW, surge: int = SURGE) -> list[tuple[int, int]]:
    """Half-open runs of lines from where a window's sum surges to where lines dive to nothing."""
    n, runs, i = len(counts), [], 0
    total = [0, *accumulate(counts)]
    high = [total[min(n, k + window)] - total[k] >= surge for k in range(n)]
    while i < n:
        if counts[i] and high[i]:
            j = i
            while j < n and (counts[j] or high[j]):
                j += 1
            runs.append((i, j))
            i = j
        else:
            i += 1
    return runs


def chosen(rows: list[Line], window: int = WINDOW, surge: int = SURGE) -> list[bool]:
    """Which lines are the article's."""
    counts = [0 if r.aside else _count(r.text, r.linked) for r in rows]
    if any(r.marked and not r.aside for r in rows):
        weighed = [c * (MARKED if r.marked else 1) for c, r in zip(counts, rows, strict=True)]
        total, own = [0, *accumulate(weighed)], [0, *accumulate(c if r.marked else 0 for c, r in zip(weighed, rows, strict=True))]
        runs = surges(weighed, window, surge) or [(0, len(rows))]
        a, b = max(runs, key=lambda run: total[run[1]] - total[run[0]])
        if 2 * (own[b] - own[a]) >= total[b] - total[a]:
            counts = [max(c, surge) if r.marked and not r.aside else 0 for c, r in zip(counts, rows, strict=True)]
    runs = surges(counts, window, surge)
    if not runs:
        return [c > 0 for c in counts]
    kept = [False] * len(rows)
    for a, b in runs:
        kept[a:b] = [not r.aside for r in rows[a:b]]
    return kept


def main_text(page: str | None, window: int = WINDOW, surge: int = SURGE) -> str:
    rows = lines(page or "")
    kept = chosen(rows, window, surge)
    if not any(kept) and any(r.worded for r in rows):  # class words alone do not void a page
        rows = [r._replace(aside=False) if r.worded else r for r in rows]
        kept = chosen(rows, window, surge)
    return "\n".join(r.text for r, k in zip(rows, kept, strict=True) if k)


def extract(pages: DataFrame, html_column: str = "html", to: str = "text") -> DataFrame:
    """pages without the html, with the text and n_chars, its code points; columns of these names are replaced."""
    kept = [c for c in pages.columns if c not in (html_column, to, "n_chars")]

    def rows(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            texts = [main_text(x) for x in batch.column(html_column).to_pylist()]
            yield pa.RecordBatch.from_arrays([*(batch.column(c) for c in kept), pa.array(texts, pa.string()), pa.array(map(len, texts), pa.int64())], [*kept, to, "n_chars"])

    schema = T.StructType([pages.schema[c] for c in kept] + [T.StructField(to, T.StringType()), T.StructField("n_chars", T.LongType())])
    return pages.select(*kept, html_column).mapInArrow(rows, schema)
