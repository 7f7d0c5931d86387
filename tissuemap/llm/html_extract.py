"""Main text of web pages by line-block distribution.

Markup is read once with one pattern. Scripts, styles, forms and other elements
that never hold article text go with their contents, and so do elements whose tag,
role, class or id says that they are navigation, headers, footers, sidebars,
notices, adverts or comments. What is left falls into blocks at block-level tags.

Text lengths of the blocks are summed over a sliding window. Where the sums rise
above a threshold the text surges, where they return to zero it dives; the blocks
between a surge and the next dive make a stretch, and the stretch with the most
text is the article, joined by others that are not much smaller. Link text counts
as nothing in the sums. An ``article`` or ``main`` element weighs in: its letters
count ``WEIGHT`` times, links included, and its edges are dives.

Defined results: null or empty pages give an empty text; a page without markup is
one block; unclosed and stray tags are tolerated; ties go to the first stretch;
every row is treated alone, so repeated rows and empty tables need no care.
"""

from __future__ import annotations

import html
import re
from collections import Counter
from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import DataFrame

TOKEN = re.compile(r"<!--.*?(?:-->|\Z)|<!\[CDATA\[(.*?)(?:\]\]>|\Z)|<[!?][^>]*(?:>|\Z)|<(/?)([a-zA-Z][\w:-]*)((?:=\s*\"[^\"]*\"|=\s*'[^']*'|[^>])*)(?:>|\Z)", re.S)
ATTRIBUTE = re.compile(r"([\w:-]+)\s*=\s*(?:\"([^\"]*)\"|'([^']*)'|([^\s\"'>]+))", re.S)
SPACE = re.compile(r"\s+")
#: Elements whose content is text for a machine, closed only by their own tag.
RAW = frozenset("script style template noscript textarea title iframe xmp noembed noframes".split())
#: Elements that hold no article text.
VOID_TEXT = frozenset("nav footer aside form button select dialog menu svg canvas object audio video map head fieldset datalist".split()) | RAW
#: Elements that may stand in a head; any other tag, and text, ends it.
HEAD = frozenset("base basefont bgsound link meta noframes noscript script style template title".split())
#: Elements without content.
EMPTY = frozenset("area base br col embed hr img input link meta param source track wbr".split())
BLOCK = frozenset(
    "address article aside blockquote body center dd details dialog dir div dl dt fieldset figcaption figure footer form h1 h2 h3 h4 h5 h6 "
    "header hgroup hr html legend li main menu nav ol optgroup option p pre section summary table tbody td tfoot th thead tr ul caption".split()
)
#: Elements that a new block-level start tag closes.
IMPLIED = {"p": BLOCK, "li": frozenset({"li"}), "dt": frozenset({"dt", "dd"}), "dd": frozenset({"dt", "dd"}), "tr": frozenset({"tr"}), "td": frozenset({"td", "th", "tr"}), "th": frozenset({"td", "th", "tr"}), "option": frozenset({"option"})}
MARKED = frozenset(
    "ad ads adbox adslot advert adverts advertisement advertising adsense banner sponsor sponsored promo promotion nav navbar navigation "
    "menu submenu breadcrumb breadcrumbs header masthead topbar footer foot sidebar aside rail widget widgets cookie cookies consent gdpr notice notices "
    "notification alert popup modal overlay newsletter subscribe subscription signup login share sharing social related recommended "
    "comment comments commentlist disqus replies reply respond discussion pagination pager tags toolbar skip hidden".split()
)
#: Words that say nothing on their own: a compound name of a marked word and these
#: is marked (``comment-list``), one with any other word is not (``share-price``).
PLAIN = frozenset(
    "list item items wrap wrapper container box block area section bar content inner outer link links button buttons form slot unit "
    "post posts article articles story stories entry top bottom left right main site page group panel text body title heading "
    "primary secondary global module region holder row col column js the and by of".split()
)
#: With one of these a header belongs to the text.
TITLED = frozenset("article entry post story content title heading".split())
REMARKS = frozenset("comment comments reply replies".split())
NAME_PART = re.compile(r"[-_:]+|(?<=[a-z])(?=[A-Z])")
ROLES = frozenset("navigation banner contentinfo complementary search form dialog alert alertdialog menu menubar toolbar".split())
WIDTH = 3
#: Letters of text in ``WIDTH`` blocks at which the text surges.
SURGE = 80
#: How often a letter within article or main counts.
WEIGHT = 20
#: Another stretch belongs to the article if it has this share of the largest.
SHARE = 0.25


def _marked(name: str, inside_article: bool) -> bool:
    """Whether one class or id says that its element is not article text."""
    parts = [x.lower() for x in NAME_PART.split(name) if x]
    marks = {x for x in (name.lower(), *parts) if x in MARKED}
    if TITLED.intersection(parts) or inside_article and not {"site", "page", "global", "top"}.intersection(parts):
        marks -= {"header"}
    if not marks:
        return False
    return name.lower() in marks or all(x in MARKED or x in PLAIN or x.replace("x", "").isdigit() for x in parts)


def _boilerplate(tag: str, attributes: str, inside_article: bool) -> bool:
    if tag in VOID_TEXT or tag == "header" and not inside_article:
        return True
    if not attributes or tag in ("html", "body"):
        return False
    for name, *values in ATTRIBUTE.findall(attributes):
        name = name.lower()
        value = next((v for v in values if v), "")
        if tag in ("article", "main"):
            # such an element is text, unless it is a reader's remark
            if name in ("class", "id") and any(x.lower() in REMARKS for part in value.split() for x in (part, *NAME_PART.split(part))):
                return True
        elif name == "role" and value.lower() in ROLES or name == "aria-hidden" and "true" in values:
            return True
        elif name in ("class", "id") and any(_marked(x, inside_article) for x in value.split()):
            return True
    return tag not in ("article", "main") and bool(re.search(r"(?:^|\s)hidden(?:\s|$|=)|display\s*:\s*none", attributes))


class _Blocks:
    """Blocks of one page in order: text, letters in links, within an article."""

    def __init__(self, page: str) -> None:
        self.done: list[tuple[str, int, bool]] = []
        self.parts: list[str] = []
        self.linked = 0
        # tag, whether it starts a dropped element, whether it starts an article
        self.stack: list[tuple[str, bool, bool]] = []
        self.open: Counter[str] = Counter()  # tags on the stack
        self.dropped = self.articles = self.links = 0
        self.at_article = False
        self._read(page)
        self._break()

    def _break(self) -> None:
        if self.parts:
            text = SPACE.sub(" ", html.unescape("".join(self.parts))).strip()
            if text:
                self.done.append((text, self.linked, self.at_article))
        self.parts, self.linked = [], 0
        self.at_article = self.articles > 0

    def _text(self, raw: str) -> None:
        if raw and not raw.isspace():
            self._end_head()
        if not self.dropped and raw:
            self.parts.append(raw)
            if self.links:
                self.linked += len(raw)

    def _end_head(self) -> None:
        """Close a head whose end tag is omitted."""
        if self.stack and self.stack[-1][0] == "head":
            self._pop()

    def _pop(self) -> None:
        tag, drop, article = self.stack.pop()
        self.open[tag] -= 1
        self.dropped -= drop
        self.articles -= article
        self.links -= tag == "a"
        if tag in BLOCK:
            self._break()

    def _close(self, tag: str) -> None:
        if self.open[tag]:
            # a stray inline tag must not close the blocks around it
            if tag not in BLOCK:
                for i in range(len(self.stack) - 1, -1, -1):
                    if self.stack[i][0] == tag:
                        if not any(t in BLOCK for t, _, _ in self.stack[i + 1 :]):
                            while len(self.stack) > i:
                                self._pop()
                        else:
                            t, drop, _ = self.stack.pop(i)
                            self.open[t] -= 1
                            self.dropped -= drop
                            self.links -= t == "a"
                        return
            while self.stack:
                last = self.stack[-1][0]
                self._pop()
                if last == tag:
                    return
        elif tag in BLOCK:
            self._break()

    def _read(self, page: str) -> None:
        at = 0
        while m := TOKEN.search(page, at):
            self._text(page[at : m.start()])
            at = m.end()
            if m[1] is not None:
                self._text(html.escape(m[1], False))
            if not m[3]:
                continue
            tag = m[3].lower()
            if m[2]:
                self._close(tag)
                continue
            if tag not in HEAD:
                self._end_head()
            if tag in RAW:
                end = re.compile(rf"</{tag}\s*>", re.I).search(page, at)
                at = end.end() if end else len(page)
                continue
            if tag in BLOCK:
                if self.stack and tag in IMPLIED.get(self.stack[-1][0], ()):
                    self._pop()
                elif tag == "p" and self.open["p"] and not any(t in BLOCK and t != "p" for t, _, _ in self.stack[[t for t, _, _ in self.stack].index("p") :]):
                    while self.stack and self.stack[-1][0] != "p":
                        self._pop()
                    self._pop()
                self._break()
            elif tag == "br":
                self._text(" ")
            if tag in EMPTY or m[4].endswith("/"):
                continue
            drop = _boilerplate(tag, m[4], self.articles > 0)
            self.dropped += drop
            article = tag in ("article", "main") and not self.dropped
            self.stack.append((tag, drop, article))
            self.open[tag] += 1
            self.links += tag == "a"
            self.articles += article
            self.at_article |= article
        self._text(page[at:])


def stretches(lengths: list[int], width: int = WIDTH, surge: int = SURGE) -> list[tuple[int, int]]:
    """Index ranges from each surge of the window sums to the next dive."""
    sums = [sum(lengths[i : i + width]) for i in range(len(lengths))]
    out, at = [], 0
    while at < len(sums):
        if sums[at] < surge or not lengths[at]:
            at += 1
            continue
        end = at
        while end < len(sums) and sums[end] > 0:
            end += 1
        out.append((at, end))
        at = end
    return out


def curve(blocks: list[tuple[str, int, bool]]) -> tuple[list[int], list[int]]:
    """Letters that each point of the curve counts, and the block it stands for;
    -1 marks the points of silence at the edges of an article."""
    lengths, owner, before = [], [], False
    for i, (text, linked, own) in enumerate(blocks):
        if own != before:
            lengths += [0] * WIDTH
            owner += [-1] * WIDTH
        free = len(text) - linked if linked < len(text) / 2 else 0
        lengths.append(WEIGHT * len(text) if own else max(0, free))
        owner.append(i)
        before = own
    return lengths, owner


def extract(page: str | None) -> str:
    """The main text of one page, blocks separated by empty lines."""
    if not page:
        return ""
    blocks = _Blocks(page).done
    lengths, owner = curve(blocks)
    found = stretches(lengths)
    mass = [sum(lengths[a:z]) for a, z in found]
    keep = [x for x, m in zip(found, mass, strict=True) if m >= SHARE * max(mass)]
    if not any(own for _, _, own in blocks):
        # without edges of an article, what lies between its parts belongs to it
        keep = [(keep[0][0], keep[-1][1])] if keep else [(0, len(lengths))]
    elif not keep:
        keep = [(i, i + 1) for i, at in enumerate(owner) if at >= 0 and blocks[at][2]]
    return "\n\n".join(blocks[owner[i]][0] for a, z in keep for i in range(a, z) if lengths[i])


def _extract(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for b in batches:
        text = [extract(x) for x in b.column("html").to_pylist()]
        own = [pa.array(text, pa.string()), pa.array([len(x) for x in text], pa.int64())]
        yield pa.record_batch([b.column("page_id"), b.column("url"), *own], ["page_id", "url", "text", "n_chars"])


def main_text(pages: DataFrame) -> DataFrame:
    """page_id, url, text, n_chars of every page."""
    kinds = {f.name: f.dataType.simpleString() for f in pages.schema}
    return pages.select("page_id", "url", "html").mapInArrow(_extract, f"page_id {kinds['page_id']}, url {kinds['url']}, text string, n_chars long")
