"""Main text of web pages by two-pass block rules.

A page is cut into blocks at block-level tags.  First pass: what lies in a container that
cannot be article text (menus, page headers and footers, sidebars, notices, adverts, forms,
comments, scripts, styles, hidden parts) is left out; every other block is judged by link
density, length and stop-word density as good, bad, near or short.  Few stop words are no evidence
against a block, as the page may be in another language.  A class, id or role marks such a container
only as a whole name, and never one that holds an article or main part.  That a block lies in a marked
article or main part is one feature, if these parts hold at least half of the page's text: it allows
more links there, and beside it only long text with stop words is good.  Second pass: short and near
blocks inherit the label of their nearest decided neighbours; the page's ends count as neither.
"""

from __future__ import annotations

import re
from collections import Counter
from collections.abc import Iterator
from html.parser import HTMLParser
from typing import NamedTuple

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

# Tags that begin and end a block.
BLOCKS = frozenset(
    "address article aside blockquote body caption center dd details dialog dir div dl dt fieldset figcaption figure footer form "
    "h1 h2 h3 h4 h5 h6 head header hgroup hr html legend li main menu nav ol option p pre section summary table tbody td tfoot th "
    "thead title tr ul".split()
)
HEADINGS = frozenset("h1 h2 h3 h4 h5 h6".split())
# Tags without content.
VOID = frozenset("area base br col embed hr img input link meta param source track wbr".split())
# Tags whose content is never article text.
OUT = frozenset(
    "head title script style noscript template nav footer aside form button select option textarea iframe object svg canvas "
    "dialog menu audio video applet".split()
)
# Words of class, id and role that mark the same.
HINTS = frozenset(
    "ad ads adv advert adverts advertisement advertising banner sponsor sponsored promo promotion cookie cookies consent gdpr notice notices "
    "notification alert popup modal overlay newsletter subscribe subscription sidebar aside menu nav navbar navigation breadcrumb "
    "breadcrumbs footer comment comments commentlist reply replies respond disqus related recommended share sharing social widget "
    "pagination pager toolbar login signin signup search copyright contentinfo complementary masthead topbar skip".split()
)
# Words that a name made of several may have beside one of these.
BESIDE = frozenset(
    "site page main global primary secondary top bottom left right side inner outer container wrapper wrap box list area section block bar links "
    "link buttons button posts post article entry stories items item form panel unit slot region content".split()
)
# Words of a name that says what its element has or lacks, not what it is.
SAYS = frozenset("has with no without non not is show shows hide hides enable enabled disable disabled free open closed on off allow allowed".split())
# Words beside which a header belongs to the article.
OWN = frozenset("article post entry story content title page".split())
CLOSES_ITSELF = {"p": {"p"}, "li": {"li"}, "dt": {"dt", "dd"}, "dd": {"dt", "dd"}, "option": {"option"}, "tr": {"tr", "td", "th"}, "td": {"td", "th"}, "th": {"td", "th"}}
# Frequent function words of English, German, French and Spanish.
STOP = frozenset(
    "the of and to in a is that it for was on are as with he be at by this had not from or have an they which one you were "
    "der die und den von zu das mit sich des auf für ist im dem nicht ein eine als auch es an werden aus er hat dass sie nach wird bei "
    "de la le et les des en un du une que est pour qui dans par plus pas au sur ne se ce il sont avec son "
    "el los y del las por con para una su al lo como más pero sus o este ya entre".split()
)
LINKS, OWN_LINKS, SHORT, LONG, FEW = 0.2, 0.5, 70, 200, 0.15
_HIDDEN = re.compile(r"display\s*:\s*none|visibility\s*:\s*hidden", re.I)
_RIGHTS = re.compile(r"(©|\(c\)|copyright\b)", re.I)
_WORD = re.compile(r"[^\W\d_]+")


class Open(NamedTuple):
    """An open element and what holds within it."""

    tag: str
    out: bool
    own: bool
    heading: bool
    linked: bool
    marks: tuple[int, ...]


_ROOT = Open("", False, False, False, False, ())


def _named(name: str) -> bool:
    """Whether a class, id or role says that its element is not article text: one of HINTS, or several
    words that end in one or are all such or beside such, none of them in SAYS."""
    parts = [w for w in re.split(r"[^a-z0-9]+", name) if w]
    if not any(w in HINTS for w in parts) or any(w in SAYS for w in parts):
        return False
    return parts[-1] in HINTS or all(w in HINTS or w in BESIDE for w in parts)


class Blocks(HTMLParser):
    """Collects (text, letters within links, inside article or main, heading, numbers of the marks it lies in)."""

    def __init__(self) -> None:
        super().__init__(convert_charrefs=True)
        self.found: list[tuple[str, int, bool, bool, tuple[int, ...]]] = []
        self.stack: list[Open] = [_ROOT]
        self.count: Counter[str] = Counter()
        self.void_marks: set[int] = set()  # marks whose element holds an article or main part
        self.parts: list[str] = []
        self.linked = self.breaks = self.marks = 0

    def cut(self) -> None:
        text = " ".join("".join(self.parts).split())
        if text:
            here = self.stack[-1]
            self.found.append((text, min(self.linked, len(text)), here.own, here.heading, here.marks))
        self.parts, self.linked, self.breaks = [], 0, 0

    def handle_starttag(self, tag: str, attrs: list) -> None:
        if tag == "br":
            self.breaks += 1
            self.parts.append(" ")
            if self.breaks > 1:
                self.cut()
            return
        if tag in BLOCKS:
            self.cut()
        if tag in CLOSES_ITSELF:
            self._close_own(tag)
        if tag in VOID:
            return
        here = self.stack[-1]
        out, marks = here.out or tag in OUT or self._hidden(dict(attrs)), here.marks
        if not out and tag not in ("html", "body", "main", "article") and self._hinted(tag, dict(attrs), here.own):
            self.marks += 1
            marks = (*marks, self.marks)
        own = here.own or (tag in ("article", "main") and not out)
        if own and not here.own:
            self.void_marks.update(marks)
        self.stack.append(Open(tag, out, own, here.heading or tag in HEADINGS, here.linked or tag == "a", marks))
        self.count[tag] += 1

    def handle_startendtag(self, tag: str, attrs: list) -> None:
        self.handle_starttag(tag, attrs)
        if tag not in VOID:
            self.handle_endtag(tag)

    def handle_endtag(self, tag: str) -> None:
        if tag in BLOCKS:
            self.cut()
        if not self.count[tag]:
            return
        for k in range(len(self.stack) - 1, 0, -1):
            if self.stack[k].tag == tag:
                self._close(k)
                return
            if tag not in BLOCKS and self.stack[k].tag in BLOCKS:  # an inline end tag does not close blocks
                return

    def handle_data(self, data: str) -> None:
        here = self.stack[-1]
        if here.out:
            return
        if not data.isspace():
            self.breaks = 0
            if here.linked:
                self.linked += len(" ".join(data.split()))
        self.parts.append(data)

    def _close(self, k: int) -> None:
        self.count.subtract(x.tag for x in self.stack[k:])
        del self.stack[k:]

    def _close_own(self, tag: str) -> None:
        for k in range(len(self.stack) - 1, 0, -1):
            if self.stack[k].tag in CLOSES_ITSELF[tag]:
                self._close(k)
                return
            if self.stack[k].tag in BLOCKS:
                return

    @staticmethod
    def _hidden(attrs: dict) -> bool:
        return "hidden" in attrs or attrs.get("aria-hidden") == "true" or bool(_HIDDEN.search(attrs.get("style") or ""))

    @staticmethod
    def _hinted(tag: str, attrs: dict, own: bool) -> bool:
        names = " ".join(attrs.get(k) or "" for k in ("class", "id", "role")).lower().split()
        if tag == "header" or any(name.split("-")[-1] == "header" for name in names):
            return not own and not any(w in OWN for name in names for w in re.split(r"[^a-z0-9]+", name))
        return any(_named(name) for name in names)


def blocks(html: str | None) -> list[tuple[str, int, bool, bool]]:
    parser = Blocks()
    parser.feed(html or "")
    parser.close()
    parser.cut()
    return [block[:4] for block in parser.found if all(k in parser.void_marks for k in block[4])]


def _judge(text: str, linked: int, own: bool, marked: bool) -> str:
    density = linked / len(text)
    if density > (OWN_LINKS if own else LINKS) or (not own and len(text) < LONG and _RIGHTS.match(text)):
        return "bad"
    words = _WORD.findall(text.lower())
    stop = sum(w in STOP for w in words) / max(1, len(words)) >= FEW
    if marked and not own:
        return "good" if stop and len(text) > LONG else "bad"
    if len(text) < SHORT:
        return "bad" if linked and not own else "short"
    return "good" if stop or len(text) > LONG else "near"


def _marked(found: list[tuple[str, int, bool, bool]]) -> bool:
    """Whether the article and main parts hold at least half of the text that is not in links."""
    own = sum(len(text) - linked for text, linked, inside, _ in found if inside)
    return own > 0 and 2 * own >= sum(len(text) - linked for text, linked, *_ in found)


def classify(found: list[tuple[str, int, bool, bool]]) -> list[bool]:
    """Which blocks are text."""
    marked = _marked(found)
    first = [_judge(text, linked, own and marked, marked) for text, linked, own, _ in found]
    out = [k == "good" for k in first]

    def passed(kind: str, k: int) -> bool:
        return first[k] == "short" or (kind == "short" and first[k] == "bad" and marked and not found[k][2])

    sides: dict[str, list[list[bool | None]]] = {}
    for kind in ("short", "near"):  # the label of the nearest decided block on each side, None at the page's ends
        label: list[bool | None] = [None, None]
        before, after = [], []
        for k in range(len(first)):
            before.append(label[0])
            if not passed(kind, k):
                label[0] = first[k] in ("good", "near")
        for k in range(len(first) - 1, -1, -1):
            after.append(label[1])
            if not passed(kind, k):
                label[1] = first[k] in ("good", "near")
        sides[kind] = [before, after[::-1]]
    for k, kind in enumerate(first):
        if kind in sides:
            near = [side[k] for side in sides[kind] if side[k] is not None]
            out[k] = any(near) if kind == "near" else bool(near) and all(near)
    for k in range(len(found) - 2, -1, -1):  # a heading goes with the text right below it
        if found[k][3] and first[k] != "bad":
            out[k] = out[k] or out[k + 1]
    if not any(out):  # nothing long enough: what was not judged bad
        out = [kind != "bad" for kind in first]
    return out


def extract(html: str | None) -> str:
    found = blocks(html)
    return "\n".join(b[0] for b, keep in zip(found, classify(found), strict=True) if keep)


def _run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        texts = []
        for value in batch.column(2):
            text = extract(value.as_py())
            texts.append(text.encode("utf-8", "replace").decode("utf-8"))
        yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), pa.array(texts, pa.string()), pa.array([len(t) for t in texts], pa.int64())], ["page_id", "url", "text", "n_chars"])


def main_text(pages: DataFrame) -> DataFrame:
    """Text of every page (page_id, url, html); other columns are not read.

    Character references are decoded, white space within a block is one space, blocks are joined
    by a line feed.  A null or empty page, and one without text, gives an empty text.  Unclosed and
    misnested tags are taken as browsers do in the common cases.  Each row is a page, repeated or not.

    Returns page_id, url, text, n_chars.
    """
    rows = pages.select(F.col("page_id").cast("long").alias("page_id"), F.col("url").cast("string").alias("url"), F.col("html").cast("string").alias("html"))
    return rows.mapInArrow(_run, "page_id long, url string, text string, n_chars long")
