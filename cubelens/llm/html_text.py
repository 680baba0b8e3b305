"""Main text of web pages: the maximum-scoring run of words and tags.

A page is a sequence of words (positive) and tags (negative); the run of largest sum is its
content region, found in one linear scan, and nothing but the run decides where the region
begins and ends. What a tag costs is learned from labelled pages, those that mark their own
article: twice the words that on average follow the tag outside of articles, times the share of
it that stands outside, so that a typical piece of a page's frame loses more than its words
gain. The marks themselves are labels only; they are never looked at when a page is scored.
Words inside elements of another role (menus, forms, comments, ...) count against a run, and
those that a run spans are left out of its text.
"""

from __future__ import annotations

import html
import re
import zlib
from collections import defaultdict
from collections.abc import Iterator
from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from cubelens.llm.arrow import map_rows, slices, texts

#: A word's score, and that of one in boilerplate.
WORD_SCORE, BOILER_SCORE = 1.0, -0.25
#: The least that a tag costs, and what one costs of which nothing was learned (a text tag: the least).
TAG_LEAST, TAG_UNKNOWN = 0.02, 0.25
#: Names (class words, ids) are counted in this many buckets; one with log-odds of standing in articles below this is boilerplate's.
NAME_BUCKETS, NAME_ODDS = 1 << 16, -3.0

#: Element names by role.
RAW = frozenset("script style noscript template iframe svg object canvas textarea annotation annotation-xml".split())
SKIP = frozenset("nav aside footer form button select option menu dialog head title".split()) | RAW
MATH = frozenset("math semantics mi mn mo ms mtext mspace mrow mfrac msqrt mroot mstyle mpadded mphantom menclose msub msup msubsup munder mover munderover mmultiscripts mtable mtr mtd".split())
INLINE = MATH | frozenset("a abbr acronym b bdi bdo big br cite code del dfn em font i img ins kbd label mark q s samp small span strike strong sub sup time tt u var wbr".split())
VOID = frozenset("area base br col embed hr img input link meta param source track wbr".split())
BOILER_WORDS = frozenset("ad ads advert adverts advertisement banner sponsor sponsored promo promotion cookie cookies consent notice gdpr popup modal overlay newsletter subscribe signup sidebar side nav navbar navigation menu breadcrumb breadcrumbs header masthead footer comment comments disqus reply replies respond share sharing social related recommended widget toolbar pagination pager skip login search".split())
#: What may stand beside them in a class or id of several words; any other word makes it a name of content or of a layout.
BESIDE = frozenset("area articles bar block bottom box button container content element footer form global group holder inner item items left links list main menu outer panel posts primary region right row secondary section site slot stories text top unit wrap wrapper zone".split())
#: Names of what is no content however many words it holds; others may name a layout around the content.
NEVER = frozenset("comment comments disqus reply replies respond related recommended ad ads advert adverts advertisement sponsor sponsored promo promotion cookie cookies consent notice gdpr newsletter subscribe signup share sharing social breadcrumb breadcrumbs pagination pager".split())
#: Elements of running text: the listed names say nothing about them (a paragraph about a share price).
TEXT_TAGS = frozenset("p h1 h2 h3 h4 h5 h6 blockquote pre figure figcaption details summary".split())
HEADINGS = frozenset("h1 h2 h3 h4 h5 h6".split())
BOILER_ROLES = frozenset("navigation banner contentinfo complementary search form dialog menu menubar alert alertdialog".split())
ARTICLE = frozenset(("article", "main"))

_TOKEN = re.compile(
    r"<!--.*?(?:-->|\Z)|<!\[CDATA\[.*?(?:\]\]>|\Z)|<[!?][^>]*(?:>|\Z)"
    r"|<(?P<close>/?)(?P<name>[A-Za-z][^\s/>]*)(?P<attrs>(?:[^>\"']|\"[^\"]*\"|'[^']*')*)(?:>|\Z)"
    r"|<(?P<bent_close>/?)(?P<bent>[A-Za-z][^\s/>]*)(?P<bent_attrs>[^>]*)(?:>|\Z)"  # an unbalanced quote: the tag ends at the next >
    r"|</[^>]*(?:>|\Z)|(?P<text>[^<]+|<)",
    re.S,
)
_MARK = re.compile(r"<(?:article|main)\b", re.I)
_ATTR = re.compile(r"""(class|id|role|hidden|aria-hidden|itemprop)(?:\s*=\s*("[^"]*"|'[^']*'|[^\s>]+))?""", re.I)
_PART = re.compile(r"[A-Za-z][a-z]*|[A-Z]+")
_CLOSES_P = frozenset("address article aside blockquote div dl fieldset footer form h1 h2 h3 h4 h5 h6 header hr main nav ol p pre section table ul".split())
_SAME_CLOSES = {"li": ("li",), "dt": ("dt", "dd"), "dd": ("dt", "dd"), "tr": ("tr", "td", "th"), "td": ("td", "th"), "th": ("td", "th"), "option": ("option",)}


#: How surely an element is boilerplate: a SOFT one is not if it turns out to hold the page's content.
SOFT, SURE, HARD = 1, 2, 3


def _bucket(token: str) -> int:
    return zlib.crc32(token.lower().encode("utf-8", "surrogatepass")) % NAME_BUCKETS


def _names(attrs: str) -> list[str]:
    """The class words and the id of a tag."""
    return [w for key, value in _ATTR.findall(attrs) if key.lower() in ("class", "id") for w in value.strip("\"'").split()] if attrs else []


def _named(token: str) -> tuple[int, bool]:
    """What a class or id says: its words are boilerplate's, and none is another's; and whether it names a header only."""
    parts = [token.lower()] if token.lower() in BOILER_WORDS else [p.lower() for p in _PART.findall(token)]
    found = BOILER_WORDS.intersection(parts)
    if not found or not all(p in BOILER_WORDS or p in BESIDE for p in parts):
        return 0, False
    return (SURE if found & NEVER else SOFT), found <= {"header", "masthead"}


def _boiler(name: str, attrs: str, learned: frozenset[int]) -> tuple[int, bool]:
    """How surely a tag opens boilerplate, and whether it opens a header, about which its content and place decide."""
    if name in SKIP:
        return (SOFT if name == "form" else HARD), False
    sure, header = 0, name == "header"
    if not attrs or name in ("html", "body"):
        return sure, header
    for key, value in _ATTR.findall(attrs):
        key, value = key.lower(), value.strip("\"'")
        if key == "hidden" or key == "aria-hidden" and value == "true":
            return HARD, False
        if key == "role" and value.lower() in BOILER_ROLES:
            sure = max(sure, SOFT)
        if key in ("class", "id"):
            for w in value.split():
                if _bucket(w) in learned:
                    sure = max(sure, SOFT)
                if name not in TEXT_TAGS:
                    listed, head = _named(w)
                    header |= head
                    sure = max(sure, 0 if head else listed)
    return sure, header


@dataclass
class Element:
    """An open or closed element: its label (the outermost article around it), the range of blocks it holds, and whether it stands in boilerplate."""

    name: str
    parent: Element | None
    depth: int
    boiler: int
    article: Element | None
    header: Element | None
    first: int
    names: list[str]
    last: int = 0
    bad: bool = False
    holds_article: bool = False
    heading: bool = False
    menu: bool = False


@dataclass
class Block:
    """A run of inline content between block tags, with the tags that stand before it."""

    parts: list[str] = field(default_factory=list)
    tags: list[tuple[str, Element | None]] = field(default_factory=list)
    boiler: bool = False
    element: Element | None = None

    @property
    def text(self) -> str:
        return " ".join("".join(self.parts).split())


def blocks_of(page: str | None, learned: frozenset[int] = frozenset()) -> list[Block]:
    """The blocks of a page in order, whitespace-only ones included if tags stand before them."""
    return parse(page, learned)[0]


def parse(page: str | None, learned: frozenset[int] = frozenset()) -> tuple[list[Block], list[Element]]:
    """The blocks and the elements of a page, boilerplate marked."""
    out, now, stack, all_of = [], Block(), [], []
    page, at = page or "", 0

    def cut() -> None:
        nonlocal now
        now.element = stack[-1] if stack else None
        out.append(now)
        now = Block()

    def pop(to: int) -> None:
        while len(stack) > to:
            stack.pop().last = len(out)

    while at < len(page):
        m = _TOKEN.match(page, at)
        at = m.end()
        if m["text"] is not None:
            now.parts.append(html.unescape(m["text"]))
            continue
        name, close, attrs = (m["name"], m["close"], m["attrs"]) if m["name"] else (m["bent"], m["bent_close"], m["bent_attrs"])
        if name is None:
            continue
        name = name.lower()
        if name in ("annotation", "annotation-xml"):  # a formula's source: the formula's line goes on
            end = None if close else re.compile(rf"</{name}\s*>", re.I).search(page, at)
            at = at if close else end.end() if end else len(page)
            continue
        if name in INLINE and not (name != "br" and not close and attrs and _boiler(name, attrs, learned)[0]):
            if name == "br":
                now.parts.append(" ")
            if name == "br" or not any(x.name == name for x in stack):
                now.tags.append((name, None))
                continue
        cut()
        if close:
            shut = None
            for k in range(len(stack) - 1, -1, -1):
                if stack[k].name == name:
                    shut = stack[k]
                    pop(k)
                    break
            now.tags.append((name, shut))
            continue
        if name in RAW:
            now.tags.append((name, None))
            end = re.compile(rf"</{re.escape(name)}\s*>", re.I).search(page, at)
            at = end.end() if end else len(page)
            continue
        closes = ("p",) if name in _CLOSES_P else _SAME_CLOSES.get(name, ())
        while stack and (stack[-1].name in closes or name in ("body", "article", "main") and stack[-1].name == "head"):
            pop(len(stack) - 1)
        if name in VOID or attrs.rstrip().endswith("/"):
            now.tags.append((name, None))
        else:
            up = stack[-1] if stack else None
            boiler, head = _boiler(name, attrs, learned)
            here = Element(name, up, len(stack), boiler, up.article if up else None, up.header if up else None, len(out), _names(attrs))
            if here.header is not None:
                here.header.heading |= name in HEADINGS
                here.header.menu |= name in ("nav", "form", "ul", "menu")
            if head:
                here.header = here
            if name in ARTICLE and here.article is None:
                here.article = here
                while up is not None and not up.holds_article:
                    up.holds_article, up = True, up.parent
            now.tags.append((name, here))
            stack.append(here)
            all_of.append(here)
    cut()
    pop(0)
    _settle(out, all_of)
    return out, all_of


def _settle(blocks: list[Block], elements: list[Element]) -> None:
    """Mark what stands in boilerplate.

    A header is the page's if it stands right in the body, has a menu or form, or no heading.
    A SOFT container with more words than all blocks outside of it that are no boilerplate holds
    the content and is none.
    """
    for e in elements:  # parents come first
        if e.header is e and (e.parent is None or e.parent.name in ("body", "html") or e.menu or not e.heading):
            e.boiler = max(e.boiler, SOFT if e.name != "header" else HARD)

    def mark() -> None:
        for e in elements:
            e.bad = e.boiler > 0 or e.parent is not None and e.parent.bad
        for b in blocks:
            b.boiler = b.element is not None and b.element.bad

    mark()
    if all(e.boiler != SOFT for e in elements):
        return
    size = np.array([len(b.text.split()) for b in blocks], int)
    for e in elements:
        if e.boiler == SOFT and not (e.parent and e.parent.bad):
            hard = np.array([_hard(b.element, e) for b in blocks[e.first : e.last]], bool)
            if size[e.first : e.last][~hard].sum() > size[[not b.boiler for b in blocks]].sum():
                e.boiler = 0
                mark()


def _hard(at: Element | None, top: Element) -> bool:
    """Whether an element between ``at`` and ``top`` is boilerplate of its own."""
    while at is not None and at is not top:
        if at.boiler:
            return True
        at = at.parent
    return False


def best_run(scores: np.ndarray) -> tuple[int, int]:
    """Start and end of the contiguous run of largest sum, the longest of equal ones; (0, 0) if none is positive."""
    best, run, start, found = 0.0, 0.0, 0, (0, 0)
    for i, x in enumerate(scores.tolist()):
        if run < 0:
            run, start = 0.0, i
        run += x
        if run > best + 1e-9 or run > 0 and abs(run - best) <= 1e-9 and i + 1 - start > found[1] - found[0]:
            best, found = run, (start, i + 1)
    return found


@dataclass(frozen=True)
class Weights:
    """What each tag costs, in words, and the buckets of class words and ids that stand outside of articles."""

    tags: dict[str, float]
    names: frozenset[int] = frozenset()


def default_weights() -> dict[str, float]:
    """Costs of tags of which nothing was learned; the empty name stands for all others."""
    return {"": -TAG_UNKNOWN} | dict.fromkeys((TEXT_TAGS | INLINE) - {"a"}, -TAG_LEAST)


def region(blocks: list[Block], weights: dict[str, float]) -> tuple[int, int]:
    """The blocks between the ends of the best run of tag and word scores.

    Marks of articles cost nothing, as if they were not there; tags of boilerplate cost the
    least, since its words count against the run already.
    """
    scores, owner = [], []
    other = weights.get("", -TAG_UNKNOWN)
    for i, b in enumerate(blocks):
        for t, e in b.tags:
            if t in ARTICLE:
                continue
            scores.append(-TAG_LEAST if e is not None and e.bad else weights.get(t, other))
            owner.append(i)
        n = len(b.text.split())
        if n:
            scores.append(n * (BOILER_SCORE if b.boiler else WORD_SCORE))
            owner.append(i)
    if not scores:
        return 0, 0
    a, z = best_run(np.array(scores))
    return (owner[a], owner[z - 1] + 1) if z > a else (0, 0)


def main_text(page: str | None, weights: Weights | dict[str, float]) -> str:
    """Text blocks of the best run that stand in no boilerplate, one to a line."""
    if isinstance(weights, dict):
        weights = Weights(weights)
    blocks = blocks_of(page, weights.names)
    a, z = region(blocks, weights.tags)
    return "\n".join(t for b in blocks[a:z] if not b.boiler and (t := b.text))


def learn(pages: DataFrame) -> Weights:
    """Weights from all pages that mark an article, in one pass.

    Of each tag: how often it stands with article text and outside, and the words behind it
    outside (a block's words shared out among the tags before it). Of each class word and id: the
    elements inside articles and those outside that hold none. Tags that this module does not
    know are counted as one, names in hashed buckets, so the driver gets tables of bounded size.
    Without labelled pages the costs are those of ``default_weights``.
    """
    known = SKIP | INLINE | VOID | _CLOSES_P | set(_SAME_CLOSES) | TEXT_TAGS | {"html", "body", "head", "tbody", "thead", "label"}

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        tags, names = defaultdict(lambda: np.zeros(3)), defaultdict(lambda: np.zeros(3))
        for part in slices(batches):
            for page in texts(part.column(0)):
                if not _MARK.search(page):
                    continue
                blocks, elements = parse(page)
                if not any(e.article for e in elements):
                    continue
                for b in blocks:
                    inside = b.element is not None and b.element.article is not None and not b.boiler
                    words = 0 if inside else len(b.text.split())
                    for t, _ in b.tags:
                        if t in ARTICLE:
                            continue
                        tags[t if t in known else ""] += (1, 0, 0) if inside else (0, 1, words / len(b.tags))
                for e in elements:
                    if e.names and not e.holds_article:
                        for k in set(map(_bucket, e.names)):
                            names[k] += (0, 1, 0) if e.article is None else (1, 0, 0)
        rows = [(t, None, *x) for t, x in sorted(tags.items())] + [(None, k, *x) for k, x in sorted(names.items())]
        kinds = (pa.string(), pa.int32(), pa.float64(), pa.float64(), pa.float64())
        yield pa.record_batch([pa.array([r[k] for r in rows], kind) for k, kind in enumerate(kinds)], ["tag", "name", "i", "o", "w"])

    rows = pages.select("html").mapInArrow(run, "tag string, name int, i double, o double, w double")
    rows = rows.groupBy("tag", "name").agg(F.sum("i").alias("i"), F.sum("o").alias("o"), F.sum("w").alias("w")).collect()
    costs = default_weights()
    for r in rows:
        if r.tag is not None:
            share, words = (r.o + 1) / (r.i + r.o + 2), (r.w + TAG_UNKNOWN) / (r.o + 1)
            costs[r.tag] = -max(TAG_LEAST, 2 * share * words)
    return Weights(costs, frozenset(r.name for r in rows if r.name is not None and np.log((r.i + 0.5) / (r.o + 0.5)) <= NAME_ODDS))


def extract(pages: DataFrame, weights: Weights | None = None) -> DataFrame:
    """(page_id, url, text, n_chars), one row per row of ``pages``.

    A null, empty or textless page gives the empty text. Repeated rows and null ids are kept;
    columns other than page_id, url and html are not read. Weights are learned from ``pages``
    unless given.
    """
    weights = learn(pages) if weights is None else weights

    def run(part: pa.RecordBatch) -> pa.RecordBatch:
        out = [main_text(p, weights) for p in texts(part.column(2))]
        return pa.record_batch([part.column(0).cast(pa.int64()), part.column(1), pa.array(out, pa.string()), pa.array([len(t) for t in out], pa.int64())], ["page_id", "url", "text", "n_chars"])

    return map_rows(pages.select("page_id", "url", "html"), run, "page_id long, url string, text string, n_chars long")
