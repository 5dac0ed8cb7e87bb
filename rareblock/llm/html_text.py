"""Main text of web pages by tag-path ratios.

A page is cut into blocks. Blocks of one root-to-leaf tag path are taken together: their mean length outside
links times their punctuation is the path's ratio. Ratios are smoothed over paths that are close in the tree,
so a headline beside long paragraphs counts with them; own and smoothed ratio are fused by their geometric
mean, and paths below a share of the best one are dropped, on every page. Inside an article or main element a
path counts at least its smoothed ratio. A name that tells of navigation, adverts, notices, comments and the like
makes the ratios of all paths under its element small; it bans nothing by itself, and says nothing where the
element holds most of the page's text and no article without such a name is beside it. Elements whose tag has such a meaning, and hidden ones, never take part.
"""

from __future__ import annotations

import html
import re
from collections import defaultdict
from collections.abc import Iterator
from dataclasses import dataclass, field
from functools import cached_property

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

# A quoted value may hold tags only if white space or the tag's end follows it; a quote that is never closed is a
# character like others. No choice is taken back, so a tag is read in one pass.
_VALUE = r"(?:\"[^\"<>]*+\"|'[^'<>]*+'|\"[^\"]*+\"(?=[\s/>])|'[^']*+'(?=[\s/>])|[^\s>\"'][^\s>]*+)"
_NAMED = rf"[^\s/>][^\s/>=]*+(?:\s*+=\s*+{_VALUE})?+"
_TOKEN = re.compile(rf"<!--.*?(?:-->|$)|<!\[CDATA\[.*?(?:\]\]>|$)|<[!?][^>]*(?:>|$)|</(?:[^a-zA-Z>][^>]*)?>|<(/?)([a-zA-Z][^\s/>]*+)((?:[\s/]++|{_NAMED})*+)(?:>|$)", re.S)
_ATTRIBUTE = re.compile(rf"([^\s/>][^\s/>=]*+)(?:\s*+=\s*+({_VALUE}))?+")

# Element names of HTML by what they mean here.
VOID = frozenset("area base br col embed hr img input link meta param source track wbr".split())
RAW = frozenset("script style textarea title xmp noscript template iframe svg math".split())
INLINE = frozenset("a abbr acronym b bdi bdo big br cite code data del dfn em font i ins kbd mark q ruby rb rp rt rtc s samp small span strike strong sub sup time tt u var wbr img".split())
NEVER = frozenset("head nav aside footer form button select option datalist label fieldset legend menu dialog object embed audio video canvas map noframes frameset applet".split())
CLOSES_P = frozenset("address article aside blockquote center details dialog dir div dl fieldset figcaption figure footer form h1 h2 h3 h4 h5 h6 header hgroup hr main menu nav ol p pre section summary table ul".split())
HINTS = frozenset(
    "ad ads advert adverts advertisement advertising adbox adslot sponsor sponsored promo promotion promoted banner nav navbar navigation navigate menu breadcrumb breadcrumbs sidebar rail "
    "footer masthead topbar toolbar cookie cookies consent gdpr notice notices notification alert newsletter subscribe subscription signup login social share sharing related recommended recommendations "
    "comment comments commentlist respond reply replies disqus popup modal overlay pagination pager widget search searchbox copyright disclaimer legal skip complementary contentinfo".split()
)
_END_BEFORE = {"li": {"li"}, "dt": {"dt", "dd"}, "dd": {"dt", "dd"}, "tr": {"tr", "td", "th"}, "td": {"td", "th"}, "th": {"td", "th"}, "option": {"option"}}
_LIST_WALL = {"li": {"ul", "ol", "menu"}, "dt": {"dl"}, "dd": {"dl"}, "tr": {"table"}, "td": {"tr", "table"}, "th": {"tr", "table"}, "option": {"select"}}
_PUNCTUATION = re.compile(r"[.,;:!?…。，！？]")
_WORDS = re.compile(r"[a-z]+")
_SPLIT_CASE = re.compile(r"(?<=[a-z0-9])(?=[A-Z])")


#: Names of reader comments, which are not text of the page however long they are.
READERS = frozenset("comment comments commentlist respond reply replies disqus".split())
#: What is left of a ratio under an element with such a name; of one paragraph in an article, by its own name.
HINTED, HINTED_PART = 0.0001, 0.2
PARTS = frozenset("p h1 h2 h3 h4 h5 h6 blockquote pre li dt dd td th figcaption".split())


@dataclass
class Hint:
    """An element with a telling name, and the weight of the text under it."""

    factor: float
    readers: bool
    mass: float = 0.0


@dataclass
class Block:
    tags: tuple[str, ...]
    inside: bool  # of an article or main element
    hints: tuple[Hint, ...] = ()
    weight: float = 1.0
    parts: list[str] = field(default_factory=list)
    linked: int = 0

    @property
    def path(self) -> tuple:
        """The tags, and apart from others of the same tags where names make it count less."""
        return (*self.tags, self.weight)

    @cached_property
    def text(self) -> str:
        return " ".join(html.unescape("".join(self.parts)).split())

    def mass(self) -> float:
        return max(0, len(self.text) - self.linked) * (1 + len(_PUNCTUATION.findall(self.text)))


def _judged(tag: str, attributes: str, inside: bool) -> tuple[bool, Hint | None]:
    """Whether an element is banned by tag or hidden, and what its names hint at."""
    if tag in NEVER or (tag == "header" and not inside):
        return True, None
    hint = None
    for name, value in _ATTRIBUTE.findall(attributes):
        name, value = name.lower(), value.strip("\"'")
        if name == "hidden" or name == "style" and re.search(r"display\s*:\s*none|visibility\s*:\s*hidden", value):
            return True, None
        if name in ("class", "id", "role"):
            told = HINTS & set(_WORDS.findall(_SPLIT_CASE.sub(" ", value).lower()))
            if told & READERS or told and tag not in ("html", "body", "article", "main"):
                hint = Hint(HINTED_PART if inside and tag in PARTS and not told & READERS else HINTED, bool(told & READERS))
    return False, hint


def blocks_of(page: str) -> list[Block]:
    """Blocks of text in page order, without those of banned elements, with their weights. Markup may be unclosed or
    cut off."""
    stack: list[tuple[str, bool, Hint | None]] = []  # name, banned, what it hints at
    out: list[Block] = []
    current: Block | None = None
    banned = inside = links = 0

    def pop() -> None:
        nonlocal banned, inside, links
        name, bad, _ = stack.pop()
        banned -= bad
        inside -= name in ("article", "main")
        links -= name == "a"

    def close_upto(names: set[str], wall: set[str]) -> None:
        for i in range(len(stack) - 1, -1, -1):
            if stack[i][0] in names:
                while len(stack) > i:
                    pop()
                return
            if stack[i][0] in wall:
                return

    def add(text: str) -> None:
        nonlocal current
        if banned or not text:
            return
        if current is None:
            if not text.strip():
                return
            current = Block(tuple(name for name, _, _ in stack if name not in INLINE), inside > 0, tuple(h for _, _, h in stack if h))
            out.append(current)
        current.parts.append(text)
        if links:
            current.linked += len(text.strip())

    at = 0
    while at < len(page):
        m = _TOKEN.search(page, at)
        add(page[at : m.start() if m else len(page)])
        if not m:
            break
        at = m.end()
        if m[0].startswith("<![CDATA["):
            add(m[0][9:].removesuffix("]]>"))
        if m[2] is None:
            continue
        tag, closing = m[2].lower(), m[1]
        if tag not in INLINE:
            current = None
        elif tag == "br":
            add(" ")
        if closing:
            if any(name == tag for name, _, _ in stack):
                close_upto({tag}, set())
            continue
        if tag in RAW:
            if not m[3].rstrip().endswith("/"):
                end = re.compile(rf"</{re.escape(tag)}\s*>", re.I).search(page, at)
                at = end.end() if end else len(page)
            continue
        if tag in VOID:
            continue
        if tag in CLOSES_P:
            close_upto({"p"}, {"table", "td", "th", "button", "object"})
        if tag in _END_BEFORE:
            close_upto(_END_BEFORE[tag], _LIST_WALL[tag])
        if tag == "body" or stack and stack[-1][0] == "head" and tag not in RAW | VOID:
            close_upto({"head"}, set())
        bad, hint = _judged(tag, m[3], inside > 0)
        stack.append((tag, bad, hint))
        banned += bad
        inside += tag in ("article", "main")
        links += tag == "a"
    out = [b for b in out if b.text]
    for b in out:
        for h in b.hints:
            h.mass += b.mass()
    half = sum(b.mass() for b in out) / 2
    plain_article = any(b.inside and not b.hints for b in out)
    for b in out:
        for h in b.hints:
            b.weight *= h.factor if h.readers or plain_article or h.mass <= half else 1.0
    return out


def path_ratios(blocks: list[Block]) -> dict[tuple, float]:
    """Mean length outside links times one and mean punctuation, of each path's blocks, times the path's weight."""
    length, marks, many = defaultdict(float), defaultdict(float), defaultdict(int)
    for b in blocks:
        length[b.path] += max(0, len(b.text) - b.linked)
        marks[b.path] += len(_PUNCTUATION.findall(b.text))
        many[b.path] += 1
    return {p: p[-1] * length[p] / many[p] * (1 + marks[p] / many[p]) for p in many}


def smoothed(ratios: dict[tuple, float], width: float = 1.0) -> dict[tuple, float]:
    """Gaussian means over the distance between paths: steps up to the common element and down. Paths that names make
    count less take their share of what others give them."""
    paths = list(ratios)
    if not paths:
        return {}

    def distance(a: tuple, b: tuple) -> int:
        a, b = a[:-1], b[:-1]
        same = next((i for i, (x, y) in enumerate(zip(a, b, strict=False)) if x != y), min(len(a), len(b)))
        return len(a) + len(b) - 2 * same

    near = np.exp(-np.array([[distance(a, b) for b in paths] for a in paths]) ** 2 / (2 * width**2))
    weight = np.array([p[-1] for p in paths])
    values = weight * (near @ (np.array([ratios[p] for p in paths]) / weight)) / near.sum(1)
    return dict(zip(paths, values.tolist(), strict=True))


def main_text(page: str, share: float = 0.05, width: float = 1.0) -> str:
    """The blocks on content paths, joined by newlines; paths made of links are dropped."""
    blocks = blocks_of(page)
    if not blocks:
        return ""
    own = path_ratios(blocks)
    marked = {b.path for b in blocks if b.inside}
    fused = {p: max(v if p in marked else 0.0, (own[p] * v) ** 0.5) for p, v in smoothed(own, width).items()}
    floor = share * max(fused.values())
    linked, total = defaultdict(int), defaultdict(int)
    for b in blocks:
        linked[b.path] += b.linked
        total[b.path] += len(b.text)
    wanted = {p for p in fused if 2 * linked[p] <= total[p] and fused[p] >= floor}
    return "\n".join(b.text for b in blocks if b.path in wanted)


def extract(pages: DataFrame, id_col: str = "page_id", url_col: str = "url", html_col: str = "html") -> DataFrame:
    """page_id, url, text and n_chars of every row; a null or empty page, or one without content, has an empty text."""
    types = {f.name: f.dataType.simpleString() for f in pages.schema.fields}

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            texts = [main_text(p or "") for p in batch.column(2).to_pylist()]
            yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), pa.array(texts, pa.string()), pa.array([len(t) for t in texts], pa.int64())], ["page_id", "url", "text", "n_chars"])

    made = pages.select(F.col(id_col).alias("page_id"), F.col(url_col).alias("url"), F.col(html_col).alias("html"))
    return made.mapInArrow(run, f"page_id {types[id_col]}, url {types[url_col]}, text string, n_chars long")
