"""Main text of web pages by tag-path ratios.

Each text of a page belongs to the path of tags that leads to it. Texts of one path are
written by one template, so the lengths and the punctuation marks of all texts of a path,
over the number of its texts, tell articles from menus better than any single text does.
The two ratios are smoothed over the paths in page order, fused by their product, and paths
above a threshold (a share of the spread over the page) are content, within article and main
elements as elsewhere. Parts that by their tag are never part of the article do not take part.
Parts named by class like such parts take part only where nothing outside them has a ratio
near theirs. What is short between content of one element, and headings of content, stay.

A page is read once from left to right, in time and memory that grow with its length: paths
and chains of named parts are numbers in a table of (parent, name), and open elements are
found by their tag.
"""

from __future__ import annotations

import html
import re
from collections.abc import Iterator
from functools import cached_property
from itertools import groupby

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

#: Fixed values of HTML.
VOID = frozenset("area base br col embed hr img input link meta param source track wbr".split())
RAW = frozenset("script style textarea title xmp noscript iframe noembed noframes".split())
INLINE = frozenset("a abbr acronym b bdi bdo big cite code data del dfn em font i ins kbd label mark q rp rt ruby s samp small span strike strong sub sup time tt u var wbr".split())
CLOSES_P = frozenset("address article aside blockquote center details dialog dir div dl fieldset figcaption figure footer form h1 h2 h3 h4 h5 h6 header hgroup hr main menu nav ol p pre section table ul".split())
SAME = {"li": ("li",), "dt": ("dt", "dd"), "dd": ("dt", "dd"), "tr": ("tr", "td", "th"), "td": ("td", "th"), "th": ("td", "th"), "option": ("option",), "tbody": ("tr", "td", "th", "thead", "tbody"), "tfoot": ("tr", "td", "th", "tbody")}
SCOPE = frozenset("table ul ol dl select body article section div main".split())
#: Parts that are never the article.
APART = frozenset("head nav footer aside form script style noscript template button select option textarea iframe object svg canvas dialog menu input label title audio video map".split())
APART_NAME = re.compile(r"(?i)(?:^|[\s_-])(?:ads?|advert\w*|banner|sponsor\w*|promo\w*|nav\w*|menu\w*|breadcrumbs?|sidebar|side|aside|footer|foot|cookies?|consent|notices?|notifications?|alert|popup|modal|overlay|newsletter|subscribe|signup|login|search|share|sharing|social|comments?|comment-?list|replies|reply|disqus|related|recommended|recirc|widgets?|toolbar|pagination|pager|tags?|masthead|topbar|copyright|legal|disclaimer|gdpr|paywall|skip|byline-share|outbrain|taboola)(?:$|[\s_-])|(?:^|[\s_-])(?:site|page|global|top|main)-?header(?:$|[\s_-])")
APART_ROLE = frozenset("navigation banner contentinfo complementary search dialog alertdialog alert menu menubar toolbar form".split())
TAG = re.compile(r"[a-zA-Z][^\s/>]*")
#: What ends a tag, or begins a quoted value within it.
STOP = re.compile(r">|=\s*([\"'])")
LONG_REFERENCE = re.compile(r"&#0*[1-9][0-9]{7,};?")
NAMES = re.compile(r"(?i)(?:^|\s)(class|id|role|hidden|style|aria-hidden)(?:\s*=\s*(?:\"([^\"]*)\"|'([^']*)'|([^\s>]+)))?")
PUNCTUATION = re.compile(r"[.,;:!?。，、；：！？]")
SPACES = re.compile(r"\s+")
KERNEL = np.array([0.25, 0.5, 0.25])
HIDDEN = re.compile(r"(?i)display\s*:\s*none|visibility\s*:\s*hidden")
HEADINGS = frozenset(("h1", "h2", "h3", "h4", "h5", "h6"))


def plain(raw: str) -> str:
    """Character references decoded, white space as single blanks."""
    return SPACES.sub(" ", html.unescape(LONG_REFERENCE.sub("\ufffd", raw))).strip()


class Chains:
    """Chains of names as numbers: 0 is the empty one, others are a chain and one more name."""

    def __init__(self):
        self.parent, self.name, self.depth = [0], [""], [0]
        self.known: dict[tuple[int, str], int] = {}

    def add(self, parent: int, name: str) -> int:
        number = self.known.setdefault((parent, name), len(self.parent))
        if number == len(self.parent):
            self.parent.append(parent)
            self.name.append(name)
            self.depth.append(self.depth[parent] + 1)
        return number

    def spans(self) -> tuple[list[int], list[int]]:
        """First and last number of each chain's extensions, itself included, in an order that keeps extensions together."""
        n = len(self.parent)
        size = [1] * n
        for k in range(n - 1, 0, -1):  # a chain comes before its extensions
            size[self.parent[k]] += size[k]
        first, free = [0] * n, [1] * n
        for k in range(1, n):
            up = self.parent[k]
            first[k] = first[up] + free[up]
            free[up] += size[k]
        return first, [a + k - 1 for a, k in zip(first, size, strict=True)]


class Page:
    """Texts of a page: (path, apart, chain of named parts, block number, text)."""

    def __init__(self, source: str):
        self.texts: list[tuple[int, bool, int, int, str]] = []
        self.paths, self.parts = Chains(), Chains()
        #: open elements: tag, path, apart, named parts around, within an article or main element
        self.open: list[tuple[str, int, bool, int, bool]] = [("", 0, False, 0, False)]
        #: where elements of a tag are open
        self.at: dict[str, list[int]] = {}
        self.block = 0
        self._read(source)

    def _text(self, raw: str) -> None:
        if raw:
            _, path, apart, named, _ = self.open[-1]
            self.texts.append((path, apart, named, self.block, raw))

    def _cut(self, k: int) -> None:
        """Closes the open elements from the k-th on."""
        while len(self.open) > k:
            self.at[self.open.pop()[0]].pop()

    def _last(self, tags) -> int:
        return max((self.at[t][-1] for t in tags if self.at.get(t)), default=0)

    def _imply(self, tag: str) -> None:
        """Closes what the start of tag ends: a paragraph, or an earlier item of its own list."""
        ends = ("p",) if tag in CLOSES_P else SAME.get(tag, ())
        while ends and (k := self._last(ends)) > self._last(SCOPE):
            self._cut(k)
            if tag in CLOSES_P or tag not in ("tr", "tbody", "tfoot"):
                return

    def _read(self, source: str) -> None:
        at = begin = 0
        last = source.rfind(">")
        quoted = sections = True
        while 0 <= (start := source.find("<", at)) < last:
            if source.startswith("<!--", start):
                end = source.find("-->", start + 4)
                self._text(source[begin:start])
                at = begin = end + 3 if end >= 0 else len(source)
                continue
            if sections and source.startswith("<![CDATA[", start):
                end = source.find("]]>", start)
                sections = end >= 0
                if sections:
                    self._text(source[begin:start])
                    at = begin = end + 3
                    continue
            if source[start + 1] in "!?":
                self._text(source[begin:start])
                at = begin = source.find(">", start) + 1
                continue
            close = source[start + 1] == "/"
            m = TAG.match(source, start + 1 + close)
            if not m:
                at = start + 1
                continue
            end = -1
            if quoted:
                end = self._end(source, m.end())
                quoted = end >= 0  # a quote that never ends is none, nor are those after it
            if end < 0:
                end = source.find(">", m.end())
            self._text(source[begin:start])
            at = begin = self._tag(source, m[0].lower(), close, source[m.end() : end], end + 1)
        self._text(source[begin:])

    @staticmethod
    def _end(source: str, at: int) -> int:
        """Where the tag ends, past quoted values; -1 if a quote is left open."""
        while m := STOP.search(source, at):
            if not m[1]:
                return m.start()
            at = source.find(m[1], m.end()) + 1
            if not at:
                return -1
        return -1

    def _tag(self, source: str, tag: str, close: bool, attributes: str, after: int) -> int:
        """Opens or closes an element; where reading goes on."""
        if tag not in INLINE:
            self.block += 1
        if close:
            if self.at.get(tag):
                self._cut(self.at[tag][-1])
            return after
        if tag in VOID:
            return after
        self._imply(tag)
        _, path, apart, named, article = self.open[-1]
        names, hidden = "", False
        for name, a, b, c in NAMES.findall(attributes):
            value, name = a or b or c, name.lower()
            if name in ("class", "id"):
                names += " " + value
            elif name == "role":
                hidden |= value.lower() in APART_ROLE
            elif name == "hidden" or name == "aria-hidden" and value.lower() == "true" or name == "style" and HIDDEN.search(value):
                hidden = True
        apart = apart or hidden or tag in APART or tag == "header" and not article
        if tag in ("article", "main"):
            if tag == "article" and self.at.get("article"):
                named = self.parts.add(named, "article")  # an article within an article is a reader's comment
            article = True
        elif tag not in ("html", "body") and names and APART_NAME.search(names.strip()):
            named = self.parts.add(named, f"{tag}.{re.sub(r'[0-9]+', '', names.strip())}")
        if attributes.endswith("/") and tag in ("svg", "path"):
            return after
        if tag in RAW:
            end = re.compile(rf"(?i)</{re.escape(tag)}\s*>").search(source, after)
            return end.end() if end else len(source)
        if tag not in INLINE or tag == "a":
            # names of classes belong to the path; a changing number does not
            mark = re.sub(r"\d+", "", ".".join(names.split()[:2]))
            path = self.paths.add(path, f"{tag}.{mark}" if mark else tag)
        self.at.setdefault(tag, []).append(len(self.open))
        self.open.append((tag, path, apart, named, article))
        return after


class Block:
    """Texts of one block: links within it belong to its path, a block of nothing but links has a path of its own."""

    def __init__(self, number: int, base: int, named: int):
        self.number, self.base, self.named = number, base, named
        self.parts: list[str] = []
        self.linked = True

    def add(self, link: bool, raw: str) -> None:
        self.parts.append(raw)
        self.linked &= link or not raw.strip()

    @property
    def path(self) -> tuple[int, bool]:
        return self.base, self.linked

    @cached_property
    def text(self) -> str:
        return plain("".join(self.parts))


def tag_of(name: str) -> str:
    return name.partition(".")[0]


def blocks_of(page: Page) -> list[Block]:
    out: list[Block] = []
    for path, apart, named, number, raw in page.texts:
        if not apart:
            link = tag_of(page.paths.name[path]) == "a"
            base = page.paths.parent[path] if link else path
            if not out or (out[-1].number, out[-1].base, out[-1].named) != (number, base, named):
                out.append(Block(number, base, named))
            out[-1].add(link, raw)
    return out


def path_scores(blocks: list[Block], smooth: bool = True) -> dict[tuple[int, bool], float]:
    """Fused ratio of each path."""
    paths: dict[tuple[int, bool], list[float]] = {}
    for b in blocks:
        if text := b.text:
            p = paths.setdefault(b.path, [0, 0, 0])
            p[0] += len(text)
            p[1] += len(PUNCTUATION.findall(text))
            p[2] += 1
    if not paths:
        return {}
    sums = np.array(list(paths.values()), float)
    ratios = sums[:, 0] / sums[:, 2], (sums[:, 1] + 1) / sums[:, 2]
    text, marks = [x if len(x) < 3 or not smooth else np.convolve(np.pad(x, 1, "edge"), KERNEL, "valid") for x in ratios]
    return dict(zip(paths, (text * marks).tolist(), strict=True))


def unnamed(blocks: list[Block], parts: Chains, share: float) -> list[Block]:
    """Blocks outside named parts; where only named parts have a ratio near the best one, those and what is around them.

    A single block, as of an advertisement, does not make a named part the article while there is text elsewhere.
    """
    scores = path_scores(blocks, smooth=False)
    best: dict[int, float] = {}
    filled: dict[int, int] = {}
    for b in blocks:
        best[b.named] = max(best.get(b.named, 0.0), scores.get(b.path, 0.0))
        filled[b.named] = filled.get(b.named, 0) + bool(b.text)
    best = {n: v for n, v in best.items() if filled[n] > (1 if n else 0)} or best
    near = [n for n, v in best.items() if v >= share * max(best.values())]
    depth = min(parts.depth[n] for n in near)
    around = set()
    for n in near:
        while parts.depth[n] <= depth and n not in around:
            around.add(n)
            n = parts.parent[n]
    return [b for b in blocks if b.named in around]


def content(blocks: list[Block], paths: Chains, share: float) -> list[bool]:
    """Whether each block is content: by the ratio of its path, or as a heading of content, or between content of its element."""
    scores = path_scores(blocks)
    limit = share * float(np.std(list(scores.values()))) if len(scores) > 1 else 0.0
    good = [scores.get(b.path, -1.0) >= limit for b in blocks]
    kept = list(good)
    low, high = paths.spans()
    last, at = -1, -1
    for i, b in enumerate(blocks):
        if good[i]:
            around = b.base if b.linked else paths.parent[b.base]
            if at >= 0 and around == last:
                for j in range(at + 1, i):
                    kept[j] |= not blocks[j].linked and low[around] <= low[blocks[j].base] <= high[around]
            last, at = around, i
    #: ranks of headings to come that are followed by content before a heading of their rank
    follows = [False] * 7
    for i in range(len(blocks) - 1, -1, -1):
        tag = tag_of(paths.name[blocks[i].base])
        if tag in HEADINGS:
            rank = int(tag[1])
            kept[i] |= follows[rank]
            follows[rank:] = [False] * (7 - rank)
        elif good[i]:
            follows = [True] * 7
    return kept


def main_text(source: str | None, share: float = 0.3) -> str:
    """The article of a page: blocks in page order, joined by one space; empty for null or empty pages."""
    if not source:
        return ""
    page = Page(source)
    candidates = blocks_of(page)
    if not any(b.text for b in candidates):
        return ""
    candidates = unnamed(candidates, page.parts, share)
    chosen = [b for b, keep in zip(candidates, content(candidates, page.paths, share), strict=True) if keep]
    whole = ("".join(x for b in same for x in b.parts) for _, same in groupby(chosen, key=lambda b: b.number))
    return " ".join(t for t in map(plain, whole) if t)


def extract(pages: DataFrame, html_col: str = "html", keep: tuple[str, ...] = ("page_id", "url")) -> DataFrame:
    """(kept columns, text, n_chars long), one row per input row.

    Null and empty pages, and pages without content, give an empty text. Pages may be of any
    length and need not be well formed. Repeated rows give repeated rows.
    """

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for at in range(0, b.num_rows, 500):
                part = b.slice(at, 500)
                texts = [main_text(x) for x in part.column(len(keep)).to_pylist()]
                yield pa.RecordBatch.from_arrays([*(part.column(i) for i in range(len(keep))), pa.array(texts, pa.string()), pa.array([len(t) for t in texts], pa.int64())], names=[*keep, "text", "n_chars"])

    kinds = ", ".join(f"`{c}` {pages.schema[c].dataType.simpleString()}" for c in keep)
    return pages.select(*keep, html_col).mapInArrow(run, f"{kinds}, text string, n_chars long")


def op9_html_extraction(spark, sf_dir: str) -> DataFrame:
    return extract(spark.read.parquet(f"{sf_dir}/pages.parquet")).select("page_id", "url", F.coalesce("text", F.lit("")).alias("text"), "n_chars")
