"""Path ratios against another reading of the page, and pages of any length or depth in bounded time."""

import random
import time
from collections import defaultdict
from html.parser import HTMLParser

import numpy as np
import pytest

from rasterchain.llm import html_extract


class Paths(HTMLParser):
    """Texts by the path of tags that leads to them."""

    def __init__(self):
        super().__init__()
        self.stack, self.texts = [], defaultdict(list)

    def handle_starttag(self, tag, attrs):
        self.stack.append((tag, *(v for _, v in attrs)))

    def handle_endtag(self, tag):
        self.stack.pop()

    def handle_data(self, data):
        if data.strip():
            self.texts[tuple(self.stack)].append(data.strip())


def test_path_ratios():
    rng = random.Random(5)
    words = ["sea", "rail,", "foot.", "winter;", "letters", "story:", "end!"]
    for _ in range(20):
        def build(depth):
            if not depth:
                return "".join(f"<p>{' '.join(rng.choice(words) for _ in range(rng.randrange(1, 30)))}</p>" for _ in range(rng.randrange(1, 4)))
            return "".join(f"<div class='c{rng.choice('abc')}'>{build(depth - 1)}</div>" for _ in range(rng.randrange(1, 4)))
        source = build(3)
        other = Paths()
        other.feed(source)
        text, marks = (np.array([sum(f(t) for t in texts) + (k and 1) for texts in other.texts.values()]) / [len(t) for t in other.texts.values()] for k, f in ((0, len), (1, lambda t: sum(c in ".,;:!?" for c in t))))
        smooth = [x if len(x) < 3 else np.array([0.25 * x[max(i - 1, 0)] + 0.5 * x[i] + 0.25 * x[min(i + 1, len(x) - 1)] for i in range(len(x))]) for x in (text, marks)]
        want = smooth[0] * smooth[1]
        page = html_extract.Page(source)
        got = html_extract.path_scores(html_extract.blocks_of(page))
        assert np.allclose(list(got.values()), want)
        # a block is content if its path's ratio reaches the share of the spread, or for what stands around it
        blocks = html_extract.blocks_of(page)
        kept = html_extract.content(blocks, page.paths, 0.3)
        limit = 0.3 * np.std(want) if len(want) > 1 else 0
        assert all(k for b, k in zip(blocks, kept, strict=True) if got.get(b.path, -1) >= limit)


PAGES = {
    "open tags": "<a " * 340_000,
    "nested": "<div>" * 100_000 + "x, y." + "</div>" * 100_000,
    "nested by name": "<div class=nav>" * 100_000 + "<p>some, text.</p>",
    "unmatched ends": "<div>" * 50_000 + "</em>" * 50_000,
    "headings within bold": "<p><div>" + "<b>" * 50_000 + "<h1>x." * 50_000,
    "sections without end": "<![CDATA[" * 100_000 + ">",
    "quotes without end": '<a b="' * 100_000 + ">",
    "angles": "<" * 1_000_000 + ">",
    "scripts": "<script>" * 50_000,
    "pieces": "<p>" + "<i>a</i> " * 100_000 + "</p>",
    "articles": "<article>" * 50_000 + "x, y. z",
}


@pytest.mark.parametrize("name", sorted(PAGES))
def test_long_and_deep_pages(name):
    start = time.process_time()
    html_extract.main_text(PAGES[name])
    assert time.process_time() - start < 5


def test_odd_markup():
    got = html_extract.main_text
    assert got("<p>A &#" + "9" * 6000 + "; b &#0000000000065; c.</p>") == "A � b A c."
    assert got("<p title='a > b'>One, two.</p><p title=\"x>y\" class='it'>Three, four.</p>") == "One, two. Three, four."
    assert got("<p>1 < 2 and 3 <4, so.</p>") == "1 < 2 and 3 <4, so."
    assert got("<figure><figcaption>A ship, at sea, in winter.</figcaption></figure><p>The ship, as told, came home; late.</p>") == "A ship, at sea, in winter. The ship, as told, came home; late."
