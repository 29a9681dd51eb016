"""The path ratios decide on pages with article elements too, and no part of an article is lost."""

from rasterchain.llm import html_extract

FIRST = "<p>The first part of the story tells, in some length, of a journey by sea, by rail, and on foot.</p><p>It had, as such stories do, a start, a middle, and an end; few remember them all.</p>"
SECOND = "<p>The second part, which is as long, goes on with the return, the winter, and the letters that came.</p>"
MENU = "<nav><a href=x>Home</a></nav>"


def parts(*fragments):
    return " ".join(x for f in fragments for x in f.replace("<p>", "").replace("</p>", "\n").strip().split("\n"))


def got(body):
    return html_extract.main_text(f"<html><body>{MENU}{body}<footer>All rights, all.</footer></body></html>")


def test_an_article_in_two_elements():
    assert got(f"<article>{FIRST}</article><article>{SECOND}</article>") == parts(FIRST, SECOND)


def test_a_teaser_article_beside_plain_text():
    assert got(f"<article class='teaser'><span>Read more</span></article><div class='text'>{FIRST}{SECOND}</div>") == parts(FIRST, SECOND)


def test_names_that_only_look_apart():
    for open_, close in (("<article class='post tag-news'>", "</article>"), ("<div class='has-sidebar'>", "</div>"), ("<div class='no-sidebar'><article class='tag-news'>", "</article></div>")):
        assert got(f"{open_}{FIRST}{SECOND}{close}<div class='sidebar'><span>Latest</span></div>") == parts(FIRST, SECOND)


def test_ratios_decide_within_an_article():
    assert got(f"<article><div class='meta'>12 May</div><h1>A title</h1>{FIRST}<ul><li>one item</li></ul>{SECOND}<div class='end'><a href=y>More</a></div></article>") == "A title " + parts(FIRST) + " one item " + parts(SECOND)


def test_links_within_sentences_stay():
    linked = SECOND.replace("the winter", "the <a href=z>winter</a>")
    assert got(f"<div>{FIRST}{linked}</div>") == parts(FIRST, SECOND)
