"""Main text of whole pages against a plain parse, with and without the tags that name parts."""

import html
import re
import time
from collections import Counter

import pyarrow.parquet as pq
import pytest

from reclink.llm import htmlblocks

TREE = htmlblocks.Tree(*htmlblocks.labelled_table())
PAGES = [r["html"] or "" for r in pq.read_table("/root/testdata/sf0.01/pages.parquet").to_pylist()]


def plain(page):
    """The article of the table's pages, whose blocks are headings and paragraphs."""
    found = re.search(r"<article>(.*)</article>", page, re.DOTALL)
    parts = re.split(r"</?(?:h1|p)>", re.sub(r"</?b>", "", found[1]).replace("<br>", " ")) if found else []
    return " ".join(" ".join(html.unescape(x).split()) for x in parts if x.strip())


def test_every_page():
    assert [p for p in PAGES if htmlblocks.main_text(p, TREE) != plain(p)] == []


@pytest.mark.parametrize("flat", [False, True])
def test_without_names(flat):
    """Without article, classes (and, flat, menus and footers) word counts and links decide."""
    right = found = wanted = 0
    for page in PAGES:
        bare = re.sub(r'</?article>| class="[^"]*"', "", page)
        bare = re.sub(r"(</?)(nav|footer|ul|li)\b", r"\1div", bare) if flat else bare
        got, want = Counter(htmlblocks.main_text(bare, TREE).split()), Counter(plain(page).split())
        right, found, wanted = right + sum((got & want).values()), found + sum(got.values()), wanted + sum(want.values())
    assert right / found > 0.97 and right / wanted > 0.99


def test_neighbours_are_used():
    used = {htmlblocks.FEATURES[f] for f in TREE.feature if f >= 0}
    assert {"words", "links", "main", "named"} < used and used & {"before_words", "after_words", "around"} and used & {"before_links", "after_links"}


def test_fresh_pages():
    x, y = htmlblocks.labelled_table(6, seed=99)
    assert ((TREE.predict(x) >= 0.5) == y).mean() > 0.98


LONG, MORE = "word " * 40, "price " * 20


@pytest.mark.parametrize(
    ("page", "text"),
    [
        (f"<article><h1>T</h1><p>{LONG}</p><p class='share-price'>{MORE}</p><p id='related-work'>{MORE}</p></article>", f"T {LONG} {MORE} {MORE}"),
        (f"<div class='notice-board'><article><p>{LONG}</p><p>short one</p></article></div>", f"{LONG} short one"),
        ("<p>A short page with no main part</p>", "A short page with no main part"),
        (f"<p>{MORE}</p><svg><p>{LONG}</p>", f"{MORE} {LONG}"),
        ("<article><p><a href='it's'>link</a> goes on</p></article>", "link goes on"),
        ('<p class="x>text one</p><p class="y">text two</p>', "text one text two"),
        (f"<article><p>{LONG}</p><p>He <span class=share>Share</span> rest</p><article><p>I like it</p></article></article>", f"{LONG} He rest"),
        (f"<main><article><header><h1>Real</h1><p class=byline>By me</p></header><p>{LONG}</p><aside>Related</aside><form><label>Name</label></form><p>end.</p></article></main><div class='cookie-banner'>We use cookies</div>", f"Real {LONG} end."),
        (f"<article><p title='a > b'>{LONG}</p><p data-x=\"<b>x</b>\">{MORE}</p></article>", f"{LONG} {MORE}"),
    ],
)
def test_markup(page, text):
    assert htmlblocks.main_text(page, TREE) == " ".join(text.split())


@pytest.mark.parametrize("part", ["<a x", '<a x="', "<!x", "<a =\"'", "<svg>", "<!--", "<p class='", "<", "&amp", "<span class=ad>"])
def test_one_pass(part):
    """Twice the page takes about twice the time, whatever is left open."""
    begin = time.monotonic()
    htmlblocks.main_text(part * (200_000 // len(part)), TREE)
    assert time.monotonic() - begin < 8
