"""Main text of web pages: flat text blocks, classified by a decision tree.

A page is cut into blocks at block-level tags.  Each block has the word count and link
density of itself and of the blocks before and after it, the unlinked words of the blocks
around it, its distance from the page's ends, and what its tags say: whether it stands in the part that
the page names as main, how strongly its elements are named as page furniture, and whether it
is a heading or a list item.  No tag decides by itself: a decision tree (Gini splits, grown
in numpy) is trained on the small labelled table below, whose pages name their parts, name
them wrongly or name nothing, and says which blocks are main text.

Elements that show no text (scripts, styles, comments, form fields) are cut out first; one
that is never closed ends at its own tag, but for scripts and styles, which take the rest as
in a browser.  A quote that closes no attribute value is an ordinary sign, and a tag ends at
the next `<` at the latest, so a page is read in one pass whatever is left open in it.
Character references are decoded; inside a block white space becomes one blank; blocks that
are kept are joined in page order by one blank.  Nothing is capped.

Null and empty pages, and pages without main text, give the empty string.  Repeated rows
are treated row by row; null page_id and url are kept.  Ties between classes in a leaf go to
main text.  Empty tables give no rows; further columns are ignored.
"""

from __future__ import annotations

import html as entities
import random
import re

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from reclink.llm._common import tidy

# ---------------------------------------------------------------- blocks
#: A comment, a declaration or a tag.  Quoted values count only right after "=" and only if
#: white space, "/" or ">" follows them.
_MARKUP = re.compile(
    r"""<!--(?:.*?--!?>|.*\Z)|<[!?][^<>]*+(?:>|(?=<)|\Z)|<(/?)([a-zA-Z][^\s/<>]*+)((?:[^<>"'=]++|=\s*+"[^"]*+"(?=[\s/>])|=\s*+'[^']*+'(?=[\s/>])|["'=])*+)(?:>|(?=<)|\Z)""",
    re.DOTALL,
)
_HINTS = re.compile(r"""(?i)\b(class|id|role|style|aria-hidden|hidden|itemprop)\b(?:\s*=\s*("[^"]*"|'[^']*'|[^\s>]+))?""")
#: Elements without text to show; of the first two everything up to their end tag is raw.
_RAW = frozenset("script style".split())
_UNSEEN = _RAW | frozenset("noscript template svg iframe object textarea select title math audio video canvas".split())
_INLINE = frozenset("a abbr acronym b bdi bdo big br cite code data del dfn em font i img ins kbd label mark q s samp small span strike strong sub sup time tt u var wbr".split())
_VOID = frozenset("area base br col embed hr img input link meta param source track wbr".split())
_HEADINGS = frozenset("h1 h2 h3 h4 h5 h6".split())
#: Elements that hold page furniture, and words of class, id or role that name it.
_FURNITURE = frozenset("nav header footer aside form menu dialog button fieldset".split())
_NAMES = frozenset(
    "ad ads advert advertisement advertising adbox alert aside banner breadcrumb breadcrumbs byline comment comments commentlist complementary consent contentinfo cookie cookies copyright "
    "disclaimer disqus footer gdpr header login menu modal nav navbar navigation newsletter notice notices pagination pager popup promo promoted related replies reply respond search share "
    "sharing sidebar sidenav signup social sponsor sponsored subscribe toolbar topbar widget widgets".split()
)
#: Of these names those that say little as a part of a longer one (share-price, related-work).
_VAGUE = frozenset("ad ads alert aside banner disclaimer header login menu modal notice notices related reply respond search share social".split())
_MAIN_NAMES = frozenset(["main", "articlebody"])
#: A start tag of these ends an open paragraph.
_CLOSES_P = frozenset("address article aside blockquote div dl fieldset footer form h1 h2 h3 h4 h5 h6 header hr main menu nav ol p pre section table ul".split())

#: Columns of a block's features.
FEATURES = ("words", "links", "before_words", "before_links", "after_words", "after_links", "around", "edge", "main", "named", "heading", "listed")
#: How strongly an element is named as furniture: not, by a vague part of a name, by a name or
#: its tag, by being hidden.
_PLAIN, _PARTLY, _WHOLLY, _HIDDEN = range(4)


def _marks(name: str, attributes: str) -> tuple[int, int]:
    """(main level, strength of the furniture name) of an element: 2 article, 1 main part."""
    main = 2 if name == "article" else 1 if name == "main" else 0
    named = _WHOLLY if name in _FURNITURE else _PLAIN
    if attributes and name not in ("html", "body"):
        for key, value in _HINTS.findall(attributes):
            key, value = key.lower(), value.strip("\"'").lower()
            if key == "hidden" or (key == "aria-hidden" and value == "true") or (key == "style" and "display:none" in value.replace(" ", "")):
                named = _HIDDEN
            elif key in ("class", "id", "role", "itemprop") and name not in ("article", "main"):
                whole, parts = value.split(), _NAMES.intersection(re.split(r"[^a-z0-9]+", value))
                if parts:
                    named = max(named, _PARTLY if parts <= _VAGUE and _NAMES.isdisjoint(whole) else _WHOLLY)
                if not _MAIN_NAMES.isdisjoint(whole) and key != "class":
                    main = max(main, 1)
    return main, named


class _Reader:
    """One pass over a page: open elements, and the blocks that are complete."""

    def __init__(self, page: str):
        self.page, self.lower = page, None
        self.out: list[tuple] = []
        self.stack: list[tuple[str, int, int]] = []  # name, main level, furniture name
        self.spans: list[bool] = []  # of open spans: whether on the stack
        self.text: list[str] = []
        self.linked = 0
        self.in_link = False
        self.closes: dict[str, int] = {}

    def end_of(self, name: str, at: int) -> int:
        """Where the end tag of an unseen element begins; the page's end for raw ones
        without, -1 for others."""
        if self.lower is None:
            self.lower = self.page.lower()
        if name not in self.closes:
            self.closes[name] = self.lower.rfind(f"</{name}")
        if self.closes[name] < at:
            return len(self.page) if name in _RAW else -1
        return self.lower.find(f"</{name}", at)

    def add(self, piece: str) -> None:
        piece = entities.unescape(piece) if "&" in piece else piece
        self.text.append(piece)
        if self.in_link:
            self.linked += len(piece.split())

    def flush(self) -> None:
        words = "".join(self.text).split()
        if words:
            heading = any(x[0] in _HEADINGS for x in self.stack)
            main, named, inside = 0, _PLAIN, False
            for name, level, strength in self.stack:
                if level == 2 and not inside:
                    # what stands outside an article says nothing of it, but by its tag
                    inside, named = True, named if named == _HIDDEN else _PLAIN
                elif level == 2:
                    strength = max(strength, _WHOLLY)  # an article in an article: a comment
                elif inside and name == "header" and heading and strength == _WHOLLY:
                    strength = _PLAIN
                main, named = max(main, level), max(named, strength)
            if any(x[0] in ("nav", "aside", "footer", "form") for x in self.stack):
                named = max(named, _WHOLLY)
            self.out.append((" ".join(words), min(1.0, self.linked / len(words)), main, named, heading, any(x[0] == "li" for x in self.stack)))
        self.text, self.linked = [], 0

    def open(self, name: str, attributes: str) -> None:
        if name in _VOID or attributes.endswith("/"):
            return
        if self.stack and ((name in _CLOSES_P and self.stack[-1][0] == "p") or (name == "li" and self.stack[-1][0] == "li")):
            self.stack.pop()
        self.stack.append((name, *_marks(name, attributes)))

    def close(self, name: str) -> None:
        for k in range(len(self.stack) - 1, -1, -1):
            if self.stack[k][0] == name:
                del self.stack[k:]
                return

    def span(self, close: bool, attributes: str) -> None:
        """A span that is named as furniture or hidden is a block of its own."""
        if not close:
            own = bool(attributes) and _marks("span", attributes)[1] >= _WHOLLY
            if own:
                self.flush()
                self.stack.append(("span", *_marks("span", attributes)))
            self.spans.append(own)
        elif self.spans and self.spans.pop():
            self.flush()
            self.close("span")

    def read(self) -> list[tuple]:
        page, at = self.page, 0
        while tag := _MARKUP.search(page, at):
            if tag.start() > at:
                self.add(page[at : tag.start()])
            at = tag.end()
            if not tag[2]:
                continue
            close, name, attributes = bool(tag[1]), tag[2].lower(), tag[3]
            if name in _UNSEEN:
                if not close and not attributes.endswith("/") and (stop := self.end_of(name, at)) >= 0:
                    at = stop
                self.text.append(" ")
            elif name in _INLINE:
                if name == "a":
                    self.in_link = not close
                elif name == "br":
                    self.text.append(" ")
                elif name == "span":
                    self.span(close, attributes)
            else:
                self.flush()
                self.close(name) if close else self.open(name, attributes)
        self.add(page[at:])
        self.flush()
        return self.out


def blocks(page: str) -> list[tuple[str, float, int, int, bool, bool]]:
    """(text, link density, main level, furniture name, heading, in a list) of each block."""
    return _Reader(page).read()


def features(found: list[tuple]) -> np.ndarray:
    """Rows of FEATURES; main is whether a block stands in the page's main part, 0.5 where
    the page names none.  `around` is the mean of unlinked words from three blocks before to
    three after, without the block itself; edge is the distance to the page's nearer end, 6 at
    most."""
    n = len(found)
    words = np.array([b[0].count(" ") + 1 for b in found], float)
    return from_columns(words, *(np.array([float(b[k]) for b in found]) for k in range(1, 6)), n)


def from_columns(words, links, levels, named, heading, listed, n: int) -> np.ndarray:
    best = levels[named < _WHOLLY].max(initial=0)
    main = np.full(n, 0.5) if best == 0 else (levels >= best).astype(float)
    before = lambda x: np.concatenate([[0.0], x[:-1]])
    after = lambda x: np.concatenate([x[1:], [0.0]])
    free = words * (1 - links)
    sums = np.concatenate([[0.0], np.cumsum(free)])
    low, high = np.maximum(np.arange(n) - 3, 0), np.minimum(np.arange(n) + 4, n)
    around = (sums[high] - sums[low] - free) / np.maximum(high - low - 1, 1)
    edge = np.minimum(np.minimum(np.arange(n), np.arange(n)[::-1]), 6)
    return np.stack([words, links, before(words), before(links), after(words), after(links), around, edge, main, named, heading, listed], axis=1)


# ---------------------------------------------------------------- the labelled table
#: How the pages of the table name their parts: (main level of the article, furniture name of
#: menus and the like, of notices and comments, and of single paragraphs of the article).
_NAMINGS = (
    (2, _WHOLLY, _WHOLLY, _PLAIN), (2, _WHOLLY, _PARTLY, _PLAIN), (2, _PARTLY, _PLAIN, _PARTLY), (2, _PLAIN, _WHOLLY, _PLAIN), (2, _PLAIN, _PLAIN, _PARTLY),
    (1, _WHOLLY, _WHOLLY, _PLAIN), (1, _WHOLLY, _PARTLY, _PARTLY), (0, _WHOLLY, _WHOLLY, _PLAIN), (0, _WHOLLY, _PLAIN, _PLAIN), (0, _PLAIN, _PLAIN, _PLAIN), (0, _PLAIN, _WHOLLY, _PARTLY),
)


def labelled_table(pages: int = 26, seed: int = 11) -> tuple[np.ndarray, np.ndarray]:
    """The small labelled table: (FEATURES, is main text) of the blocks of made-up pages,
    `pages` for each way of naming the parts.  A page is a menu, a short notice, a title,
    paragraphs of all lengths with lists, links and subheadings, boxes between them, related
    links, readers' comments and a footer; some parts are missing from some pages."""
    rng = random.Random(seed)
    x, y = [], []
    for level, menu, notice, odd in _NAMINGS:
        for number in range(pages):
            rows: list[tuple] = []  # words, links, level, name, heading, listed, label

            def put(words, links=0.0, main=0, name=_PLAIN, heading=0, listed=0, label=0):
                rows.append((words, links, main, name, heading, listed, label))

            if number % 5 == 4:  # a short page: its text, and a few links before it at most
                for _ in range(rng.choice((0, 0, 1, 2, 4))):
                    put(rng.randint(1, 2), 1.0, 0, menu, listed=rng.randint(0, 1))
                for _ in range(rng.choice((1, 2, 2, 3))):
                    put(rng.choice((rng.randint(2, 12), 20, 40, 80)), 0.0, level, _PLAIN, label=1)
            else:
                inner = lambda name: level if name and rng.random() < 0.5 else 0  # noqa: E731  named furniture may stand inside the main part
                if number % 4 != 1:
                    for _ in range(rng.randint(3, 7)):
                        put(rng.randint(1, 2), 1.0, 0, menu, listed=1)
                if number % 3 != 2:
                    put(rng.randint(3, 14), rng.choice((0.0, 0.0, 0.3)), 0, notice)
                if number % 5 == 3:
                    put(rng.randint(15, 30), 0.1, 0, max(notice, menu))
                put(rng.randint(2, 25), 0.0, level, _PLAIN, 1, label=1)
                for _ in range(rng.choice((2, 3, 5, 8, 12, 30))):
                    words = rng.choice((1, 2, 4, 9, 15, 30, 60, 90, 140, 400))
                    name = odd if words >= 12 and rng.random() < 0.4 else _PLAIN
                    put(words, rng.choice((0.0, 0.0, 0.0, 0.15, 0.4)) if words >= 9 else 0.0, level, name, label=1)
                    if rng.random() < 0.12:
                        put(rng.randint(2, 8), 0.0, level, _PLAIN, 1, label=1)
                    if rng.random() < 0.1:
                        for _ in range(3):
                            put(rng.randint(3, 14), rng.choice((0.0, 0.2)), level, _PLAIN, 0, 1, label=1)
                    if rng.random() < 0.1 and notice:
                        put(rng.randint(2, 9), rng.choice((0.0, 0.5, 1.0)), inner(notice), max(notice, odd))
                    if rng.random() < 0.06 and level:
                        put(rng.randint(1, 4), 1.0, level, _PLAIN, label=1)
                if number % 3 == 0:
                    put(2, 0.0, inner(menu), menu, 1)
                    for _ in range(3):
                        put(rng.randint(3, 9), 1.0, inner(menu), menu, listed=1)
                if number % 4 == 2:
                    talk = max(notice, menu)
                    home = inner(talk) if talk >= _WHOLLY else 0
                    put(rng.randint(1, 3), 0.0, home, talk, 1)
                    for _ in range(rng.randint(2, 4)):
                        put(2, 1.0, home, talk)
                        put(rng.randint(4, 45), 0.0, home, talk)
                if number % 4 != 3:
                    put(rng.randint(4, 14), rng.choice((0.0, 0.0, 0.5)), 0, menu)
                if number % 2 and number % 4 != 3:
                    for _ in range(3):
                        put(rng.randint(1, 2), 1.0, 0, menu, listed=rng.randint(0, 1))
            columns = np.array(rows, float).T
            x.append(from_columns(*columns[:6], len(rows)))
            y.append(columns[6].astype(int))
    return np.concatenate(x), np.concatenate(y)


class Tree:
    """A binary decision tree grown by Gini impurity; at a tie the first feature wins."""

    def __init__(self, x: np.ndarray, y: np.ndarray, depth: int = 14, least: int = 2):
        self.feature: list[int] = []
        self.limit: list[float] = []
        self.next: list[tuple[int, int]] = []
        self.value: list[float] = []
        self._grow(x, y, depth, least)

    def _grow(self, x, y, depth, least) -> int:
        me = len(self.value)
        for column, start in ((self.feature, -1), (self.limit, 0.0), (self.next, (0, 0)), (self.value, float(y.mean()))):
            column.append(start)
        if depth == 0 or y.min() == y.max():
            return me
        best = (1e-12, -1, 0.0)
        whole = len(y) * y.mean() * (1 - y.mean())
        for f in range(x.shape[1]):
            order = np.argsort(x[:, f], kind="stable")
            v, ones = x[order, f], np.cumsum(y[order])
            cut = np.flatnonzero(v[1:] > v[:-1]) + 1
            cut = cut[(cut >= least) & (len(y) - cut >= least)]
            if len(cut):
                left, right = ones[cut - 1] / cut, (ones[-1] - ones[cut - 1]) / (len(y) - cut)
                gain = whole - cut * left * (1 - left) - (len(y) - cut) * right * (1 - right)
                k = int(gain.argmax())
                if gain[k] > best[0] + 1e-12:
                    best = (gain[k], f, (v[cut[k]] + v[cut[k] - 1]) / 2)
        if best[1] >= 0:
            low = x[:, best[1]] <= best[2]
            self.feature[me], self.limit[me] = best[1], best[2]
            self.next[me] = (self._grow(x[low], y[low], depth - 1, least), self._grow(x[~low], y[~low], depth - 1, least))
        return me

    def predict(self, x: np.ndarray) -> np.ndarray:
        """Share of main text in the leaf of each row."""
        at = np.zeros(len(x), int)
        feature, limit, step = np.array(self.feature), np.array(self.limit), np.array(self.next)
        while (live := np.flatnonzero(feature[at] >= 0)).size:
            node = at[live]
            right = x[live, feature[node]] > limit[node]
            at[live] = step[node, right.astype(int)]
        return np.array(self.value)[at]


def main_text(page: str, tree: Tree) -> str:
    found = blocks(page)
    if not found:
        return ""
    keep = tree.predict(features(found)) >= 0.5
    return " ".join(b[0] for b, k in zip(found, keep) if k)


# ---------------------------------------------------------------- Spark
def extract(pages: DataFrame) -> DataFrame:
    """Per row of pages (page_id, url, html): page_id, url, text, n_chars."""
    tree = Tree(*labelled_table())

    def apply(batches):
        for batch in batches:
            texts = [main_text(page, tree) if page else "" for page in batch.column(2).to_pylist()]
            yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), pa.array(texts, pa.string()), pa.array([len(t) for t in texts], pa.int64())], names=["page_id", "url", "text", "n_chars"])

    rows = pages.select(F.col("page_id").cast("long").alias("page_id"), F.col("url").cast("string").alias("url"), F.col("html").cast("string").alias("html"))
    return rows.mapInArrow(tidy(apply), "page_id long, url string, text string, n_chars long")
