"""Main text of web pages: flat text blocks, classified by a decision tree on word counts and link densities of neighbours.

A page is cut into blocks at block-level tags. Each block is described by its own word count and link density, those of the
blocks before and after it, how much unlinked text its container holds, and only then by where it stands: under a tag or a
class name that marks page furniture, under article or main, in a heading or list. The tree is trained on a table of some
thousand labelled blocks, which a rule in this module lays out as pages of very different builds: with and without
semantic tags, telling class names, tables, forms round the whole page. Half of them can only be told by words and links.
"""

from __future__ import annotations

import functools
import html
import random
import re
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame

# Tag names by what they do in a page.
RAW = frozenset("script style noscript template textarea iframe object svg math select canvas xmp".split())
VOID = frozenset("area base br col embed hr img input link meta param source track wbr".split())
BLOCK = frozenset(
    "address article aside blockquote body br caption center dd details dialog dir div dl dt fieldset figcaption figure footer form h1 h2 h3 h4 h5 h6 head header hr html li main menu nav ol option p pre section summary table tbody td tfoot th thead title tr ul".split()
)
FURNITURE = frozenset("nav header footer aside form head menu dialog button".split())
#: Tags that hold blocks which belong together.
CONTAINERS = frozenset("div section article main body td th form aside nav footer header center fieldset blockquote details dialog".split())
CLOSES_P = BLOCK - {"br", "hr", "caption", "tbody", "tr", "td", "th", "tfoot", "thead", "option", "html", "body", "head", "title"}
HEADINGS = frozenset("h1 h2 h3 h4 h5 h6".split())
#: Words in a class, id or role that mark page furniture.
MARKS = frozenset(
    "ad ads advert advertisement adverts banner breadcrumb breadcrumbs byline comment comments consent cookie cookies disqus footer gdpr header login masthead menu modal nav navbar navigation newsletter notice overlay pagination pager popup promo promoted promotion related reply replies respond search share sharing sidebar signup social sponsor sponsored subscribe tags toolbar widget widgets alert complementary contentinfo subscription discussion feedback warning remarks opinions reactions".split()
)

_TOKEN = re.compile(r"<!--.*?(?:--!?>|\Z)|<!\[CDATA\[.*?(?:\]\]>|\Z)|<[!?][^>]*(?:>|\Z)|<(/?)([a-zA-Z][^\s/>]*)((?:[^>\"']|\"[^\"]*\"|'[^']*')*)(?:>|\Z)|[^<]+|<", re.S)
#: Marks of lists of other texts: an article in them is one of many. An article overrides the other marks, main all but hidden.
LISTS = frozenset("ad ads advert advertisement adverts comment comments discussion disqus feedback promo promoted promotion related reply replies respond sponsor sponsored remarks opinions reactions".split())
#: Tags and marks that also wrap whole pages; one long text of few links inside makes them a plain wrapper.
SOFT = frozenset("form header overlay search tags toolbar widget widgets".split())
#: Words that may stand beside a mark in one class name, such as site-footer; any other word (has-sidebar) makes it no mark.
BESIDE = frozenset("area bar block bottom box global inner item left links list main page primary right secondary section site top user".split())
LONG_WORDS, LONG_DENSITY = 20, 0.34

_ATTRIBUTE = re.compile(r"([^\s=/>\"']+)(?:\s*=\s*(?:\"([^\"]*)\"|'([^']*)'|([^\s>\"']+)))?")
_NONE = re.compile(r"display\s*:\s*none", re.I)
_NAME = re.compile(r"[A-Za-z][a-z]*|[A-Z]+(?![a-z])")
_SPACE = re.compile(r"\s+")


@dataclass
class Block:
    text: str
    words: int
    linked: int
    furniture: int
    article: int
    heading: int
    listed: int
    container: int


def _marks(given: str) -> tuple[frozenset[str], bool]:
    """The marks that a tag's class, id and role name, by whole names, and whether its attributes hide it."""
    marks: set[str] = set()
    hidden = False
    for m in _ATTRIBUTE.finditer(given):
        key, value = m[1].lower(), m[2] or m[3] or m[4] or ""
        if key in ("class", "id", "role"):
            for name in value.split():
                words = {w.lower() for w in _NAME.findall(name)}
                if words <= MARKS | BESIDE:
                    marks |= words & MARKS
        elif key == "hidden":
            hidden |= value.lower() != "false"
        elif key == "aria-hidden":
            hidden |= value.lower() == "true"
        elif key == "style":
            hidden |= bool(_NONE.search(value))
    return frozenset(marks), hidden


class _Open:
    """The open tags of a page: a stack, and for each name how often and where it is open, so that no question walks the stack."""

    def __init__(self) -> None:
        self.stack: list[tuple] = []
        self.places: dict[str, list[int]] = {}
        self.headings = 0

    def push(self, name: str, *state: object) -> None:
        self.places.setdefault(name, []).append(len(self.stack))
        self.stack.append((name, *state))
        self.headings += name in HEADINGS

    def pop(self) -> tuple:
        top = self.stack.pop()
        self.places[top[0]].pop()
        self.headings -= top[0] in HEADINGS
        return top

    def last(self, name: str) -> int:
        """The place of the innermost open tag of a name, or -1."""
        places = self.places.get(name)
        return places[-1] if places else -1


def blocks_of(page: str) -> list[Block]:
    """The text blocks of a page in order, white space inside each turned into one space. Scripts, styles and comments give none.

    Unclosed tags are closed by what contains them; a p also ends at the next block. Text that ends inside a tag is markup.
    The time is linear in the page, however deep its tags are nested.
    """
    out: list[Block] = []
    opened = _Open()
    parts: list[str] = []
    within: list[int] = []  # the innermost open soft wrapper of each block, or -1
    outer: list[int] = []  # the wrapper round each soft wrapper
    linked = 0
    # level: 0 unmarked, 1 marked, 2 a list or tag of other texts, 3 hidden; soft: the innermost wrapper that a long text may free
    level, soft, container, containers = 0, -1, 0, 1
    article = link = 0
    raw = ""

    def close() -> None:
        nonlocal linked
        text = _SPACE.sub(" ", html.unescape("".join(parts))).strip()
        parts.clear()
        if text:
            listed = opened.last("li") >= 0 or opened.last("dt") >= 0
            out.append(Block(text, len(text.split()), linked, int(level > 0), article, int(opened.headings > 0), int(listed), container))
            within.append(soft)
        linked = 0

    def pop(n: int) -> None:
        nonlocal level, soft, container, article, link
        while len(opened.stack) > n:
            _, level, soft, container, a, b = opened.pop()
            article, link = article - a, link - b

    for token in _TOKEN.finditer(page):
        name = token[2]
        if name is None:
            text = token[0]
            if raw or text.startswith(("<!", "<?")):
                if not raw and text.startswith("<![CDATA["):
                    parts.append(html.escape(text[9:].removesuffix("]]>"), quote=False))
                continue
            parts.append(text)
            if link:
                linked += len(text.split())
            continue
        name = name.lower()
        if raw:
            if token[1] and name == raw:
                raw = ""
            continue
        if token[1]:
            if name == "br" or name == "p" and opened.last("p") < 0:
                close()
                continue
            at = opened.last(name)
            if at >= 0:
                if name in BLOCK:
                    close()
                pop(at)
            continue
        if name in RAW:
            if not token[3].endswith("/"):
                raw = name
            continue
        if name in BLOCK:
            close()
        if name in VOID:
            continue
        if name in CLOSES_P and opened.last("p") >= 0:
            pop(opened.last("p"))
        if name == "li" and opened.stack and opened.stack[-1][0] == "li":
            pop(len(opened.stack) - 1)
        given = token[3]
        marks, hidden = _marks(given) if given and name not in ("html", "body") else (frozenset(), False)
        whole = name in ("main", "article")
        outside = level, soft, container
        if name in CONTAINERS:
            container, containers = containers, containers + 1
        if hidden:
            level = 3
        elif name == "main" and level < 3 or name == "article" and level < 2 and not article and LISTS.isdisjoint(marks):
            level, soft = 0, -1
        elif not whole and (name in FURNITURE or marks) and not (name == "header" and article):
            if (marks | {name} & FURNITURE) <= SOFT:
                outer.append(soft)
                soft = len(outer) - 1
            else:
                level = max(level, 2 if name in FURNITURE - SOFT or marks & LISTS else 1)
        inside, anchor = whole and level == 0, name == "a"
        opened.push(name, *outside, inside, anchor)
        article, link = article + inside, link + anchor
    close()
    # A long text of few links frees all wrappers round it, so the innermost one tells whether a block is free.
    freed: set[int] = set()
    for block, at in zip(out, within, strict=True):
        if not block.furniture and block.words >= LONG_WORDS and block.linked <= LONG_DENSITY * block.words:
            while at >= 0 and at not in freed:
                freed.add(at)
                at = outer[at]
    for block, at in zip(out, within, strict=True):
        block.furniture = int(block.furniture or at >= 0 and at not in freed)
    return out


FEATURES = ("words", "density", "words_before", "density_before", "words_after", "density_after", "container_words", "sentence", "furniture", "article", "heading", "listed", "has_article")


def table_of(blocks: list[Block]) -> np.ndarray:
    """One row of FEATURES for each block; what lies beyond the page counts as empty and unlinked."""
    own = np.zeros((len(blocks) + 2, 2))
    held: dict[int, int] = {}
    for i, b in enumerate(blocks, 1):
        own[i] = b.words, min(b.linked / b.words, 1.0)
        held[b.container] = held.get(b.container, 0) + max(b.words - b.linked, 0)
    any_article = float(any(b.article and not b.furniture for b in blocks))
    place = [[held[b.container], float(b.text[-1] in ".!?:;\u2026\"'\u201d\u00bb"), min(b.furniture, 1), min(b.article, 1), b.heading, b.listed, any_article] for b in blocks]
    return np.hstack([own[1:-1], own[:-2], own[2:], np.array(place, float).reshape(-1, 7)])


@dataclass
class Node:
    share: float
    feature: int = -1
    cut: float = 0.0
    low: Node | None = None
    high: Node | None = None


def grow(table: np.ndarray, labels: np.ndarray, depth: int = 9, least: int = 4) -> Node:
    """A binary tree by the largest fall of the Gini impurity; the first feature wins ties, so words and links go before marks."""
    share = float(labels.mean()) if len(labels) else 0.0
    node = Node(share)
    if depth == 0 or share in (0.0, 1.0):
        return node
    n, best = len(labels), (1e-9, -1, 0.0)
    whole = 2 * share * (1 - share) * n
    for f in range(table.shape[1]):
        order = np.argsort(table[:, f], kind="stable")
        values, good = table[order, f], np.cumsum(labels[order])
        at = np.flatnonzero(values[1:] > values[:-1]) + 1  # rows on the low side
        at = at[(at >= least) & (n - at >= least)]
        if not len(at):
            continue
        low, high = good[at - 1], good[-1] - good[at - 1]
        gain = whole - 2 * low * (1 - low / at) - 2 * high * (1 - high / (n - at))
        i = int(np.argmax(gain))
        if gain[i] > best[0] + 1e-9:
            best = (float(gain[i]), f, float((values[at[i]] + values[at[i] - 1]) / 2))
    if best[1] < 0:
        return node
    high = table[:, best[1]] > best[2]
    node.feature, node.cut = best[1], best[2]
    node.low, node.high = grow(table[~high], labels[~high], depth - 1, least), grow(table[high], labels[high], depth - 1, least)
    return node


def predict(node: Node, table: np.ndarray) -> np.ndarray:
    if node.feature < 0:
        return np.full(len(table), node.share >= 0.5)
    high = table[:, node.feature] > node.cut
    out = np.empty(len(table), bool)
    out[high], out[~high] = predict(node.high, table[high]), predict(node.low, table[~high])
    return out


class _Writer:
    """Lays out labelled pages. Every block's text begins with + (main text) or - (anything else)."""

    def __init__(self, seed: int) -> None:
        self.rng = random.Random(seed)

    def some(self, low: int, high: int) -> int:
        return self.rng.randint(low, high)

    def text(self, mark: str, low: int, high: int, stop: str = ".") -> str:
        n = self.some(low, high)
        return mark + " ".join(self.rng.choice(("rain", "the", "valley", "of", "house", "came", "and", "light", "seldom", "went")) for _ in range(n)) + stop

    def linked(self, mark: str, low: int, high: int) -> str:
        return f"<a href=x>{self.text(mark, low, high, '')}</a>"

    def paragraph(self) -> str:
        kind = self.rng.random()
        if kind < 0.25:
            return f"<p>{self.text('+', 1, 9, self.rng.choice(('.', '?', '!', '')))}</p>"
        if kind < 0.4:
            return f"<p>{self.text('+', 12, 60, '')} <a href=y>{self.text('', 1, 6, '')}</a> and so on.</p>"
        if kind < 0.5:
            return "<ul>" + "".join(f"<li>{self.text('+', 1, 14, '')}</li>" for _ in range(self.some(2, 6))) + "</ul>"
        if kind < 0.58:
            return f"<h2>{self.text('+', 1, 7, '')}</h2><p>{self.text('+', 20, 90)}</p>"
        if kind < 0.64:
            return f"<p>{self.text('+', 15, 70)}<br>{self.text('+', 4, 40)}</p>"
        if kind < 0.68:
            return f"<blockquote><p>{self.text('+', 5, 40)}</p></blockquote>"
        return f"<p>{self.text('+', 20, 120)}</p>"

    def article(self, short: float = 0.0) -> str:
        if self.rng.random() < short:
            # A main element may hold next to nothing; its text is then told by where it stands alone.
            most = self.rng.choice((2, 20))
            return self.maybe(f"<h1>{self.text('+', 1, 9, '')}</h1>", 0.6) + "".join(f"<p>{self.text('+', 1, most, self.rng.choice(('.', '')))}</p>" for _ in range(self.some(1, 4)))
        title = f"<h1>{self.text('+', 2, 10, '')}</h1>" if self.rng.random() < 0.9 else ""
        return title + f"<p>{self.text('+', 25, 90)}</p>" + "".join(self.paragraph() for _ in range(self.some(1, 9)))

    def menu(self) -> str:
        if self.rng.random() < 0.6:
            return "<ul>" + "".join(f"<li>{self.linked('-', 1, 3)}</li>" for _ in range(self.some(3, 9))) + "</ul>"
        return " | ".join(self.linked("-", 1, 3) for _ in range(self.some(3, 8)))

    def stories(self) -> str:
        """Links to other texts, with titles of some length."""
        kind, out = self.rng.random(), []
        for _ in range(self.some(2, 8)):
            title = self.linked("-", 4, 16)
            # With a teaser beside each title, less than half of such a list's words may be links.
            out.append(f"<p>{title} {self.text('', 4, 22)}</p>" if kind < 0.4 else f"<p>{title}</p>" if kind < 0.7 else f"<li>{title}</li>")
        return "".join(out)

    def closing(self) -> str:
        return f"{self.text('-', 3, 9)} {self.linked('', 1, 2)} {self.linked('', 1, 3)}" if self.rng.random() < 0.6 else self.text("-", 2, 8, self.rng.choice(("", ".")))

    def comments(self) -> str:
        return "".join(f"<div>{self.linked('-', 1, 2)}<p>{self.text('-', 3, 160)}</p></div>" for _ in range(self.some(1, 5)))

    def side(self) -> str:
        return f"<h3>{self.text('-', 1, 3, '')}</h3><p>{self.text('-', 8, 120)}</p>" + self.stories()

    def notice(self) -> str:
        return f"<p>{self.text('-', 10, 120)} {self.linked('', 1, 3)}</p>"

    def maybe(self, part: str, share: float = 0.5) -> str:
        return part if self.rng.random() < share else ""

    def semantic(self) -> str:
        inside = self.article(0.4) + self.maybe(f"<div class='{self.rng.choice(('ad', 'promo', 'newsletter', 'related'))}'>{self.notice()}</div>", 0.4) + self.maybe(f"<aside>{self.side()}</aside>", 0.3) + self.maybe(f"<p>{self.linked('+', 1, 12)}</p>", 0.3) + self.maybe(f"<p>{self.text('+', 2, 40)}</p>")
        return f"{self.maybe(f'<header>{self.closing()}</header>')}{self.maybe(f'<nav>{self.menu()}</nav>', 0.8)}{self.maybe(f"<div class=ad>{self.text('-', 2, 90)}</div>", 0.7)}<article>{inside}</article>{self.maybe(f'<section class=comments>{self.comments()}</section>', 0.4)}{self.maybe(f'<div>{self.stories()}</div>', 0.4)}{self.maybe(f'<footer>{self.closing()}</footer>', 0.5)}"

    def in_main(self) -> str:
        tail = self.maybe(f"<form>{self.text('-', 1, 6, '')}</form>", 0.4) + self.maybe(f"<div class='reader-comments comments'>{self.comments()}</div>")
        return f"<div id=menu>{self.menu()}</div><main>{self.article(0.4)}{tail}</main>{self.maybe(f'<div class=cookie-notice>{self.notice()}</div>')}{self.maybe(f'<footer>{self.closing()}</footer>', 0.6)}"

    def named(self) -> str:
        return f"<div class='site-header'>{self.closing()}</div><div class=menu>{self.menu()}</div><div class='{self.rng.choice(('content', 'post has-sidebar', 'entry', 'story'))}'>{self.article()}</div><div class=sidebar>{self.side()}</div>{self.maybe(f'<div class=comments>{self.comments()}</div>')}{self.maybe(f'<div class=footer>{self.closing()}</div>', 0.6)}"

    def bare(self) -> str:
        cut = self.article() + self.maybe(self.stories(), 0.4)
        return f"<div>{self.menu()}</div><div>{cut}</div>{self.maybe(f'<div>{self.stories()}</div>', 0.7)}{self.maybe(f'<div>{self.closing()}</div>', 0.6)}"

    def nested(self) -> str:
        return f"<div class=x1><div class=x2>{self.menu()}</div><div class=x3><div>{self.linked('-', 1, 3)}</div><div class=col-a>{self.article()}{self.maybe(self.stories(), 0.3)}</div><div class=col-b>{self.stories()}</div></div></div>{self.maybe(f'<div>{self.closing()}</div>', 0.6)}"

    def tabled(self) -> str:
        return f"<table><tr><td>{self.menu()}</td><td>{self.article()}</td><td>{self.stories()}</td></tr><tr><td colspan=3>{self.closing()}</td></tr></table>"

    def wrapped(self) -> str:
        return f"<form class='{self.rng.choice(('', 'overlay', 'widget'))}'><div>{self.menu()}</div><div>{self.article()}</div></form><form>{self.text('-', 1, 8, '')}</form><div hidden><p>{self.text('-', 20, 60)}</p></div>{self.maybe(f'<div>{self.closing()}</div>', 0.6)}"

    def flowing(self) -> str:
        lines = "<br>".join(self.text("+", 15, 70) if self.rng.random() < 0.8 else self.text("+", 3, 12) for _ in range(self.some(3, 7)))
        return f"<center>{self.menu()}</center><h1>{self.text('+', 2, 8, '')}</h1><div>{self.text('+', 25, 60)}<br>{lines}</div>{self.maybe(f'<center>{self.closing()}</center>', 0.6)}"


#: The builds of pages that the labelled table is made of, and how many of each.
BUILDS = ("semantic", "in_main", "named", "bare", "nested", "tabled", "wrapped", "flowing")
PAGES_EACH = 80


def labelled_blocks(builds: tuple[str, ...] = BUILDS, pages_each: int = PAGES_EACH, seed: int = 0) -> tuple[np.ndarray, np.ndarray]:
    """The labelled table: FEATURES of every block of pages of these builds, and whether each is main text."""
    tables, labels = [], []
    for build in builds:
        for i in range(pages_each):
            found = blocks_of(getattr(_Writer(seed * 1_000_003 + 1000 * BUILDS.index(build) + i), build)())
            tables.append(table_of(found))
            labels += [b.text[0] == "+" for b in found]
    return np.vstack(tables), np.array(labels, float)


@functools.cache
def trained_tree() -> Node:
    return grow(*labelled_blocks())


def main_text(page: str, tree: Node) -> str:
    """The main blocks of a page in order, joined by line feeds."""
    found = blocks_of(page)
    if not found:
        return ""
    return "\n".join(b.text for b, keep in zip(found, predict(tree, table_of(found)), strict=True) if keep)


def extract(pages: DataFrame) -> DataFrame:
    """page_id, url and the main text of every row of ``pages`` (page_id, url, html); null html is empty, and so is its text.

    Repeated rows stay; further columns are ignored; an empty table gives no rows. The tree is grown once, before the job.
    """
    tree = trained_tree()

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            texts = [main_text(x, tree) if x else "" for x in batch.column(2).to_pylist()]
            yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), pa.array(texts, pa.string())], ["page_id", "url", "text"])

    return pages.select("page_id", pages["url"].cast("string").alias("url"), pages["html"].cast("string")).mapInArrow(run, f"page_id {dict(pages.dtypes)['page_id']}, url string, text string")
