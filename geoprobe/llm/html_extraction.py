"""Main text of web pages: flat text blocks classified by a decision tree.

A tolerant scanner cuts a page into text blocks at block-level tags, in one pass and in linear time whatever the markup. Each
block has its word count and link density, those of the blocks before and after it, its kind (heading, list item,
paragraph), and whether its innermost landmarks are content or furniture: navigation, forms, asides, footers and hidden parts count from the
outermost article inwards, what encloses the article counts apart. A decision tree, grown once on the driver from the small labelled table
below and broadcast, says which blocks belong to the article. In that table half of the pages carry neither landmarks nor telling class names, so that words, links and
neighbours must tell.

Null html, and pages without kept blocks, give the empty text; malformed or unclosed markup is read as far as it goes (an
unclosed quote is an ordinary character; an unclosed tag, comment, script or style runs to the end of the page); repeated rows are treated alike; other columns
are ignored.
"""

from __future__ import annotations

import re
from dataclasses import dataclass
from html import unescape

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import map_text

#: Element names and the class, id and role words that mark page furniture or content.
BLOCK = set("address article aside blockquote body button caption center dd details dialog div dl dt fieldset figcaption figure footer form h1 h2 h3 h4 h5 h6 head header hgroup hr html label legend li main menu nav ol p pre search section summary table tbody td tfoot th thead title tr ul".split())
RAW = set("script style title textarea iframe noscript template select svg math".split())
VOID = set("area base br col embed hr img input link meta param source track wbr".split())
HEADINGS = {"h1", "h2", "h3", "h4", "h5", "h6"}
FORMS = {"form", "fieldset", "label", "button", "legend"}
FURNITURE = {"nav", "footer", "aside", "menu", "dialog", "search"} | FORMS
CONTENT = {"article", "main"}
ROLES = {"navigation": "nav", "complementary": "aside", "contentinfo": "footer", "search": "search", "form": "form", "dialog": "dialog", "banner": "header", "main": "main", "article": "article"}
BAD_WORDS = set(
    "ad ads adv advert advertisement advertising banner promo promotion sponsor sponsored cookie cookies consent gdpr notice alert sidebar aside menu nav navbar navigation breadcrumb breadcrumbs footer header masthead topbar toolbar comment comments reply replies "
    "discussion respond share sharing social related recommended recommendations newsletter subscribe subscription signup login popup modal overlay widget pagination pager tags tagcloud meta-nav toc copyright disclaimer legal hidden noprint complementary contentinfo search".split()
)
GOOD_WORDS = set("article content post entry story main body text maincontent".split())

_TAG = re.compile(r"(/?)([a-zA-Z][a-zA-Z0-9:-]*)")
_STOP = re.compile(r">|=[ \t\r\n\f]*[\"']")
_ATTRIBUTE = re.compile(r"""([^\s=/>"']+)(?:\s*=\s*("[^"]*"|'[^']*'|[^\s>]*))?""")
_RAW_END = {name: re.compile(rf"</{name}(?=[\s/>])", re.I) for name in RAW}
_HIDDEN = re.compile(r"display\s*:\s*none|visibility\s*:\s*hidden")
_NAME = re.compile(r"[A-Za-z]+")
_LONG = re.compile(r"&#(?:0*([0-9]+)|[xX]0*([0-9a-fA-F]+));?")

#: The first of equally good features is split on.
FIELDS = ("in_content", "inner_furniture", "outer_furniture", "unseen", "bad_name", "good_name", "heading", "item", "paragraph", "words", "links", "before", "before_links", "after", "after_links")


@dataclass(slots=True)
class Open:
    """An open element with what holds for it and all that encloses it; `block` is the place of the nearest block element.
    Furniture and bad names count from the outermost content element inwards, `outer` is what encloses that."""

    name: str = ""
    block: int = -1
    content: bool = False
    furniture: bool = False
    outer: bool = False
    bad: bool = False
    good: bool = False
    unseen: bool = False
    linked: bool = False
    mark: str = ""


@dataclass(slots=True)
class Block:
    text: str
    words: int
    links: float
    tag: str
    inside: Open

    @property
    def mark(self) -> str:
        return self.inside.mark


def attributes_of(text: str) -> dict[str, str]:
    return {key.lower(): value.strip("\"'").lower() for key, value in _ATTRIBUTE.findall(text)}


def decoded(text: str) -> str:
    """Text with its character references replaced; numbers beyond all characters give U+FFFD at any length."""
    if "&#" in text:
        text = _LONG.sub(lambda m: m[0] if len(m[1] or m[2]) <= 7 else "\ufffd", text)
    return unescape(text)


def opened(name: str, attributes: dict[str, str], up: Open, place: int) -> Open:
    """The marks of an element from its tag and those of what encloses it."""
    kind = ROLES.get(attributes.get("role", ""), name)
    names = {w for key in ("class", "id") for x in attributes.get(key, "").split() for w in (x, *_NAME.findall(x))}
    bad = bool(names & BAD_WORDS) and name not in ("html", "body")
    enters = kind in CONTENT and not up.content
    furniture = kind in FURNITURE or kind == "header" and not up.content
    unseen = "hidden" in attributes or attributes.get("aria-hidden") == "true" or bool(_HIDDEN.search(attributes.get("style", "")))
    return Open(
        name, place if name in BLOCK else up.block, up.content or kind in CONTENT, not enters and (up.furniture or furniture), up.outer or furniture and not up.content and kind not in FORMS, not enters and (up.bad or bad),
        up.good or bool(names & GOOD_WORDS), up.unseen or unseen, up.linked or name == "a" and "href" in attributes, attributes.get("data-keep") or up.mark,
    )


def tag_end(page: str, at: int) -> int:
    """The place of the `>` that ends a tag, quoted values left out; the page's length if there is none."""
    while True:
        m = _STOP.search(page, at)
        if m is None:
            return len(page)
        if m[0] == ">":
            return m.start()
        close = page.find(m[0][-1], m.end())
        if close < 0:
            # No such quote follows any more: it is an ordinary character.
            end = page.find(">", m.end())
            return end if end >= 0 else len(page)
        at = close + 1


def blocks_of(page: str) -> list[Block]:
    """The text blocks of a page in order. Every open element is kept; depth costs constant work a block and a tag."""
    out: list[Block] = []
    open_: list[Open] = []
    places: dict[str, list[int]] = {}
    outside = Open()
    pieces: list[tuple[str, bool]] = []
    at, size = 0, len(page)

    def flush() -> None:
        text = " ".join("".join(t for t, _ in pieces).split())
        if text:
            linked = sum(len(t.split()) for t, x in pieces if x)
            words, top = len(text.split()), open_[-1] if open_ else outside
            out.append(Block(text, words, min(1.0, linked / words), open_[top.block].name if top.block >= 0 else "", top))
        pieces.clear()

    def close(place: int) -> None:
        for x in reversed(open_[place:]):
            places[x.name].pop()
        del open_[place:]

    while at < size:
        start = page.find("<", at)
        start = size if start < 0 else start
        if start > at:
            pieces.append((decoded(page[at:start]), bool(open_) and open_[-1].linked))
        if start == size:
            break
        m = _TAG.match(page, start + 1)
        if m is None:
            if page.startswith("<!--", start):
                end = page.find("-->", start + 2) + 2
            elif page.startswith(("<!", "<?", "</"), start):
                end = page.find(">", start)
            else:
                pieces.append(("<", bool(open_) and open_[-1].linked))
                at = start + 1
                continue
            at = end + 1 if end > start else size
            continue
        closing, name = bool(m[1]), m[2].lower()
        end = tag_end(page, m.end())
        if end == size:
            break
        at = end + 1
        if name in BLOCK:
            flush()
        elif name == "br":
            pieces.append((" ", False))
        if name in VOID:
            continue
        top = open_[-1].block if open_ else -1
        if closing:
            # An inline end tag doesn't close blocks.
            if places.get(name) and (name in BLOCK or places[name][-1] > top):
                close(places[name][-1])
            continue
        text = page[m.end() : end]
        if name in RAW and not text.endswith("/"):
            found = _RAW_END[name].search(page, at)
            end = page.find(">", found.end()) if found else -1
            at = end + 1 if end >= 0 else size
            continue
        if name in BLOCK and top >= 0 and (open_[top].name == "p" or open_[top].name == name == "li"):
            close(top)
        if name == "a" and places.get("a") and places["a"][-1] > top:
            close(places["a"][-1])
        places.setdefault(name, []).append(len(open_))
        open_.append(opened(name, attributes_of(text) if text else {}, open_[-1] if open_ else outside, len(open_)))
    flush()
    return out


def features(blocks: list[Block]) -> np.ndarray:
    own = [(b.words, b.links) for b in blocks]
    rows = []
    for i, b in enumerate(blocks):
        before, after, x = own[i - 1] if i else (0, 0.0), own[i + 1] if i + 1 < len(own) else (0, 0.0), b.inside
        rows.append((x.content, x.furniture, x.outer, x.unseen, x.bad, x.good, b.tag in HEADINGS, b.tag == "li", b.tag == "p", b.words, b.links, *before, *after))
    return np.array(rows, np.float64).reshape(len(blocks), len(FIELDS))


class Tree:
    """A binary classification tree by Gini impurity."""

    def __init__(self, x: np.ndarray, y: np.ndarray, depth: int = 12, least: int = 1):
        self.value, self.field = float(y.mean()), -1
        if depth == 0 or len(y) < 2 * least or y.min() == y.max():
            return
        best = (len(y) * self.value * (1 - self.value) - 1e-9, -1, 0.0)
        for f in range(x.shape[1]):
            order = np.argsort(x[:, f], kind="stable")
            v, t = x[order, f], y[order]
            left = np.cumsum(t)
            n = np.arange(1, len(t))
            ok = (v[1:] > v[:-1]) & (n >= least) & (len(t) - n >= least)
            if ok.any():
                a, b = left[:-1] / n, (left[-1] - left[:-1]) / (len(t) - n)
                cost = np.where(ok, n * a * (1 - a) + (len(t) - n) * b * (1 - b), np.inf)
                i = int(np.argmin(cost))
                if cost[i] < best[0]:
                    best = (float(cost[i]), f, float(v[i] + v[i + 1]) / 2)
        if best[1] >= 0:
            self.field, self.at = best[1], best[2]
            low = x[:, self.field] <= self.at
            self.low, self.high = Tree(x[low], y[low], depth - 1, least), Tree(x[~low], y[~low], depth - 1, least)

    def keep(self, row) -> bool:
        node = self
        while node.field >= 0:
            node = node.low if row[node.field] <= node.at else node.high
        return node.value > 0.5


    def used(self) -> set[str]:
        """Names of the features that the tree splits on."""
        return set() if self.field < 0 else {FIELDS[self.field]} | self.low.used() | self.high.used()


class _Pages:
    """A generator of labelled pages: containers carry data-keep="y" or "n"."""

    def __init__(self, seed: int):
        self.rng = np.random.default_rng(seed)
        letters = np.array(list("aeilnorst"))
        self.words = ["".join(self.rng.choice(letters, int(n))) for n in self.rng.integers(2, 8, 400)]

    def number(self, low: int, high: int) -> int:
        return int(self.rng.integers(low, high + 1))

    def chance(self, p: float) -> bool:
        return self.rng.random() < p

    def prose(self, low: int, high: int) -> str:
        return " ".join(self.words[i] for i in self.rng.integers(0, len(self.words), self.number(low, high))) + "."

    def opaque(self) -> str:
        """Attributes that tell nothing."""
        return [f' class="c{self.number(1, 99)}"', ' class="row"', f' id="x{self.number(1, 99)}"', ""][self.number(0, 3)]

    def links(self, low: int, high: int, tag: str = "li") -> str:
        made = "".join(f'<{tag}><a href="/{i}">{self.prose(1, 5)}</a></{tag}>' for i in range(self.number(low, high)))
        return f"<ul>{made}</ul>" if tag == "li" else made

    def paragraph(self, low: int, high: int) -> str:
        """Prose, now and then with a link inside."""
        text = self.prose(low, high)
        return f"{text} <a href='/y'>{self.prose(1, 3)}</a> {self.prose(8, 20)}" if self.chance(0.25) else text

    def body(self, plain: bool) -> str:
        """The blocks of an article. Where nothing else tells, they are prose of some length."""
        kinds = ["p", "p", "p", "p", "h2", "blockquote"] + ([] if plain else ["li", "td", "p"])
        made = []
        for _ in range(self.number(2 if plain else 1, 8)):
            t = kinds[self.number(0, len(kinds) - 1)]
            made.append(f"<{t}>{self.paragraph(*((2, 9) if t == 'h2' else (16, 90) if plain else (1, 90)))}</{t}>")
        return f"<h1>{self.prose(3, 14)}</h1>" + "".join(made) + (f"<p>{self.prose(16, 60)}</p>" if plain else "")

    def box(self, tag: str, name: str, inner: str, known: bool) -> str:
        """A piece of furniture under its own tag or name, or without either."""
        if not known:
            return f'<div{self.opaque()} data-keep="n">{inner}</div>'
        return f'<{tag}{self.opaque()} data-keep="n">{inner}</{tag}>' if tag != "div" else f'<div class="{name}" data-keep="n">{inner}</div>'

    def named(self) -> str:
        """Furniture that its tag or name tells, whatever its text is."""
        some = "".join(f"<p>{self.paragraph(1, 100)}</p>" for _ in range(self.number(1, 3)))
        tag, name = [("nav", ""), ("aside", ""), ("form", ""), ("footer", ""), ("div", "ad"), ("div", "cookie-notice"), ("div", "sidebar"), ("section", "comments"), ("div", "share"), ("div", "related")][self.number(0, 9)]
        inner = self.links(2, 6) if tag == "nav" and self.chance(0.7) else f"<label>{self.prose(1, 6)}</label>{some}" if tag == "form" else some + (self.links(1, 3) if self.chance(0.4) else "")
        if tag == "section":
            return f'<section class="{name}" data-keep="n">{some}{some}</section>'
        return self.box(tag, name, inner, True)

    def unnamed(self) -> str:
        """Furniture that only its words, links and neighbours tell: menus, teasers between links, lines of small print."""
        kind = self.number(0, 3)
        inner = self.links(3, 8) if kind == 0 else self.links(2, 6, "p") if kind == 1 else f'<p><a href="/t">{self.prose(2, 8)}</a></p><p>{self.prose(4, 12)}</p><p><a href="/u">{self.prose(2, 8)}</a></p>' if kind == 2 else "".join(f"<{t}>{self.prose(2, 7)}</{t}>" for t in self.rng.choice(["p", "span", "td", "li", "dd"], self.number(1, 3)))
        return self.box("div", "", inner, False)

    def hidden(self) -> str:
        return f'<div{[" style=" + chr(34) + "display:none" + chr(34), " hidden", " aria-hidden=true"][self.number(0, 2)]} data-keep="n"><p>{self.prose(1, 90)}</p></div>'

    def page(self, i: int) -> str:
        plain = i % 2 == 1
        inside = self.body(plain)
        if not plain:
            # Furniture stands inside articles as well.
            for _ in range(self.number(0, 3)):
                made = self.named() if self.chance(0.7) else self.hidden() if self.chance(0.4) else f'<div data-keep="n">{self.links(2, 7)}</div>'
                inside = inside + made + f"<p>{self.paragraph(1, 60)}</p>" if self.chance(0.5) else inside + made
        kind = i // 2 % 4
        if plain:
            article = [f'<div{self.opaque()} data-keep="y">{inside}</div>', f'<div{self.opaque()}><section{self.opaque()} data-keep="y">{inside}</section></div>', f'<div class="post-content" data-keep="y">{inside}</div>', f'<div id="main" data-keep="y">{inside}</div>'][kind]
        else:
            article = [
                f'<article{self.opaque()} data-keep="y">{inside}</article>', f'<main data-keep="y"><article><header><p>{self.prose(2, 8)}</p></header>{inside}</article></main>',
                f'<div class="with-sidebar"><article data-keep="y">{inside}</article></div>', f'<form><div role="main" data-keep="y">{inside}</div></form>',
            ][kind]
        around = [self.unnamed() if plain and self.chance(0.75) else self.hidden() if self.chance(0.1) else f'<header data-keep="n"><p>{self.prose(1, 60)}</p></header>' if self.chance(0.1) else f'<aside data-keep="n"><article><p>{self.prose(5, 60)}</p></article></aside>' if self.chance(0.1) else self.named() for _ in range(self.number(2, 7))]
        cut = self.number(0, len(around))
        return "<html><body>" + "".join(around[:cut]) + article + "".join(around[cut:]) + "</body></html>"


def labelled_pages(seed: int = 7, pages: int = 1000) -> list[str]:
    """The labelled table: small pages, by turns with landmarks or names and without."""
    made = _Pages(seed)
    return [made.page(i) for i in range(pages)]


_TREE: list[Tree] = []


def trained() -> Tree:
    """The tree, grown once per process; `extracted` grows it on the driver and ships it."""
    if not _TREE:
        found = [blocks_of(page) for page in labelled_pages()]
        _TREE.append(Tree(np.vstack([features(f) for f in found]), np.array([b.mark == "y" for f in found for b in f], np.float64)))
    return _TREE[0]


def main_text(page: str, tree: Tree | None = None) -> str:
    tree = tree or trained()
    found = blocks_of(page)
    return "\n".join(b.text for b, row in zip(found, features(found).tolist(), strict=True) if tree.keep(row))


def extracted(pages: DataFrame) -> DataFrame:
    """page_id, url, text (main text, blocks joined by line feeds), n_chars."""
    shared = pages.sparkSession.sparkContext.broadcast(trained())

    def run(batch: pa.RecordBatch) -> dict:
        texts = [main_text(h or "", shared.value) for h in batch.column("html").to_pylist()]
        return {"page_id": batch.column("page_id"), "url": batch.column("url"), "text": texts, "n_chars": [len(t) for t in texts]}

    return map_text(pages.select(F.col("page_id").cast("long").alias("page_id"), F.col("url").cast("string").alias("url"), F.col("html").cast("string").alias("html")), run, "page_id long, url string, text string, n_chars long", column="html")
