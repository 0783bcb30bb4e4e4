"""HTML extraction by a recurrent block labeller: a numpy bidirectional LSTM over the leaf blocks of a page.

A page is cut into leaf blocks: stretches of text between block-level tags. Each block becomes a vector of its hashed
tag path (element names, and names with their class, id and role words), its hashed words, and a few measures (length,
share of link text, punctuation, place). The network reads the vectors of all blocks of a page in both directions, so
every block is classified in the context of the whole document; blocks above one half are the main text.

Training: labels come from the structure of a bounded sample of pages (blocks inside an article or main element and
outside navigation, page headers and footers, forms, asides, notices, adverts and comments) and from generated
layouts, whose container names are drawn from usual ones, so that pages without such elements are covered too.

Scripts, styles, comments, the source inside an iframe and other markup never become text; a textarea holds text without markup.
All other elements, drawings and formulas among them, are read as part of the page, and the network decides on their blocks. White space inside a block becomes one space, a line
break is white space, character references are decoded in each stretch of text between two tags, blocks are joined by an empty line, and nothing is capped.
Reading takes time linear in the page, however its tags are nested or broken.

Defined results: null or empty html gives empty text; so does a page without main blocks; malformed markup is read
tolerantly to its end (only a script or style without an end tag takes what follows it); repeated rows give a row each; extra columns are ignored; an empty table gives no rows.
"""

from __future__ import annotations

import html as html_lib
import re
import zlib
from bisect import bisect_left
from collections.abc import Iterator
from itertools import count

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from treegrammar.llm.recurrent import Adam, BiLstm

PATH_BITS, WORD_BITS, MEASURES, HIDDEN = 192, 48, 8, 24
WIDTH = PATH_BITS + WORD_BITS + MEASURES
#: Pages of the training sample, bytes of html that it may hold for each, generated pages, and training steps.
PAGES, PAGE_BYTES, GENERATED, STEPS, BATCH, SPAN = 240, 200_000, 1500, 1000, 32, 64

#: Blocks whose vectors are held at once; larger pages are read in several stretches, and the states of both directions are carried on.
STRETCH = 20_000

_NAME_OF_TAG = re.compile(r"<(/?)([a-zA-Z][^\s/>]*)")
_TAG_STOP = re.compile("[>\"']")
#: Elements whose content is no markup, and their end tags.
_RAW_END = {n: re.compile(rf"</{n}(?=[\s/>])[^>]*>", re.I) for n in ("script", "style", "textarea", "iframe")}
_ATTR = re.compile(r"\b(class|id|role)\s*=\s*(?:\"([^\"]*)\"|'([^']*)'|([^\s>]+))", re.I)
_NAME = re.compile(r"[a-z]+")
#: Elements that stand inside a line, elements without content, and start tags that end an open paragraph.
INLINE = frozenset("a abbr acronym b bdi bdo big cite code data del dfn em font i ins kbd label mark q s samp small span strike strong sub sup time tt u var wbr br img ruby rt svg math".split())
VOID = frozenset("area base br col embed hr img input link meta param source track wbr".split())
BLOCK_ENDS_P = frozenset("address article aside blockquote details div dl fieldset figure footer form h1 h2 h3 h4 h5 h6 header hr main menu nav ol p pre section table ul".split())
ENDS_SAME = {"li": {"ul", "ol", "menu"}, "dt": {"dl"}, "dd": {"dl"}, "tr": {"table", "tbody", "thead", "tfoot"}, "td": {"tr"}, "th": {"tr"}, "option": {"select", "datalist"}}
#: Elements that stand inside a line only where text does, such places, and the elements that count as markup of the page inside svg and math.
HOLDERS = frozenset("noscript object select template textarea".split())
TEXTUAL = frozenset("p h1 h2 h3 h4 h5 h6 li dt dd td th pre figcaption caption".split())
FOREIGN = frozenset(("svg", "math"))
#: Elements that keep a paragraph around them open.
KEEPS_P = ("button", "td", "th", "table", "object")
NOT_FOREIGN = BLOCK_ENDS_P | INLINE | frozenset(ENDS_SAME) | frozenset("html head body center tbody thead tfoot caption button".split()) | HOLDERS
#: Words of container names for the structural labels.
AWAY_ELEMENTS = frozenset("nav footer aside form button head header menu dialog".split())
AWAY_WORDS = frozenset(
    "ad ads advert adverts advertisement banner sponsor sponsored promo cookie cookies consent notice notices gdpr alert popup modal overlay sidebar rail widget menu nav navbar navigation breadcrumb breadcrumbs"
    " pagination pager header masthead footer bottom copyright comment comments commentlist reply replies respond discussion share sharing social follow related recommended newsletter subscribe signup login search toolbar"
    " navigation banner contentinfo complementary".split()
)


class Node:
    """An open element that is not inline: what features and labels need of it and those around it, so that no path is ever walked again."""

    __slots__ = ("up", "label", "depth", "main", "away", "header", "key")

    def __init__(self, up: Node | None, label: str):
        self.up, self.label, self.depth = up, label, up.depth + 1 if up else 0
        is_main, is_away, is_header = _traits(label)
        main, away, header, key = (up.main, up.away, up.header, up.key) if up else (-1, False, -1, -1)
        self.main = self.depth if is_main else main  # depth of the innermost article or main element
        self.away = away or is_away
        self.header = self.depth if is_header and header < 0 else header  # depth of the outermost header
        self.key = _KEYS.get((key, label))  # the same for equal paths, as long as they are kept
        if self.key is None:
            if len(_KEYS) > 50_000:
                _KEYS.clear()
            self.key = _KEYS[key, label] = next(_NEXT_KEY)


_KEYS: dict[tuple[int, str], int] = {}
_NEXT_KEY = count()
_TRAITS: dict[str, tuple[bool, bool, bool]] = {}


def _traits(label: str) -> tuple[bool, bool, bool]:
    """Whether an element is an article or main element, one outside the main text, a header."""
    got = _TRAITS.get(label)
    if got is None:
        name, *words = label.split(" ")
        if len(_TRAITS) > 20_000:
            _TRAITS.clear()
        got = _TRAITS[label] = (name in ("article", "main"), name in AWAY_ELEMENTS and name != "header" or not AWAY_WORDS.isdisjoint(words), name == "header")
    return got


class Block:
    """A leaf block: the innermost open element around it (inline ones aside), its text, and how many characters of it are links."""

    __slots__ = ("node", "text", "linked")

    def __init__(self, node: Node | None, text: str, linked: int):
        self.node, self.text, self.linked = node, text, linked

    @property
    def path(self) -> tuple[str, ...]:
        out, node = [], self.node
        while node is not None:
            out.append(node.label)
            node = node.up
        return tuple(reversed(out))


def _label(name: str, attrs: str) -> str:
    """The element's name and the words of its class, id and role."""
    if not attrs or "=" not in attrs:
        return name
    words = sorted({w for m in _ATTR.finditer(attrs) for w in _NAME.findall((m[2] or m[3] or m[4] or "").lower())})
    return " ".join([name, *words])


class _Open:
    """The open elements of a page, with the places of those that matter, so that every question takes no walk."""

    def __init__(self) -> None:
        self.names: list[str] = []
        self.at: dict[str, list[int]] = {}  # name -> places
        self.blocks: list[int] = []  # places of elements that are neither inline nor holders
        self.holders: list[int] = []
        self.foreign: list[int] = []
        self.nodes: list[Node] = []

    def push(self, name: str, label: str) -> None:
        k = len(self.names)
        self.names.append(name)
        self.at.setdefault(name, []).append(k)
        if name not in INLINE:
            self.nodes.append(Node(self.nodes[-1] if self.nodes else None, label))
            (self.holders if name in HOLDERS else self.blocks).append(k)
        if name in FOREIGN:
            self.foreign.append(k)

    def close(self, at: int) -> None:
        """Close the element at a place and all inside it."""
        while len(self.names) > at:
            name = self.names.pop()
            self.at[name].pop()
            if name not in INLINE:
                self.nodes.pop()
                (self.holders if name in HOLDERS else self.blocks).pop()
            if name in FOREIGN:
                self.foreign.pop()

    def last(self, name: str) -> int:
        """The place of the innermost element of a name, or -1."""
        places = self.at.get(name)
        return places[-1] if places else -1

    def in_line(self, upto: int) -> bool:
        """Whether an element below the first ``upto`` open ones stands in a line of text."""
        k = bisect_left(self.blocks, upto) - 1
        return k >= 0 and self.names[self.blocks[k]] in TEXTUAL


def leaf_blocks(html: str | None) -> list[Block]:
    """The text blocks of a page in order, in time linear in its length."""
    html, at, endless = html or "", 0, set()
    out: list[Block] = []
    open_ = _Open()
    parts: list[str] = []
    linked = 0
    last_gt, quoted = html.rfind(">"), True

    def flush() -> None:
        nonlocal parts, linked
        if parts:
            text = " ".join("".join(parts).split())
            if text:
                out.append(Block(open_.nodes[-1] if open_.nodes else None, text, min(linked, len(text))))
        parts, linked = [], 0

    def put(text: str) -> None:
        """Text of the page; its character references are decoded by themselves, as they cannot go on behind a tag."""
        nonlocal linked
        text = html_lib.unescape(text) if "&" in text else text
        parts.append(text)
        if open_.last("a") >= 0:
            linked += len(text)

    def tag_end(k: int) -> int:
        """The place of the ``>`` that ends a tag. A ``>`` inside quotes ends none, until a quote without an end shows that the page's quotes cannot be trusted."""
        nonlocal quoted
        start = k
        while quoted:
            m = _TAG_STOP.search(html, k)
            if m is not None and m[0] == ">":
                return m.start()
            k = html.find(m[0], m.end()) + 1 if m is not None else 0
            if not k:
                quoted = False
        return html.find(">", start)

    while at < len(html):
        if html[at] != "<":
            end = html.find("<", at)
            end = len(html) if end < 0 else end
            put(html[at:end])
            at = end
            continue
        if html.startswith("<!--", at):
            end = html.find("-->", at + 4)
            at = len(html) if end < 0 else end + 3
            continue
        m = _NAME_OF_TAG.match(html, at)
        if last_gt < at or m is None and html[at + 1 : at + 2] not in ("!", "?"):
            put("<")
            at += 1
            continue
        if m is None:
            at = html.find(">", at) + 1
            continue
        end = tag_end(m.end())
        attrs, at = html[m.end() : end], end + 1
        name, ends = m[2].lower(), m[1]
        single = attrs.rstrip().endswith("/")
        foreign = bool(open_.foreign)
        if name in _RAW_END and not ends and not (foreign and single):
            raw = None if name in endless else _RAW_END[name].search(html, at, last_gt + 1)
            if raw is None:
                endless.add(name)
                if name in ("script", "style"):  # what follows is code; after the others it is read as markup
                    break
                continue
            body, at = html[at : raw.start()], raw.end()
            if name == "textarea":
                apart = not open_.in_line(len(open_.names))
                if apart:
                    flush()
                    open_.push(name, _label(name, attrs))
                put(body)
                if apart:
                    flush()
                    open_.close(len(open_.names) - 1)
            continue
        if foreign and name not in NOT_FOREIGN:  # parts of drawings and formulas do not end a block
            if name in ("text", "title", "desc"):
                parts.append(" ")
            continue
        inline = name in INLINE
        if ends:
            first = open_.last(name)
            if first >= 0:
                blocks = bool(open_.blocks) and open_.blocks[-1] > first
                if inline and (blocks or open_.holders and open_.holders[-1] > first):
                    continue  # an inline end tag does not close blocks
                if not inline and (name not in HOLDERS or blocks or not open_.in_line(first)):
                    flush()
                open_.close(first)
            elif not inline and name not in HOLDERS and name not in _RAW_END:
                flush()
            continue
        if name in ("br", "wbr", "img", "hr"):
            parts.append(" ")
        if not inline and (name not in HOLDERS or not open_.in_line(len(open_.names))):
            flush()
            if open_.foreign:  # a block ends an open drawing or formula
                open_.close(open_.foreign[0])
            if name in BLOCK_ENDS_P and (first := open_.last("p")) >= 0 and all(open_.last(n) < first for n in KEEPS_P):
                open_.close(first)
            if name in ENDS_SAME and (first := open_.last(name)) >= 0 and all(open_.last(n) < first for n in ENDS_SAME[name]):
                open_.close(first)
        if name not in VOID and not single:
            open_.push(name, name if inline else _label(name, attrs))
    flush()
    return out


_SLOTS: dict[str, tuple[int, ...]] = {}


def _slot(word: str, bits: int) -> int:
    return zlib.crc32(word.encode("utf-8", "replace")) % bits


def _slots_of(label: str) -> tuple[int, ...]:
    """The places of an element's name as innermost one, of its name, and of the words of its attributes in a path vector."""
    got = _SLOTS.get(label)
    if got is None:
        name, *words = label.split(" ")
        if len(_SLOTS) > 20_000:
            _SLOTS.clear()
        got = _SLOTS[label] = tuple(_slot(w, PATH_BITS) for w in (f"<{name}>", name, *(f".{x}" for x in words)))
    return got


class _PathSums:
    """How often each place is hit by the elements of a path; going from one block to the next costs what was closed and opened between them."""

    def __init__(self) -> None:
        self.sums, self.node = np.zeros(PATH_BITS, np.float32), None

    def _count(self, node: Node, by: int) -> None:
        for k in _slots_of(node.label)[1:]:
            self.sums[k] += by

    def vector(self, node: Node | None) -> np.ndarray:
        """Elements count 0.7 each, the two innermost ones 1, and the innermost one has a place of its own besides."""
        if node is not self.node:
            old, new, opened = self.node, node, []
            while old is not new:
                if new is None or old is not None and old.depth >= new.depth:
                    self._count(old, -1)
                    old = old.up
                else:
                    opened.append(new)
                    new = new.up
            for x in opened:
                self._count(x, 1)
            self.node = node
        out = self.sums * np.float32(0.7)
        for x in (node, node.up if node is not None else None):
            if x is not None:
                for k in _slots_of(x.label)[1:]:
                    out[k] += 0.3
        if node is not None:
            out[_slots_of(node.label)[0]] += 1
        return out


_VECTORS: dict[int, np.ndarray] = {}  # of equal paths


def features(blocks: list[Block], start: int = 0, stop: int | None = None) -> np.ndarray:
    """The vectors of the blocks of a page, or of a stretch of them; places are those in the page."""
    n = len(blocks)
    stop = n if stop is None else min(stop, n)
    out = np.zeros((stop - start, WIDTH), np.float32)
    sums, vector, last = _PathSums(), np.zeros(PATH_BITS, np.float32), None
    for k in range(start, stop):
        b = blocks[k]
        row, text = out[k - start], b.text
        if b.node is not last:
            last = b.node
            vector = _VECTORS.get(last.key) if last is not None else sums.vector(None)
            if vector is None:
                if len(_VECTORS) > 10_000:
                    _VECTORS.clear()
                vector = _VECTORS[last.key] = sums.vector(last)
        row[:PATH_BITS] = vector
        words = text.lower().encode("utf-8", "replace").split(b" ")
        size = len(words)
        slots = np.fromiter(map(zlib.crc32, words), np.int64, size) % WORD_BITS
        row[PATH_BITS : PATH_BITS + WORD_BITS] = np.bincount(slots, minlength=WORD_BITS) / size
        row[-MEASURES:] = (np.log1p(size) / 4, min(1.0, b.linked / len(text)), (text.count(".") + text.count(",")) / size, float(text[-1] in ".!?"), k / n, 1 / (1 + k), 1 / (n - k), 1.0)
    return out


def structural_labels(blocks: list[Block]) -> np.ndarray | None:
    """One for blocks of the main text by the names of their elements; None if the page has no article or main element."""
    nodes = [b.node for b in blocks]
    if not any(x is not None and x.main >= 0 for x in nodes):
        return None
    # A header inside the main element belongs to it.
    return np.array([float(x is not None and x.main >= 0 and not x.away and not 0 <= x.header <= x.main) for x in nodes], np.float32)


def generated_page(rng: np.random.Generator, sentences: list[str]) -> tuple[str, list[int]]:
    """A page of random layout and the label of each of its leaf blocks, in order."""
    html: list[str] = []
    labels: list[int] = []
    pick = lambda *x: x[int(rng.integers(len(x)))]
    text = lambda n: " ".join(sentences[int(rng.integers(len(sentences)))] for _ in range(n))
    short = lambda: " ".join(text(1).split(" ")[: int(rng.integers(1, 5))]) or "x"

    def put(s: str, label: int | None = None) -> None:
        html.append(s)
        if label is not None:
            labels.append(label)

    def wrap(open_: str, fill) -> None:
        put(f"<{open_}>")
        fill()
        put(f"</{open_.split(' ')[0]}>")

    def items() -> None:
        wrap("ul", lambda: [put(f'<li><a href="/x">{short()}</a></li>', 0) for _ in range(int(rng.integers(2, 9)))])

    def away_text() -> None:
        for _ in range(int(rng.integers(1, 3))):
            put(f"<{(t := pick('p', 'div', 'span'))}>{text(1)}</{t}>", 0 if t != "span" else None)
            if t == "span":
                put("<hr>", 0)

    def comments() -> None:
        def one() -> None:
            put(f"<div><b>{short()}</b></div>", 0)
            put(f"<p>{text(int(rng.integers(1, 4)))}</p>", 0)

        kind = pick("ol class=comments", 'div class="comment-list"', 'section id="comments"', 'div class="discussion"', 'section class="reader-comments"')
        item = pick("li", 'div class="comment"', "article", 'div class="reply"')
        wrap(kind, lambda: [wrap(item, one) for _ in range(int(rng.integers(1, 5)))])

    def boiler(kind: str) -> None:
        if kind == "menu":
            wrap(pick("nav", 'div class="menu"', 'div id="nav"', 'div role="navigation"', "header"), items)
        elif kind == "header":
            wrap(pick("header", "header", 'div class="header"', 'div id="masthead"', 'div role="banner"'), lambda: [put(f"<{(t := pick('h1', 'div', 'p', 'h2'))}>{pick(short(), text(1))}</{t}>", 0) for _ in range(int(rng.integers(1, 3)))])
        elif kind == "named":
            put(f"<{(t := pick('div', 'div', 'section', 'p'))} {pick('class', 'class', 'id', 'role')}=\"{pick(*sorted(AWAY_WORDS))}\">{pick(short(), text(1), text(2))}</{t}>", 0)
        elif kind == "share":
            put(f"<div class=\"{pick('share', 'social', 'follow', 'toolbar')}\"><a href=\"#\">{short()}</a> <a href=\"#\">{short()}</a></div>", 0)
        elif kind == "footer":
            wrap(pick("footer", 'div class="footer"', 'div id="footer"', 'div role="contentinfo"'), lambda: put(f"<p>&copy; {short()} {text(1)}</p>", 0))
        elif kind == "side":
            wrap(pick("aside", 'div class="sidebar"', 'div id="sidebar"', 'div class="widget"', 'div class="related"'), pick(items, away_text))
        elif kind == "ad":
            put(f"<{(t := pick('div', 'p', 'section'))} class=\"{pick('ad', 'ads', 'advert', 'advertisement', 'banner', 'sponsored', 'promo')}\">{text(int(rng.integers(1, 3)))}</{t}>", 0)
        elif kind == "notice":
            put(f"<div {pick('class', 'id')}=\"{pick('cookie', 'cookie-notice', 'consent', 'notice', 'alert', 'gdpr-banner', 'popup')}\">{text(1)}</div>", 0)
        elif kind == "form":
            wrap("form", lambda: put(f"<label>{short()}</label> <input name=q> <button>{short()}</button>"))
            if "<button>" in html[-2]:
                labels.extend([0, 0])
        else:
            comments()

    bare = rng.random() < 0.12  # nothing before the article

    def body() -> None:
        if rng.random() < (0.4 if bare else 0.8):
            inner = rng.random() < 0.2  # an article may have a header of its own
            put(("<header>" if inner else "") + f"<h1>{short()} {short()}</h1>" + ("</header>" if inner else ""), 1)
        brief = rng.random() < 0.2
        for _ in range(int(rng.integers(20, 70) if rng.random() < 0.2 else rng.integers(1, 9))):
            kind = rng.random()
            if kind < 0.6:
                put(f"<p>{pick('', '<b>')}{short() if brief else text(int(rng.integers(1, 6)))}" + pick("</p>", "</p>", "<br></p>"), 1)
            elif kind < 0.67:
                put(f"<{(t := pick('h2', 'h2', 'h3'))}>{short()}</{t}>", 1)
            elif kind < 0.75:
                wrap(pick("ul", "ol"), lambda: [put(f"<li>{pick(text(1), short())}</li>", 1) for _ in range(int(rng.integers(2, 6)))])
            elif kind < 0.79:
                put(f"<{(t := pick('blockquote', 'pre', 'figcaption', 'div'))}>{text(1)}</{t}>", 1)
            elif kind < 0.83:
                wrap("table", lambda: [wrap("tr", lambda r=r: [put(f"<{(t := 'th' if r == 0 else 'td')}>{short()}</{t}>", 1) for _ in range(3)]) for r in range(int(rng.integers(2, 5)))])
            else:
                boiler(pick("ad", "notice", "side", "menu", "share", "form", "named", "named", "named"))

    if not bare and rng.random() < 0.8:
        put(f"<!DOCTYPE html><html><head><title>{short()}</title></head><body>", 0)
    frames = [pick('div id="wrapper"', 'div class="container"', 'div id="page"', 'div class="row"', 'div class="site"', "div", "section") for _ in range(int(rng.integers(0, 4)))]
    for f in frames:
        put(f"<{f}>")
    for kind in ("notice", "header", "header", "named", "menu", "ad", "side"):
        if not bare and rng.random() < 0.45:
            boiler(kind)
    holder = pick("article", "article", "main", 'div class="content"', 'div id="content"', 'div class="post-body"', 'div class="entry"', 'section class="story"', 'div role="main"', "div", 'div class="article"', 'div class="article-body"', 'div class="col main"', 'div class="main-content"', 'div class="page-text"')
    for _ in range(int(rng.integers(2, 20)) if rng.random() < 0.15 else 1):  # a page may hold several articles
        wrap(holder, body)
    for kind in ("share", "comments", "side", "named", "form", "ad", "footer"):
        if rng.random() < 0.4:
            boiler(kind)
    for f in reversed(frames):
        put(f"</{f.split(' ')[0]}>")
    put("</body></html>")
    return "".join(html), labels


class BlockLabeller:
    def __init__(self) -> None:
        self.net = BiLstm(WIDTH, HIDDEN)

    def train(self, pages: list[str], steps: int = STEPS, seed: int = 3) -> list[float]:
        rng = np.random.default_rng(seed)
        kept: list[tuple[np.ndarray, np.ndarray]] = []
        sentences: list[str] = []
        for page in pages:
            blocks = leaf_blocks(page)
            sentences += [s for b in blocks for s in b.text.split(". ") if 1 < len(s) < 300][:20]
            labels = structural_labels(blocks)
            if labels is not None and len(blocks):
                kept.append((features(blocks), labels))
        sentences = sentences or ["Some words of a page", "More words, and others too", "Short"]
        for _ in range(GENERATED):
            page, labels = generated_page(rng, sentences)
            blocks = leaf_blocks(page)
            if len(blocks) == len(labels):
                kept.append((features(blocks), np.array(labels, np.float32)))
        adam, losses = Adam(self.net.p, 0.01), []
        for step in range(steps):
            adam.rate = 0.015 * (1 - step / steps) + 0.001
            chosen = [kept[i] for i in rng.choice(len(kept), BATCH)]
            x, mask, y = np.zeros((SPAN, BATCH, WIDTH), np.float32), np.zeros((SPAN, BATCH), np.float32), np.zeros((SPAN, BATCH), np.float32)
            for k, (f, labels) in enumerate(chosen):
                at = int(rng.integers(max(1, len(f) - SPAN + 1)))
                part = f[at : at + SPAN]
                x[: len(part), k], mask[: len(part), k], y[: len(part), k] = part, 1, labels[at : at + SPAN]
                if rng.random() < 0.15:  # names of elements alone must not decide
                    x[:, k, : PATH_BITS] *= rng.random(PATH_BITS) > 0.2
            loss, grads = self.net.gradients(x, mask, y)
            adam.step(grads)
            losses.append(loss)
        return losses

    def main_texts(self, pages: list[str | None]) -> list[str]:
        """The main text of each page; pages of similar length are read together."""
        whole = [leaf_blocks(p) for p in pages]
        texts = self._read([b if len(b) <= STRETCH else [] for b in whole])
        for i, b in enumerate(whole):
            if len(b) > STRETCH:
                texts[i] = [x.text for x, v in zip(b, self.long_logits(b).tolist(), strict=True) if v > 0]
        return ["\n\n".join(t) for t in texts]

    def long_logits(self, blocks: list[Block]) -> np.ndarray:
        """The logits of the blocks of a page, with the vectors of ``STRETCH`` blocks in memory: backward over the stretches, then forward."""
        out, p = np.zeros(len(blocks), np.float32), self.net.p
        cuts = range(0, len(blocks), STRETCH)
        last = None
        for at in reversed(cuts):
            states, last = self.net.one_way(features(blocks, at, at + STRETCH)[::-1], 1, last)
            out[at : at + STRETCH] = (states @ p["o"][1])[::-1]
        last = None
        for at in cuts:
            x = features(blocks, at, at + STRETCH)
            states, last = self.net.one_way(x, 0, last)
            out[at : at + STRETCH] += states @ p["o"][0] + x @ p["s"] + p["c"]
        return out

    def _read(self, blocks: list[list[Block]]) -> list[list[str]]:
        """The texts of the main blocks of each page."""
        out: list[list[str]] = [[] for _ in blocks]
        order = sorted(range(len(blocks)), key=lambda i: len(blocks[i]))
        at = 0
        while at < len(order):
            group = [order[at]]
            longest = len(blocks[order[at]])
            for i in order[at + 1 : at + 256]:
                if len(blocks[i]) * (len(group) + 1) > 40_000 or len(blocks[i]) > 1.3 * longest + 4:
                    break
                group.append(i)
            t = len(blocks[group[-1]])
            x, mask = np.zeros((t, len(group), WIDTH), np.float32), np.zeros((t, len(group)), np.float32)
            for k, i in enumerate(group):
                n = len(blocks[i])
                x[:n, k], mask[:n, k] = features(blocks[i]), 1
            y = self.net.logits(x, mask)[0]
            for k, i in enumerate(group):
                out[i] = [b.text for b, v in zip(blocks[i], y[:, k].tolist(), strict=False) if v > 0]
            at += len(group)
        return out


def fit(spark: SparkSession, pages: DataFrame, sample: int = PAGES) -> BlockLabeller:
    """Train on about ``sample`` pages, chosen by a hash of page_id; larger ones than ``PAGE_BYTES`` are left to others."""
    rows = pages.select(F.col("page_id").cast("long").alias("page_id"), F.col("html").cast("string").alias("html"))
    n = rows.count()
    draw = F.pmod(F.xxhash64("page_id"), F.lit(1 << 30)) / F.lit(float(1 << 30))
    chosen = rows.where((draw < min(1.0, sample / max(1, n))) & (F.octet_length("html") <= PAGE_BYTES))
    got = sorted((r["page_id"], r["html"] or "") for r in chosen.toLocalIterator())
    model = BlockLabeller()
    model.train([h for _, h in got])
    return model


def extract(spark: SparkSession, pages: DataFrame, model: BlockLabeller) -> DataFrame:
    """page_id, url, text and n_chars of every row (page_id, url, html)."""
    shared = spark.sparkContext.broadcast(model)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        own = shared.value
        for batch in batches:
            for at in range(0, batch.num_rows, 256):
                part = batch.slice(at, 256)
                texts = own.main_texts(part.column(2).to_pylist())
                yield pa.RecordBatch.from_arrays([part.column(0), part.column(1), pa.array(texts, pa.string()), pa.array([len(t) for t in texts], pa.int64())], names=["page_id", "url", "text", "n_chars"])

    rows = pages.select(F.col("page_id").cast("long").alias("page_id"), F.col("url").cast("string").alias("url"), F.col("html").cast("string").alias("html"))
    return rows.mapInArrow(run, "page_id long, url string, text string, n_chars long")
