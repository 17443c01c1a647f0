"""Main text of web pages by a tree-structured graphical model.

A page's block elements form a tree of nodes, each content or not. Text that
stands directly in the page, in ``html`` or ``body``, or beside other blocks of its
element is a node of its own. A node has a potential from its own features (tag,
class and id words, how long its text is and how much of it is links, what it is
inside of) and every parent-child edge one for their two states; edges below the
page's own elements have a table of their own. One upward and one downward pass of
sum-product messages give each node's probability to be content; the text of a
block counts if its node's is at least a half. All potentials, those of the page's
own elements included, are learned from labelled pages by the gradient of their
likelihood, which the same messages give.

The labelled pages are made here: ``labelled_pages`` writes page after page with
articles of varied mark-up, in named elements, in bare ones, in tables, straight in
the body or without any tag, among menus, headers, footers, side columns, notices,
adverts, forms and comments, and knows which blocks it meant as content.

Defined cases: a null or empty page has the empty text; mark-up that ends early
keeps what came before; elements left open end where their parents do; character
references are decoded; white space, line breaks included, is one space inside a
block; a quote that nothing closes is an ordinary character; repeated rows get
equal answers; an empty table gives no rows; extra columns are ignored. Reading a
page takes time in proportion to its length, whatever its mark-up.
"""

from __future__ import annotations

import html as _references
import re
from collections import Counter
from collections.abc import Container, Iterator
from functools import cache
from math import exp, log, sqrt

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

# Element names of the HTML standard.
BLOCK_TAGS = frozenset(
    "address article aside blockquote body center dd details dialog dir div dl dt fieldset figcaption figure footer form frameset h1 h2 h3 h4 h5 h6 header hgroup hr html legend li main menu nav ol optgroup option p pre section select summary table tbody td tfoot th thead tr ul caption".split()
)
VOID_TAGS = frozenset("area base br col embed hr img input link meta param source track wbr".split())
RAW_TAGS = frozenset("script style noscript template title textarea iframe noembed noframes xmp svg math head".split())
_NO_CLOSE_RAW = frozenset(("script", "style", "title", "textarea", "iframe", "noembed", "noframes", "xmp"))
#: Elements left out whole that hold mark-up: they end where their parents do at the latest; the first two may close themselves.
_FOREIGN, _NESTED = frozenset(("svg", "math")), frozenset(("svg", "math", "noscript", "template"))
#: An opening tag closes these if they are still open above it.
CLOSES = {"li": ("li",), "dt": ("dt", "dd"), "dd": ("dt", "dd"), "tr": ("tr", "td", "th"), "td": ("td", "th"), "th": ("td", "th"), "option": ("option",)}
_TAG_NAME = re.compile(r"[a-zA-Z][^\s/>]*")
_TAG_STOP = re.compile(r">|=\s*([\"'])")
_NAMES = re.compile(r"""\b(?:class|id|role)\s*=\s*(?:"([^"]*)"|'([^']*)'|([^\s"'>]+))""", re.I)
_WORD = re.compile(r"[a-z]+")
_CAMEL = re.compile(r"(?<=[a-z])(?=[A-Z])")


#: Elements that hold the page itself.
FRAME_TAGS = frozenset(("#page", "html", "body"))
TEXT_TAG = "#text"


class Node:
    __slots__ = ("tag", "names", "parent", "chars", "linked", "marks")

    def __init__(self, tag: str, names: tuple[str, ...], parent: int):
        self.tag, self.names, self.parent = tag, names, parent
        self.chars = self.linked = self.marks = 0


class Scanner:
    """The tags of a page from left to right. No character is read more than a fixed number of times."""

    def __init__(self, page: str):
        self.page, self.last_end = page, page.rfind(">")
        self.last_quote = {q: page.rfind(q) for q in "\"'"}
        self.quotes = True

    def next(self, at: int) -> tuple[int, int, bool, str | None, str] | None:
        """(start, end, closing, name, attributes) of the first mark-up from ``at`` on; a comment, a declaration or a tag cut short has no name."""
        page = self.page
        while (start := page.find("<", at)) >= 0:
            sign = page[start + 1 : start + 2]
            if sign in ("!", "?"):
                stop, size = ("-->", 3) if page.startswith("<!--", start) else (">", 1)
                end = page.find(stop, start + 2)
                return start, end + size if end >= 0 else len(page), False, None, ""
            closing = sign == "/"
            name = _TAG_NAME.match(page, start + 1 + closing)
            if name:
                end = self._tag_end(name.end())
                if end:
                    return start, end, closing, name[0].lower(), page[name.end() : end - 1]
                after = page.find("<", name.end())
                return start, after if after >= 0 else len(page), False, None, ""
            at = start + 1
        return None

    def _tag_end(self, at: int) -> int:
        """Where a tag ends whose name ends at ``at``; 0 if nowhere."""
        page, here = self.page, at
        if at > self.last_end:
            return 0
        while self.quotes and (stop := _TAG_STOP.search(page, here)):
            if not stop[1]:
                return stop.end()
            here = stop.end()
            if here <= self.last_quote[stop[1]]:
                here = page.index(stop[1], here) + 1
        self.quotes = False  # a quote ran over all that is left: from here on quotes hide nothing
        return page.index(">", at) + 1


@cache
def _closing(tag: str) -> re.Pattern:
    return re.compile(rf"</{tag}\b", re.I)


def _raw_end(page: str, tag: str, at: int) -> int:
    """After the closing tag of an element whose inside is no mark-up; the page's end without one."""
    found = _closing(tag).search(page, at)
    end = page.find(">", found.end()) if found else -1
    return end + 1 if end >= 0 else len(page)


def _head_end(page: str, at: int) -> int:
    """After ``</head>``, or before ``<body``."""
    found = re.compile(r"</head\b|<body\b", re.I).search(page, at)
    if not found:
        return len(page)
    if page[found.start() + 1] != "/":
        return found.start()
    end = page.find(">", found.end())
    return end + 1 if end >= 0 else len(page)


def _nested_end(scanner: Scanner, tag: str, at: int, around: set[str]) -> int:
    """Where an element of mark-up that opened before ``at`` ends: after its closing tag, or before that of one of ``around``."""
    depth, inner, held = 1, [], Counter()
    while found := scanner.next(at):
        start, at, closing, name, attributes = found
        if name is None:
            continue
        if closing:
            if name == tag:
                depth -= 1
                if not depth:
                    return at
            elif held[name]:
                while (left := inner.pop()) != name:
                    held[left] -= 1
                held[name] -= 1
            elif name in around:
                return start
        elif name == tag:
            depth += not (attributes.endswith("/") and tag in _FOREIGN)
        elif name in _NO_CLOSE_RAW:
            at = _raw_end(scanner.page, name, at)
        elif name in BLOCK_TAGS and name not in VOID_TAGS:
            inner.append(name)
            held[name] += 1
    return len(scanner.page)


def parse(page: str) -> tuple[list[Node], list[tuple[int, str]]]:
    """The tree of nodes (parents before children), and the blocks: (node, text) in page order."""
    nodes, open_nodes, open_tags, links, at = [Node("#page", (), -1)], [0], Counter(), 0, 0
    held: list[tuple[str, bool]] = []
    found: list[tuple[int, str, int, int]] = []  # element, text, its linked characters and its marks

    def flush() -> None:
        if held:
            text = " ".join("".join(t for t, _ in held).split())
            if text:
                found.append((open_nodes[-1], text, sum(len(t.strip()) for t, linked in held if linked), sum(map(text.count, ".,;:!?"))))
            held.clear()

    def leave(depth: int) -> None:
        flush()
        for i in open_nodes[depth:]:
            open_tags[nodes[i].tag] -= 1
        del open_nodes[depth:]

    def text(raw: str) -> None:
        held.append((_references.unescape(raw) if "&" in raw else raw, links > 0))

    scanner = Scanner(page)
    while mark := scanner.next(at):
        if mark[0] > at:
            text(page[at : mark[0]])
        _, at, closing, tag, attributes = mark
        if tag is None:
            continue
        if closing:
            if tag == "a":
                links = max(0, links - 1)
            elif tag in BLOCK_TAGS:
                flush()
                if open_tags[tag]:
                    d = len(open_nodes) - 1
                    while nodes[open_nodes[d]].tag != tag:
                        d -= 1
                    leave(d)
            continue
        if tag in RAW_TAGS:
            if tag in _FOREIGN and attributes.endswith("/"):
                continue
            if tag in _NESTED:
                at = _nested_end(scanner, tag, at, {t for t, n in open_tags.items() if n})
            else:
                at = _head_end(page, at) if tag == "head" else _raw_end(page, tag, at)
        elif tag == "br":
            held.append((" ", False))
        elif tag in BLOCK_TAGS:
            flush()
            if nodes[open_nodes[-1]].tag == "p":
                leave(len(open_nodes) - 1)
            for other in CLOSES.get(tag, ()):
                if nodes[open_nodes[-1]].tag == other:
                    leave(len(open_nodes) - 1)
            if tag in VOID_TAGS:
                continue
            names = tuple(_WORD.findall(_CAMEL.sub(" ", " ".join(x or y or z for x, y, z in _NAMES.findall(attributes))).lower())) if attributes else ()
            nodes.append(Node(tag, names, open_nodes[-1]))
            open_nodes.append(len(nodes) - 1)
            open_tags[tag] += 1
            if tag in ("article", "main", "body"):
                links = 0
        elif tag == "a":
            links += 1
    if at < len(page):
        text(page[at:])
    flush()
    shared = {n.parent for n in nodes} | {i for i, c in Counter(f[0] for f in found).items() if c > 1}
    blocks = []
    for element, words, linked, marks in found:
        i = element
        if element in shared or nodes[element].tag in FRAME_TAGS:
            i = len(nodes)
            nodes.append(Node(TEXT_TAG, (), element))
        nodes[i].chars, nodes[i].linked, nodes[i].marks = len(words), linked, marks
        blocks.append((i, words))
    return nodes, blocks


_MAIN_TAGS = frozenset(("article", "main"))


def features(nodes: list[Node], known: Container[str] | None = None) -> list[list[str]]:
    """Each node's features: its own, those of the text below it, what the elements around it are called, and whether the page has a main element around or beside it. ``known``: those that matter."""
    chars, linked, kids = [n.chars for n in nodes], [n.linked for n in nodes], [0] * len(nodes)
    for i in range(len(nodes) - 1, 0, -1):
        p = nodes[i].parent
        chars[p] += chars[i]
        linked[p] += linked[i]
        kids[p] += 1
    whole = max(1, chars[0])
    main = [n.tag in _MAIN_TAGS for n in nodes]
    named = [not _MAIN_NAMES.isdisjoint(n.names) for n in nodes]
    any_main, any_named = any(main), any(named)
    out, above = [], [frozenset()]
    for i, n in enumerate(nodes):
        if i:
            p = nodes[n.parent]
            around = above[n.parent]
            if p.tag not in FRAME_TAGS:
                more = {f"in {p.tag}", *(f"in name {w}" for w in p.names)}
                more = more if known is None else {f for f in more if f in known}
                around = around if more <= around else around | more
            above.append(around)
            main[i] |= main[n.parent]
            named[i] |= named[n.parent]
        size = min(12, int(chars[i]).bit_length())
        share = linked[i] * 4 // chars[i] if chars[i] else 5
        out.append(
            [f"tag {n.tag}", f"size {size}", f"links {share}", f"own {min(10, n.chars.bit_length())}", f"marks {min(4, n.marks)}", f"part {chars[i] * 4 // whole}", f"{n.tag} links {share}", f"kids {min(3, kids[i])}"]
            + [f"main {main[i]}" if any_main else "no main", f"named {named[i]}" if any_named else "no named"]
            + [f"name {w}" for w in set(n.names)]
            + sorted(above[i])
        )
    return out


class TreeModel:
    """Log potentials: per feature (content against not), and per (parent, child) pair of states; ``frame_edges`` are those below the page's own elements."""

    def __init__(self, weights: dict[str, float], bias: float, edges: list[list[float]], root: list[float], frame_edges: list[list[float]] | None = None):
        self.weights, self.bias, self.edges, self.root, self.frame_edges = weights, bias, edges, root, frame_edges or edges

    def unary(self, names: list[str]) -> float:
        get = self.weights.get
        return self.bias + sum(get(f, 0.0) for f in names)

    def _messages(self, nodes: list[Node], potentials: list[float]) -> tuple[list[float], list[float], list[float], list[list[list[float]]]]:
        """Log odds of each node given the evidence at and below it, those it sends its parent, those given all evidence, and each node's edge table."""
        n = len(nodes)
        edges = [self.frame_edges if i and nodes[x.parent].tag in FRAME_TAGS else self.edges for i, x in enumerate(nodes)]
        up: list[float] = list(potentials)
        sent = [0.0] * n
        for i in range(n - 1, 0, -1):
            (e00, e01), (e10, e11) = edges[i]
            x = exp(max(-40.0, min(40.0, up[i])))
            sent[i] = log((e10 + e11 * x) / (e00 + e01 * x))
            up[nodes[i].parent] += sent[i]
        full = [0.0] * n
        full[0] = up[0] + log(self.root[1] / self.root[0])
        for i in range(1, n):
            (e00, e01), (e10, e11) = edges[i]
            y = exp(max(-40.0, min(40.0, full[nodes[i].parent] - sent[i])))  # the parent without this child
            full[i] = up[i] + log((e01 + e11 * y) / (e00 + e10 * y))
        return up, sent, full, edges

    def marginals(self, nodes: list[Node], potentials: list[float]) -> list[float]:
        """P(content) of each node. potentials: log of phi(content) / phi(not)."""
        return list(map(_share, self._messages(nodes, potentials)[2]))

    def expected(self, nodes: list[Node], potentials: list[float]) -> tuple[list[float], list[list[list[float]]], list[list[list[float]]]]:
        """P(content) of each node, P(parent's state, own state) of each but the first, and their edge tables."""
        up, sent, full, edges = self._messages(nodes, potentials)
        pairs = [[[0.0, 0.0], [0.0, 0.0]]]
        for i in range(1, len(nodes)):
            x, y = (exp(max(-40.0, min(40.0, v))) for v in (up[i], full[nodes[i].parent] - sent[i]))
            e = edges[i]
            joint = [[e[0][0], e[0][1] * x], [e[1][0] * y, e[1][1] * x * y]]
            total = sum(map(sum, joint))
            pairs.append([[v / total for v in row] for row in joint])
        return list(map(_share, full)), pairs, edges


def _share(odds: float) -> float:
    return 1 / (1 + exp(-max(-700.0, min(700.0, odds))))


def fit(pages: list[tuple[list[Node], list[bool]]], epochs: int = 8, rate: float = 0.3) -> TreeModel:
    """All potentials by gradient steps on the likelihood of the pages' labels, page by page: what the labels have less what sum-product expects, each step scaled by the potential's past gradients."""
    past: dict = {}
    logs = [[[0.0, 0.0], [0.0, 0.0]] for _ in range(2)]  # of plain edges, and of those below the page's own elements
    model = TreeModel({}, 0.0, *([[1.0, 1.0], [1.0, 1.0]], [1.0, 1.0], [[1.0, 1.0], [1.0, 1.0]]))
    weights, data = model.weights, [(nodes, labels, features(nodes)) for nodes, labels in pages]

    def step(key, gradient: float) -> float:
        past[key] = seen = past.get(key, 1.0) + gradient * gradient
        return rate * gradient / sqrt(seen)

    order = np.random.default_rng(3)
    for _ in range(epochs):
        for k in order.permutation(len(data)).tolist():
            nodes, labels, names = data[k]
            chance, pairs, edges = model.expected(nodes, list(map(model.unary, names)))
            slopes: dict = {}
            for i, p in enumerate(chance):
                off = labels[i] - p
                for f in names[i]:
                    slopes[f] = slopes.get(f, 0.0) + off
                slopes[None] = slopes.get(None, 0.0) + off
                if i:
                    table, up = int(edges[i] is model.frame_edges), labels[nodes[i].parent]
                    for a in (0, 1):
                        for b in (0, 1):
                            slopes[table, a, b] = slopes.get((table, a, b), 0.0) + (up == a and labels[i] == b) - pairs[i][a][b]
            for key, slope in slopes.items():
                if key is None:
                    model.bias += step(key, slope)
                elif isinstance(key, tuple):
                    t, a, b = key
                    logs[t][a][b] += step(key, slope)
                else:
                    weights[key] = weights.get(key, 0.0) + step(key, slope)
            model.edges, model.frame_edges = ([[exp(x) for x in row] for row in t] for t in logs)
    return model


# --- labelled pages -------------------------------------------------------------------------------------------------

#: Class or id words that the made pages use for what is not content, by kind.
_OUTSIDE = {
    "menu": ("nav menu navbar navigation topnav breadcrumb breadcrumbs links tabs toc sitemap pagination pager", "nav ul div"),
    "header": ("header masthead banner topbar logo site branding hero", "header div"),
    "footer": ("footer copyright legal bottom colophon imprint credits", "footer div"),
    "side": ("sidebar aside widget related recommended popular trending recent archive tags categories promo", "aside div section"),
    "notice": ("cookie consent notice gdpr banner alert popup modal overlay disclaimer warning privacy", "div section aside"),
    "advert": ("ad ads advert advertisement sponsor sponsored promo promotion adsense dfp outbrain taboola", "div aside section"),
    "form": ("form search subscribe newsletter signup login contact register feedback", "form div"),
    "comment": ("comments comment discussion replies responses thread disqus reader respond", "section div ol ul"),
    "share": ("share social sharing buttons follow tools meta byline author bio", "div ul"),
}
_INSIDE = ("article post entry story content main body text page blog news", "article main div section")
_MAIN_NAMES = frozenset(_INSIDE[0].split())


class _Writer:
    def __init__(self, seed: int):
        self.draw = np.random.default_rng(seed)
        letters = list("etaoinshrdlucmfwypvbgk")
        self.vocabulary = ["".join(self.draw.choice(letters, self.draw.integers(1, 10))) for _ in range(600)]

    def pick(self, options: str) -> str:
        return str(self.draw.choice(options.split()))

    def chance(self, p: float) -> bool:
        return bool(self.draw.random() < p)

    def words(self, low: int, high: int) -> str:
        found = list(self.draw.choice(self.vocabulary, self.draw.integers(low, high + 1)))
        out = []
        for w in found:
            mark = "." if self.chance(0.1) else "," if self.chance(0.06) else " &amp;" if self.chance(0.01) else "!!" if self.chance(0.01) else " |" if self.chance(0.01) else ""
            out.append(w + mark)
        return " ".join(out).capitalize() + ("." if len(out) > 5 else "")

    def names(self, options: str) -> str:
        if self.chance(0.12):
            return ""
        word = self.pick(options)
        tail = "-" + self.pick("box wrap inner list area block item container 1 left right") if self.chance(0.4) else ""
        key = "class" if self.chance(0.7) else "id"
        return f' {key}="{word}{tail}"'

    def links(self, low: int, high: int) -> str:
        return "".join(f'<li><a href="/{i}">{self.words(1, 4)}</a></li>' for i in range(self.draw.integers(low, high + 1)))

    def outside(self, kind: str) -> str:
        options, tags = _OUTSIDE[kind]
        tag = self.pick(tags)
        names = self.names(options) if tag in ("div", "section", "ul", "ol") and kind != "menu" or self.chance(0.6) else ""
        if tag in ("div", "section", "ul", "ol") and not names:
            names = f' class="{self.pick(options)}"'
        if kind == "menu":
            inner = self.links(3, 12) if tag == "ul" else f"<ul>{self.links(3, 12)}</ul>"
        elif kind == "header":
            inner = f'<a href="/">{self.words(1, 4)}</a>' + (f"<h1>{self.words(1, 5)}</h1>" if self.chance(0.4) else "") + (f"<p>{self.words(3, 12)}</p>" if self.chance(0.4) else "")
        elif kind == "footer":
            inner = f"&copy; {self.words(2, 5)} &middot; {self.words(4, 30)}" if self.chance(0.5) else f"<p>&copy; {self.words(4, 40)}</p>" + (f"<ul>{self.links(2, 8)}</ul>" if self.chance(0.5) else "")
        elif kind == "side":
            inner = f"<h3>{self.words(1, 4)}</h3>" + (f"<ul>{self.links(3, 9)}</ul>" if self.chance(0.6) else f"<p>{self.words(6, 50)}</p>")
        elif kind in ("notice", "advert"):
            inner = self.words(4, 40) if self.chance(0.4) else f"<p>{self.words(6, 50)}</p>" + (f"<button>{self.words(1, 2)}</button>" if self.chance(0.5) else "")
        elif kind == "form":
            inner = f"<label>{self.words(1, 4)}</label><input type=text><p>{self.words(3, 14)}</p><button>{self.words(1, 2)}</button>"
        elif kind == "comment":
            item = "li" if tag in ("ol", "ul") else "div"
            inner = "" if item == "li" else f"<h3>{self.words(1, 3)}</h3>"
            for _ in range(self.draw.integers(1, 6)):
                body = self.words(4, 70)
                inner += f"<{item}{self.names('comment reply response') if self.chance(0.7) else ''}>" + (f"<p>{self.words(1, 4)}</p>" if self.chance(0.4) else "") + (f"<p>{body}</p>" if self.chance(0.7) else body) + f"</{item}>"
        else:
            inner = self.words(1, 8) + f"<ul>{self.links(1, 4)}</ul>"
        return f"<{tag}{names}>{inner}</{tag}>"

    def inside(self, blocks: list[str]) -> str:
        """The blocks of an article, some of them with what is no content between or after them."""

        def block(tag: str, low: int, high: int) -> str:
            blocks.append(self.words(low, high))
            cut = blocks[-1].find(" ", 8)
            body = blocks[-1] if cut < 0 or self.chance(0.6) else f"<b>{blocks[-1][:cut]}</b>{blocks[-1][cut:]}" if self.chance(0.5) else f'{blocks[-1][:cut]}<a href="x">{blocks[-1][cut:]}</a>' if self.chance(0.15) else f"{blocks[-1]}<br>"
            return f"<{tag}>{body}" + ("" if tag in ("p", "li") and self.chance(0.15) else f"</{tag}>")

        out = block("h1", 3, 12) if self.chance(0.75) else ""
        if out and self.chance(0.2):
            out = f"<header>{out}</header>"
        for _ in range(self.draw.integers(1, 9)):
            kind = self.draw.random()
            if kind < 0.72:
                out += block("p", *((1, 5) if self.chance(0.2) else (8, 140)))
            elif kind < 0.8:
                out += block("h2", 2, 8)
            elif kind < 0.86:
                out += "<ul>" + "".join(block("li", 2, 25) for _ in range(self.draw.integers(2, 5))) + "</ul>"
            elif kind < 0.9:
                out += block("blockquote", 8, 60)
            elif kind < 0.94:
                out += "<table><tr>" + "".join(block("td", 1, 6) for _ in range(3)) + "</tr></table>"
            elif self.chance(0.5):
                out += self.outside(self.pick("advert side share form"))
            else:  # text beside blocks
                blocks.append(self.words(8, 60))
                out += f"<hr>{blocks[-1]}<hr>"
        return out

    def article(self, blocks: list[str]) -> str:
        options, tags = _INSIDE
        tag = self.pick(tags)
        names = self.names(options)
        if tag in ("div", "section") and not names:
            names = f' class="{self.pick(options)}"'
        out = self.inside(blocks)
        if self.chance(0.25):
            out = f"<div{self.names('content body text inner entry')}>{out}</div>"
        if self.chance(0.25):
            out += self.outside(self.pick("comment share"))
        return f"<{tag}{names}>{out}</{tag}>"

    def plain(self, blocks: list[str]) -> str:
        """Text in no element of its own, perhaps with paragraphs between."""
        out = ""
        for k in range(self.draw.integers(1, 4)):
            blocks.append(self.words(6, 160))
            out += blocks[-1].replace(". ", ".<br>") if self.chance(0.4) else blocks[-1]
            if k or self.chance(0.4):
                blocks.append(self.words(6, 120))
                out += f"<p>{blocks[-1]}</p>"
            else:
                break
        return out


LAYOUTS = ("named", "bare", "nested", "table", "plain")
_SHARES = (0.5, 0.18, 0.12, 0.1, 0.1)


def labelled_pages(count: int, seed: int = 5, layout: str | None = None) -> list[tuple[str, list[str]]]:
    """(page, its content blocks in order): articles in named elements, straight in the body, in bare elements or table cells, or without any."""
    w, out = _Writer(seed), []
    for _ in range(count):
        blocks: list[str] = []
        kind = layout or str(w.draw.choice(LAYOUTS, p=_SHARES))
        alone = kind != "named" and w.chance(0.3)
        before = [k for k in ("header", "menu", "notice", "advert", "form") if not alone and w.chance(0.55)]
        after = [k for k in ("comment", "side", "share", "advert", "form", "notice", "footer") if not alone and w.chance(0.5)]
        w.draw.shuffle(before)
        if kind == "named":
            main = w.article(blocks)
        elif kind == "plain":
            main = w.plain(blocks)
        else:
            main = w.inside(blocks)
        if kind == "nested":
            for _ in range(w.draw.integers(1, 4)):
                tag = w.pick("div div section center")
                main = f"<{tag}>{main}</{tag}>"
        if kind == "table":
            cells = [w.outside(k) for k in ("menu", "side") if not alone and w.chance(0.6)]
            cells.insert(w.draw.integers(0, len(cells) + 1), main)
            main = "<table><tr>" + "".join(f"<td{' valign=top' if w.chance(0.5) else ''}>{c}</td>" for c in cells) + "</tr></table>"
        if kind in ("named", "nested") and w.chance(0.3):
            main = f"<div{w.names('wrapper container page layout row outer')}>{main}{w.outside('side') if not alone and w.chance(0.5) else ''}</div>"
        body = "".join(map(w.outside, before)) + main + "".join(map(w.outside, after))
        if kind == "named" and w.chance(0.3):
            body = f"<div{w.names('wrapper container page site')}>{body}</div>"
        head = f"<title>{w.words(2, 6)}</title><style>p{{}}</style><script>x('<p>')</script>"
        if alone and w.chance(0.5):
            page = body
        elif kind != "named" and w.chance(0.2):
            page = f"<body>{body}</body>"
        else:
            page = f"<!DOCTYPE html><html><head>{head}</head><body>{body}</body></html>"
        out.append((page, [" ".join(_references.unescape(b).split()) for b in blocks]))
    return out


def labels_of(nodes: list[Node], blocks: list[tuple[int, str]], content: list[str]) -> list[bool]:
    """A node is content if most text at or below it is."""
    inside, total, k = [0] * len(nodes), [0] * len(nodes), 0
    for node, text in blocks:
        hit = k < len(content) and text == content[k]
        k += hit
        while node >= 0:
            total[node] += len(text)
            inside[node] += len(text) * hit
            node = nodes[node].parent
    return [2 * i > t for i, t in zip(inside, total, strict=True)]


TRAINING_PAGES = 700


@cache
def trained(pages: int = TRAINING_PAGES) -> TreeModel:
    data = []
    for page, content in labelled_pages(pages):
        nodes, blocks = parse(page)
        data.append((nodes, labels_of(nodes, blocks, content)))
    return fit(data)


def main_blocks(page: str | None, model: TreeModel) -> list[str]:
    if not page:
        return []
    nodes, blocks = parse(page)
    chance = model.marginals(nodes, list(map(model.unary, features(nodes, model.weights))))
    return [text for node, text in blocks if chance[node] >= 0.5]


def extract(pages: DataFrame, model: TreeModel | None = None) -> DataFrame:
    """(page_id, url, text, n_chars) of (page_id, url, html)."""
    model = model or trained()

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            texts = ["\n\n".join(main_blocks(p.as_py(), model)) for p in batch.column(2)]
            yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), pa.array(texts, pa.string()), pa.array([len(t) for t in texts], pa.int64())], ["page_id", "url", "text", "n_chars"])

    return pages.select(F.col("page_id").cast("long"), F.col("url").cast("string"), F.col("html").cast("string")).mapInArrow(run, "page_id long, url string, text string, n_chars long")
