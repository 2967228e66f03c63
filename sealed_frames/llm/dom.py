"""A forgiving HTML parser into a small tree, fast enough for whole crawls.

Comments, declarations and the contents of raw-text elements leave no text; character references are
decoded; end tags that are left out are supplied for paragraphs, list items, table parts and options;
stray end tags are passed over; what is open at the end of the page is closed.
"""

from __future__ import annotations

import re
from bisect import bisect_right
from functools import lru_cache
from html import unescape

# Element names of HTML by how they are parsed or laid out.
VOID = frozenset("area base br col embed hr img input link meta param source track wbr".split())
RAW = frozenset("script style textarea title noscript iframe noembed noframes xmp template svg math".split())
INLINE = frozenset(
    "a abbr acronym b bdi bdo big cite code data del dfn em font i img ins kbd label mark nobr q s samp small span strike strong sub sup time tt u var wbr br ruby rb rt rp picture source".split()
)
#: Open elements that a start tag closes, up to the nearest of the elements behind the bar.
_LIST = frozenset({"ul", "ol", "menu"})
_TABLE = frozenset({"table"})
CLOSES = {
    "li": (frozenset({"li"}), _LIST),
    "dt": (frozenset({"dt", "dd"}), frozenset({"dl"})),
    "dd": (frozenset({"dt", "dd"}), frozenset({"dl"})),
    "tr": (frozenset({"tr", "td", "th"}), _TABLE),
    "td": (frozenset({"td", "th"}), _TABLE | {"tr"}),
    "th": (frozenset({"td", "th"}), _TABLE | {"tr"}),
    "tbody": (frozenset({"thead", "tbody", "tr", "td", "th"}), _TABLE),
    "option": (frozenset({"option"}), frozenset({"select"})),
}
ENDS_PARAGRAPH = frozenset(
    "address article aside blockquote center details dialog dir div dl fieldset figcaption figure footer form h1 h2 h3 h4 h5 h6 header hgroup hr main menu nav ol p pre section summary table ul".split()
)

_OPEN = re.compile(r"<(?:!--|(/?)([a-zA-Z][^\s/>]*)|[!?/])")
_COMMENT_END = re.compile(r"--!?>")
_STOP = re.compile(r">|=\s*([\"'])")
_ATTRIBUTE = re.compile(r"([^\s=/\"'>]+)(?:\s*=\s*(?:\"([^\"]*)\"|'([^']*)'|([^\s\"'>]+)))?")


class Node:
    """An element; ``items`` holds its text pieces (str) and child elements in page order."""

    __slots__ = ("tag", "attributes", "items", "index")

    def __init__(self, tag: str, attributes: str = ""):
        self.tag, self.attributes = tag, attributes
        self.items: list[Node | str] = []
        self.index = -1

    def named(self) -> dict[str, str]:
        out: dict[str, str] = {}
        for m in _ATTRIBUTE.finditer(self.attributes):
            out.setdefault(m[1].lower(), unescape(m[2] or m[3] or m[4] or ""))
        return out


def _tag_end(html: str, at: int, last_quote: dict[str, int]) -> int:
    """Place of the bracket that ends a tag, those in quoted values aside; -1: there is none.

    Quotes count behind an equals sign only, and only if one follows that closes them."""
    while (m := _STOP.search(html, at)) is not None:
        if m[1] is None:
            return m.start()
        at = m.end() if m.end() > last_quote[m[1]] else html.index(m[1], m.end()) + 1
    return -1


@lru_cache(maxsize=64)
def _raw_end(name: str) -> re.Pattern:
    return re.compile(rf"</{re.escape(name)}(?=[\s/>])", re.I)


def _pieces(html: str):
    """(text, end tag?, name, attributes) of each tag with the text before it; name None at the end.

    Reads forward only: time is linear in the page, however broken it is. Once a tag has no end outside
    quotes, quotes mean nothing in the rest of the page."""
    last, last_quote, quotes = html.rfind(">"), {q: html.rfind(q) for q in "\"'"}, True
    at = 0
    while (m := _OPEN.search(html, at)) is not None:
        start, after, name = m.start(), m.end(), m[2]
        if start > last:  # no tag ends any more, but a comment needs no end
            name, start = None, html.find("<!--", start)
            if start < 0:
                break
        if name is None:
            yield html[at:start], False, "", ""
            if html.startswith("<!--", start):
                end = _COMMENT_END.search(html, start + 4)
                at = end.end() if end else len(html)
            else:
                at = html.index(">", after) + 1
            continue
        stop = _tag_end(html, after, last_quote) if quotes else -1
        if stop < 0:
            quotes, stop = False, html.index(">", after)
        name, attributes = name.lower(), html[after:stop]
        yield html[at:start], bool(m[1]), name, attributes
        at = stop + 1
        if not m[1] and name in RAW and not attributes.rstrip().endswith("/"):
            end = _raw_end(name).search(html, at)
            at = html.index(">", end.end()) + 1 if end and end.start() < last else len(html)
    yield html[at:], False, None, ""


class _Open:
    """The open elements, root first, with the places of each name, of blocks and of all but inline ones."""

    def __init__(self, root: Node):
        self.nodes, self.blocks, self.solid = [root], [], [0]
        self.places: dict[str, list[int]] = {}

    def push(self, node: Node) -> None:
        at = len(self.nodes)
        self.nodes.append(node)
        self.places.setdefault(node.tag, []).append(at)
        if node.tag in ENDS_PARAGRAPH:
            self.blocks.append(at)
        if node.tag not in INLINE:
            self.solid.append(at)

    def cut(self, at: int) -> None:
        """Close the element at a place and all within it."""
        while len(self.nodes) > at:
            tag = self.nodes.pop().tag
            self.places[tag].pop()
            if tag in ENDS_PARAGRAPH:
                self.blocks.pop()
            if tag not in INLINE:
                self.solid.pop()

    def innermost(self, tags) -> int:
        return max((p[-1] for t in tags if (p := self.places.get(t))), default=0)

    def outermost_within(self, tags, at: int) -> int:
        """Place of the first of ``tags`` behind a place; 0: none."""
        found = []
        for p in filter(None, map(self.places.get, tags)):
            if (i := bisect_right(p, at)) < len(p):
                found.append(p[i])
        return min(found, default=0)


def parse(html: str) -> Node:
    root = Node("#page")
    opened = _Open(root)
    for text, closing, name, attributes in _pieces(html):
        if text:
            opened.nodes[-1].items.append(unescape(text) if "&" in text else text)
        if not name:
            continue
        if closing:
            at = 0 if name in VOID or name in RAW else opened.innermost((name,))
            if at and not (name in INLINE and opened.blocks and opened.blocks[-1] > at):
                opened.cut(at)
            continue
        if name in ENDS_PARAGRAPH and opened.nodes[opened.solid[-1]].tag == "p":
            opened.cut(opened.solid[-1])
        if name in CLOSES:
            shut, stop = CLOSES[name]
            if at := opened.outermost_within(shut, opened.innermost(stop)):
                opened.cut(at)
        node = Node(name, attributes)
        opened.nodes[-1].items.append(node)
        if name not in VOID and name not in RAW and not (attributes.endswith("/") and name in INLINE and name != "a"):
            opened.push(node)
    return root
