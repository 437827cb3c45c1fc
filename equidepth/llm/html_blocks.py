"""Leaf blocks of an HTML page: runs of text between block-level tags, with the tags above them.

A tolerant reader: unclosed and misnested tags, comments, doctypes, CDATA and raw-text elements are read as
browsers do where that decides which text belongs together. Inline tags and line breaks stay inside a
block; references are decoded; white space becomes one space.

The tags above a block are a node of a tree of paths: blocks and pages under the same tags share it, and a node holds only what
it adds to its parent, so nesting of any depth costs as much as its tags. Closing a tag looks up where it is open.
"""

from __future__ import annotations

import re
from dataclasses import dataclass
from html import unescape

TOKEN = re.compile(r"<!--.*?(?:--!?>|$)|<!\[CDATA\[(.*?)(?:\]\]>|$)|<[!?][^>]*>?|<(/?)([a-zA-Z][^\s/>]*)((?:=\s*+(?:\"[^\"]*+\"|'[^']*+'|[\"'].*+|[^\s>]*+)|[^>=]++)*+)>?", re.S)
ATTRIBUTE = re.compile(r"([^\s=/>\"']+)\s*(?:=\s*(\"[^\"]*\"|'[^']*'|[^\s>]+))?")
SPACE = re.compile(r"\s+")
NAMES = re.compile(r"[a-z]+|[0-9]+")

# Elements of the HTML standard by how they shape blocks.
VOID = frozenset("area base br col embed hr img input link meta param source track wbr".split())
RAW = frozenset("script style noscript template textarea title iframe noframes xmp svg math".split())
INLINE = frozenset("a abbr acronym b bdi bdo big br cite code data del dfn em font i img ins kbd label mark q rp rt ruby s samp small span strike strong sub sup time tt u var wbr".split())
CLOSES_P = frozenset("address article aside blockquote center details dialog dir div dl fieldset figcaption figure footer form h1 h2 h3 h4 h5 h6 header hgroup hr main menu nav ol p pre search section summary table ul".split())
SAME = {"li": {"li"}, "dt": {"dt", "dd"}, "dd": {"dt", "dd"}, "tr": {"tr", "td", "th"}, "td": {"td", "th"}, "th": {"td", "th"}, "option": {"option"}}
HOLDERS = frozenset("article main aside nav header footer form section".split())
FENCE = frozenset("ul ol dl table div section article main aside nav header footer body form".split())


class Node:
    """A path of open tags: the last tag with the words of its class, id and role, under its parent.

    fresh: its tag and words that no tag above has; near: the words nearest above or here; holder: the nearest sectioning tag.
    """

    __slots__ = ("tag", "names", "parent", "fresh", "near", "holder", "kids")

    def __init__(self, tag: str, names: tuple[str, ...], parent: "Node | None", fresh: tuple[tuple[str, ...], tuple[str, ...]] = ((), ())):
        self.tag, self.names, self.parent, self.fresh, self.kids = tag, names, parent, fresh, {}
        self.near = names or (parent.near if parent else ())
        self.holder = tag if tag in HOLDERS else parent.holder if parent else "none"

    def up(self):
        """This node and those above it, the root without a tag left out."""
        node = self
        while node.parent is not None:
            yield node
            node = node.parent


@dataclass
class Block:
    """Text of a leaf block; the open tags above it; length inside links; bold."""

    text: str
    path: Node
    link_chars: int
    links: int
    breaks: int


class Stack:
    """The open tags, where each is, and which words they hold."""

    def __init__(self, root: Node):
        self.root, self.nodes, self.where, self.fences, self.held = root, [], {}, [], {}

    @property
    def top(self) -> Node:
        return self.nodes[-1] if self.nodes else self.root

    def push(self, tag: str, names: tuple[str, ...]) -> None:
        above, places = self.top, self.where.setdefault(tag, [])
        node = above.kids.get((tag, names))
        if node is None:
            fresh = tuple(dict.fromkeys(n for n in names if not self.held.get(n)))
            node = above.kids[tag, names] = Node(tag, names, above, (() if places else (tag,), fresh))
        if tag in FENCE:
            self.fences.append(len(self.nodes))
        places.append(len(self.nodes))
        self.nodes.append(node)
        for n in names:
            self.held[n] = self.held.get(n, 0) + 1

    def cut(self, at: int) -> None:
        """Close the tags from place `at` on."""
        while len(self.nodes) > at:
            node = self.nodes.pop()
            self.where[node.tag].pop()
            if node.tag in FENCE:
                self.fences.pop()
            for n in node.names:
                self.held[n] -= 1

    def last(self, tags) -> int:
        """The last place of any of the tags, -1 where none is open."""
        return max((self.where[t][-1] for t in tags if self.where.get(t)), default=-1)

    @property
    def fence(self) -> int:
        return self.fences[-1] if self.fences else -1


def _names(attributes: str) -> tuple[str, ...]:
    if not attributes or not attributes.strip(" /"):
        return ()
    found: list[str] = []
    for name, value in ATTRIBUTE.findall(attributes):
        if name.lower() in ("class", "id", "role", "itemprop", "aria-label"):
            found += NAMES.findall(value.strip("\"'").lower().replace("_", "-"))
        elif name.lower() in ("hidden", "aria-hidden"):
            found.append("hidden")
    return tuple(found)


def blocks_of(html: str | None, root: Node | None = None) -> list[Block]:
    """The leaf blocks with any text, in page order; root: of a tree of paths that other pages may share."""
    if not html:
        return []
    out: list[Block] = []
    stack = Stack(root or Node("", (), None))
    parts: list[str] = []
    link_chars = links = breaks = 0
    in_link = False

    def flush():
        nonlocal parts, link_chars, links, breaks
        if parts:
            text = SPACE.sub(" ", "".join(parts)).strip()
            if text:
                out.append(Block(text, stack.top, link_chars, links, breaks))
        parts, link_chars, links, breaks = [], 0, 0, 0

    def add(piece: str):
        nonlocal link_chars
        parts.append(unescape(piece) if "&" in piece else piece)
        if in_link:
            link_chars += len(piece)

    at, end = 0, len(html)
    search = TOKEN.search
    while at < end:
        m = search(html, at)
        if not m:
            add(html[at:])
            break
        if m.start() > at:
            add(html[at : m.start()])
        at = m.end()
        name = m[3]
        if name is None:
            if m[1]:
                parts.append(m[1])
            continue
        name = name.lower()
        if name in RAW:
            if not m[2] and not m[4].endswith("/"):
                close = re.compile(rf"</{re.escape(name)}\s*>", re.I).search(html, at)
                at = close.end() if close else end
            continue
        if name in INLINE:
            if name == "a":
                in_link = not m[2]
                links += in_link
            elif name in ("br", "wbr", "img"):
                parts.append(" ")
                breaks += name == "br"
            continue
        flush()
        if m[2]:
            place = stack.last((name,))
            if place >= 0 and (name != "p" or place > stack.fence):
                stack.cut(place)
            if name in FENCE:
                in_link = False
            continue
        top = stack.top.tag
        if name in CLOSES_P and top == "p":
            stack.cut(len(stack.nodes) - 1)
        if name in SAME and (place := stack.last(SAME[name])) > stack.fence:
            stack.cut(place)
        top = stack.top.tag
        if name[0] == "h" and name[1:].isdigit() and top[:1] == "h" and top[1:].isdigit():
            stack.cut(len(stack.nodes) - 1)
        if name not in VOID and not m[4].endswith("/"):
            stack.push(name, _names(m[4]))
    flush()
    return out
