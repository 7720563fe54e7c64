"""A forgiving HTML reader: block tree, text runs in page order and per-block statistics.

Inline markup is transparent, so a block's text is what stands between block boundaries.  Scripts, styles,
titles and other raw-text elements, comments and declarations give no text.  Every element costs a
constant amount of work apart from the depth of what it closes.
"""

from __future__ import annotations

import re
from collections import Counter
from zlib import crc32

_TOKEN = re.compile(
    r"<!--.*?(?:-->|\Z)|<[!?][^>]*(?:>|\Z)|</([a-zA-Z][^\s/>]*)[^>]*(?:>|\Z)|<([a-zA-Z][^\s/>]*)((?:[^>\"']++|\"[^\"]*+\"|'[^']*+')*+)>|<([a-zA-Z][^\s/>]*)([^>]*)(?:>|\Z)",
    re.S,
)
_ATTR = re.compile(r"\b(?:class|id|role)\s*=\s*(?:\"([^\"]*)\"|'([^']*)'|([^\s>]+))", re.I)

RAW = frozenset("script style title textarea noscript iframe noembed noframes xmp template svg math".split())
VOID = frozenset("area base br col embed hr img input link meta param source track wbr".split())
INLINE = frozenset("a abbr acronym b bdi bdo big cite code data del dfn em font i ins kbd mark q s samp small span strike strong sub sup time tt u var ruby rt rp nobr picture html head".split())
#: Elements that a start tag of the key closes, up to the nearest barrier.
CLOSES = {
    "li": (frozenset(["li"]), frozenset("ul ol menu table".split())),
    "dt": (frozenset("dt dd".split()), frozenset(["dl"])),
    "dd": (frozenset("dt dd".split()), frozenset(["dl"])),
    "tr": (frozenset(["tr"]), frozenset(["table"])),
    "td": (frozenset("td th".split()), frozenset("tr table".split())),
    "th": (frozenset("td th".split()), frozenset("tr table".split())),
    "option": (frozenset(["option"]), frozenset(["select"])),
}

TAGS = "article main nav header footer aside form p heading list item table cell div section quote figure details field body other".split()
_GROUP = {t: t for t in "article main nav header footer aside form p div section body".split()}
_GROUP |= {f"h{k}": "heading" for k in range(1, 7)} | dict.fromkeys("ul ol menu dl".split(), "list") | dict.fromkeys("li dt dd".split(), "item")
_GROUP |= dict.fromkeys("table tbody thead tfoot tr".split(), "table") | dict.fromkeys("td th caption".split(), "cell") | dict.fromkeys("blockquote pre address".split(), "quote")
_GROUP |= dict.fromkeys("figure figcaption".split(), "figure") | dict.fromkeys("details summary dialog".split(), "details") | dict.fromkeys("button label select option fieldset legend optgroup datalist output".split(), "field")

#: Buckets that words of class, id and role names and their four-letter pieces are hashed into.
NAME_BUCKETS = 2048
_WORD = re.compile(r"[^\W\d_]+")
_HUMP = re.compile(r"(?<=[a-z])(?=[A-Z])")


def name_features(names: str) -> frozenset[int]:
    """Buckets of the words in some names, camel case split, and of the words' four-letter pieces."""
    out = set()
    for word in _WORD.findall(_HUMP.sub(" ", names)):
        w = f"^{word.lower()}$"
        out.add(crc32(w.encode()) % NAME_BUCKETS)
        out.update(crc32(w[k : k + 4].encode()) % NAME_BUCKETS for k in range(len(w) - 3))
    return frozenset(out)


class Kinds:
    """Interned element kinds: tag group and name features of class, id and role."""

    def __init__(self):
        self.of: dict[tuple[str, str], int] = {}
        self.rows: list[tuple[int, frozenset[int]]] = []
        self._ids: dict[tuple[int, frozenset[int]], int] = {}

    def get(self, tag: str, attrs: str) -> int:
        key = (tag, attrs)
        k = self.of.get(key)
        if k is None:
            names = " ".join(a or b or c for a, b, c in _ATTR.findall(attrs)) if attrs else ""
            row = (TAGS.index(_GROUP.get(tag, "other")), name_features(names))
            if row not in self._ids:
                self._ids[row] = len(self.rows)
                self.rows.append(row)
            k = self._ids[row]
            if len(self.of) < 100_000:
                self.of[key] = k
        return k


class Page:
    """Block nodes in page order (0 is the page itself) and text runs ``(node, raw text pieces)``."""

    __slots__ = ("parent", "depth", "kind", "chars", "linked", "runs", "marks")

    def __init__(self):
        self.parent, self.depth, self.kind, self.chars, self.linked = [], [], [], [], []
        self.runs: list[tuple[int, list[str]]] = []
        self.marks: list[str] = []


def read(html: str, kinds: Kinds, mark: str | None = None) -> Page:
    """Parse a whole page. ``mark``: attribute whose value labels a training node (inherited by what it encloses)."""
    page = Page()
    parent, depth, kind, chars, linked = page.parent, page.depth, page.kind, page.chars, page.linked
    stack: list[tuple[str, int]] = []
    opened: Counter[str] = Counter()
    label: list[str] = page.marks

    def push(tag: str, attrs: str) -> None:
        node = len(parent)
        up = stack[-1][1] if stack else -1
        parent.append(up)
        depth.append(len(stack))
        if mark is not None:
            m = re.search(rf'{mark}="([^"]*)"', attrs)
            label.append(m[1] if m else (label[up] if up >= 0 else ""))
            attrs = re.sub(rf'\s*{mark}="[^"]*"', "", attrs)
        kind.append(kinds.get(tag, attrs))
        chars.append(0)
        linked.append(0)
        stack.append((tag, node))
        opened[tag] += 1

    def pop_to(tag: str) -> None:
        while True:
            t, _ = stack.pop()
            opened[t] -= 1
            if t == tag:
                return

    push("body", "")
    pieces: list[str] = []
    links = 0
    pos, size = 0, len(html)

    def cut() -> None:
        nonlocal pieces
        if pieces:
            page.runs.append((stack[-1][1], pieces))
            pieces = []

    def add(text: str) -> None:
        pieces.append(text)
        n = len(text.strip())
        if n:
            chars[stack[-1][1]] += n
            if links > 0:
                linked[stack[-1][1]] += n

    while pos < size:
        m = _TOKEN.search(html, pos)
        if m is None:
            add(html[pos:])
            break
        if m.start() > pos:
            add(html[pos : m.start()])
        pos = m.end()
        end, start = m[1], m[2] or m[4]
        if start:
            tag, attrs = start.lower(), m[3] or m[5] or ""
            if tag in INLINE:
                if tag == "a" and not attrs.endswith("/"):
                    links += 1
            elif tag in RAW:
                if not attrs.endswith("/"):
                    close = re.compile(rf"</{tag}(?=[\s/>])[^>]*>?", re.I).search(html, pos)
                    pos = close.end() if close else size
            elif tag in VOID:
                if tag == "br":
                    pieces.append(" ")
                elif tag == "hr":
                    cut()
            elif tag == "body":
                cut()
                kind[0] = kinds.get("body", re.sub(rf'\s*{mark}="[^"]*"', "", attrs) if mark else attrs)
            else:
                cut()
                links = 0
                if opened["p"] and tag not in ("button", "label", "select", "option"):
                    pop_to("p")
                if tag in CLOSES:
                    same, wall = CLOSES[tag]
                    if any(opened[t] for t in same):
                        for t, _ in reversed(stack):
                            if t in same:
                                pop_to(t)
                                break
                            if t in wall:
                                break
                push(tag, attrs)
        elif end:
            tag = end.lower()
            if tag == "a":
                links = max(0, links - 1)
            elif tag in INLINE or tag in RAW or tag == "body":
                pass
            elif tag == "br":
                pieces.append(" ")
            elif tag in VOID:
                pass
            elif opened[tag]:
                cut()
                links = 0
                pop_to(tag)
            elif tag == "p":
                cut()
    cut()
    return page
