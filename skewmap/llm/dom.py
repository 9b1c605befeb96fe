"""A small tolerant HTML reader: tags to a tree of elements and text, as flat lists."""

from __future__ import annotations

import html
import re

TOKEN = re.compile(
    r"<!--.*?(?:-->|\Z)|<!\[CDATA\[(?P<cdata>.*?)(?:\]\]>|\Z)|<[!?][^>]*>?|<(?P<close>/)?(?P<name>[A-Za-z][^\s/>\x00]*)(?P<attrs>(?:[^>\"']|\"[^\"]*\"|'[^']*')*)>",
    re.S,
)
ATTRIBUTE = re.compile(r"([^\s=\"'/<>]+)\s*=\s*(?:\"([^\"]*)\"|'([^']*)'|([^\s>]+))|([^\s=\"'/<>]+)")
#: Fixed values of the HTML standard: elements without content, with raw text, and block-level elements.
VOID = frozenset("area base br col embed hr img input link meta param source track wbr".split())
RAW = frozenset("script style textarea title noscript iframe noembed noframes xmp template".split())
BLOCK = frozenset(
    "address article aside blockquote body caption center dd details dialog dir div dl dt fieldset figcaption figure footer form frameset h1 h2 h3 h4 h5 h6 head header hgroup hr html legend li main menu nav ol option p pre section select summary table tbody td tfoot th thead tr ul".split()
)
#: A start tag of the first kind ends an open element of the second kind, up to the nearest of the third.
ENDS = {
    "li": (("li",), ("ul", "ol", "menu")),
    "dt": (("dt", "dd"), ("dl",)),
    "dd": (("dt", "dd"), ("dl",)),
    "tr": (("tr", "td", "th"), ("table",)),
    "td": (("td", "th"), ("tr", "table")),
    "th": (("td", "th"), ("tr", "table")),
    "option": (("option",), ("select",)),
    "body": (("head",), ("html",)),
}
INLINE_OPEN = frozenset("a abbr b bdi bdo big cite code data em font i kbd mark q s samp small span strike strong sub sup time tt u var".split())


class Tree:
    """Elements in page order: parent, tag, class-and-id words; and text runs (element, text, starts a new block)."""

    def __init__(self) -> None:
        self.parent: list[int] = [-1]
        self.tag: list[str] = ["#root"]
        self.hint: list[str] = [""]
        self.runs: list[tuple[int, str, bool]] = []


def parse(page: str) -> Tree:
    """Tree of a page; whatever is not closed ends with the page, and stray end tags are passed over."""
    tree = Tree()
    stack = [0]
    fresh, end = True, 0
    parent, tag, hint, runs = tree.parent, tree.tag, tree.hint, tree.runs

    def text(s: str) -> None:
        nonlocal fresh
        if s:
            runs.append((stack[-1], s, fresh))
            fresh = False

    at = 0
    while m := TOKEN.search(page, at):
        if m.start() > at:
            text(html.unescape(page[at : m.start()]))
        at = m.end()
        name = m["name"]
        if name is None:
            if m["cdata"]:
                text(m["cdata"])
            continue
        name = name.lower()
        if m["close"]:
            for depth in range(len(stack) - 1, 0, -1):
                if tag[stack[depth]] == name:
                    del stack[depth:]
                    break
                if name in INLINE_OPEN and tag[stack[depth]] in BLOCK:
                    break
            fresh = fresh or name in BLOCK
            continue
        if name in BLOCK:
            fresh = True
            for depth in range(len(stack) - 1, 0, -1):  # a block ends an open paragraph, with what is open in it
                t = tag[stack[depth]]
                if t == "p":
                    del stack[depth:]
                    break
                if t in BLOCK:
                    break
        if name in ENDS:
            ended, within = ENDS[name]
            for depth in range(len(stack) - 1, 0, -1):
                t = tag[stack[depth]]
                if t in within:
                    break
                if t in ended:
                    del stack[depth:]
                    if name != "tr" or t == "tr":
                        break
        if name == "br":
            text(" ")
            continue
        attrs = m["attrs"]
        parent.append(stack[-1])
        tag.append(name)
        words = ""
        if attrs and ("=" in attrs or "hidden" in attrs):
            for k, a, b, c, bare in ATTRIBUTE.findall(attrs):
                k = (k or bare).lower()
                if k in ("class", "id", "role", "itemprop", "aria-label"):
                    words += f" {(a or b or c).lower()}"
                elif k == "hidden" or k == "aria-hidden" and (a or b or c) == "true" or k == "style" and "display:none" in (a or b or c).replace(" ", "").lower():
                    words += " hidden"
        hint.append(words)
        if name in VOID or attrs.rstrip().endswith("/") and name not in BLOCK and name not in RAW and name not in INLINE_OPEN:
            continue
        if name in RAW:
            close = re.compile(rf"</{re.escape(name)}\s*>", re.I).search(page, at)
            at = close.end() if close else len(page)
            continue
        stack.append(len(parent) - 1)
    text(html.unescape(page[at:].split("<", 1)[0] if re.match(r"<[A-Za-z/!]", page[at : at + 2] or " ") else page[at:]))
    return tree
