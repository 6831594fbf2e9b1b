"""A forgiving HTML reader: block elements and the text runs inside them, as a tree in page order."""

from __future__ import annotations

import re
from collections.abc import Iterator
from dataclasses import dataclass, field
from html import unescape

# Element names of the HTML standard.
VOID = frozenset("area base br col embed hr img input link meta param source track wbr".split())
BLOCK = frozenset(
    "address article aside blockquote body button caption center dd details dialog dir div dl dt fieldset figcaption figure footer form "
    "h1 h2 h3 h4 h5 h6 header hgroup html label legend li main menu nav ol option p pre search section select summary table tbody td tfoot th thead tr ul".split()
)
RAW = frozenset("script style textarea title xmp".split())
DROPPED = frozenset("noscript template svg math iframe object canvas audio video datalist".split())
CLOSES_P = BLOCK - frozenset("body button caption dd dt html label legend li option select tbody td tfoot th thead tr".split()) | {"hr"}
# what a start tag closes, and the elements beyond which it doesn't look
IMPLIED = {
    "li": (("li",), ("ul", "ol", "menu")),
    "dt": (("dt", "dd"), ("dl",)),
    "dd": (("dt", "dd"), ("dl",)),
    "option": (("option",), ("select",)),
    "tr": (("tr",), ("table",)),
    "td": (("td", "th"), ("table",)),
    "th": (("td", "th"), ("table",)),
    "tbody": (("tbody", "thead", "tfoot"), ("table",)),
    "tfoot": (("tbody", "thead", "tfoot"), ("table",)),
}
_NAME = re.compile(r"(/?)([a-zA-Z][^\s/>]*)")
_REST = re.compile(r"""(?:"[^"]*"|'[^']*'|[^'">]+)*+>""")
MAX_DEPTH = 512  # deeper blocks become siblings, as in browsers
_ATTR = re.compile(r"""([^\s=/"']+)(?:\s*=\s*(?:"([^"]*)"|'([^']*)'|([^\s"'>]+)))?""")


@dataclass(slots=True)
class Node:
    tag: str  # of an element; "#text" for a run
    parent: int
    attrs: dict[str, str] = field(default_factory=dict)
    text: str = ""
    chars: int = 0  # of the run, or of all runs below
    linked: int = 0  # of these inside links


def _attributes(raw: str) -> dict[str, str]:
    out: dict[str, str] = {}
    for m in _ATTR.finditer(raw) if raw.strip(" /") else ():
        out.setdefault(m[1].lower(), unescape(m[2] or m[3] or m[4] or ""))
    return out


def _tags(html: str) -> Iterator[tuple[int, int, str, str, str]]:
    """(start, end, slash, name, rest) of each tag, comment and declaration, the last two without a name; the caller may send where to read on.

    Every part of a page is looked at a bounded number of times, whatever is left open in it: behind the last ``>`` no tag ends, and once
    a quote inside a tag has no end, this and all later tags end at their first ``>``.
    """
    last, quotes, at = html.rfind(">"), True, html.find("<")
    while at >= 0:
        after = at + 1
        if html.startswith("!--", after):
            stop = html.find("-->", at + 4)
            after = len(html) if stop < 0 else stop + 3
            yield at, after, "", "", ""
        elif html.startswith(("!", "?"), after):
            stop = html.find(">", after)
            after = len(html) if stop < 0 else stop + 1
            yield at, after, "", "", ""
        elif at > last:
            return
        elif m := _NAME.match(html, after):
            rest = _REST.match(html, m.end()) if quotes else None
            if rest:
                after = rest.end()
            else:
                quotes, after = False, html.find(">", m.end()) + 1
            after = (yield at, after, m[1], m[2].lower(), html[m.end() : after - 1]) or after
        at = html.find("<", after)


def parse(html: str) -> list[Node]:
    """Nodes in page order, each after its parent; the first is the root. White space in a run is one space; no run is empty."""
    nodes = [Node("#root", -1)]
    depth = [0]
    stack: list[tuple[str, int]] = [("#root", 0)]  # open elements; the node of the block they are in
    places: dict[str, list[int]] = {}  # of each element's open ones in the stack
    run: list[str] = []
    link = 0
    links = dropped = 0

    def block(tag: str, raw: str) -> None:
        parent = stack[-1][1]
        if depth[parent] >= MAX_DEPTH:
            parent = nodes[parent].parent
        nodes.append(Node(tag, parent, _attributes(raw)))
        depth.append(depth[parent] + 1)

    def push(tag: str, node: int) -> None:
        places.setdefault(tag, []).append(len(stack))
        stack.append((tag, node))

    def flush() -> None:
        nonlocal link
        if run:
            text = " ".join("".join(run).split())
            if text:
                nodes.append(Node("#text", stack[-1][1], text=text, chars=len(text), linked=min(link, len(text))))
                depth.append(depth[stack[-1][1]] + 1)
            run.clear()
            link = 0

    def say(raw: str) -> None:
        nonlocal link
        if raw and not dropped:
            text = unescape(raw) if "&" in raw else raw
            run.append(text)
            if links:
                link += len(text.strip())

    def pop() -> None:
        nonlocal links, dropped
        tag = stack[-1][0]
        if tag in BLOCK:
            flush()
        stack.pop()
        places[tag].pop()
        links -= tag == "a"
        dropped -= tag in DROPPED

    def close(tags: tuple[str, ...], within: tuple[str, ...]) -> None:
        top = lambda names: max((places[t][-1] for t in names if places.get(t)), default=0)
        if (k := top(tags)) > top(within):
            while len(stack) > k:
                pop()

    at, tags, skip = 0, _tags(html), None
    while True:
        try:
            start, after, end, tag, raw = tags.send(skip)
        except StopIteration:
            break
        say(html[at:start])
        at, skip = after, None
        if not tag:
            continue
        if end:
            if tag == "br":
                say(" ")
            elif places.get(tag) and tag not in ("html", "body"):
                close((tag,), () if tag in BLOCK else ("td", "th", "li", "article", "section", "main", "body"))
            continue
        if tag in RAW:
            stop = re.compile(rf"</{re.escape(tag)}(?=[\s/>])[^>]*>?", re.I).search(html, at)
            at = skip = stop.end() if stop else len(html)
            continue
        if tag in CLOSES_P:
            close(("p",), ("td", "th", "button", "table"))
        if tag in IMPLIED:
            close(*IMPLIED[tag])
        if tag in VOID:
            if tag == "hr":
                flush()
            elif tag == "br":
                say(" ")
            continue
        if raw.endswith("/") and tag not in BLOCK:
            continue
        if tag in ("html", "body", "head"):
            if tag != "head" and not places.get(tag) and len(stack) == 1 + bool(places.get("html")):
                block(tag, raw)
                push(tag, len(nodes) - 1)
            continue
        if tag in BLOCK:
            flush()
            block(tag, raw)
            push(tag, len(nodes) - 1)
        else:
            push(tag, stack[-1][1])
            links += tag == "a"
            dropped += tag in DROPPED
    say(html[at:])
    flush()
    for n in reversed(nodes):
        if n.parent >= 0:
            nodes[n.parent].chars += n.chars
            nodes[n.parent].linked += n.linked
    return nodes
