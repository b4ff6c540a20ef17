"""A tolerant HTML tree and the texts made from it.

The tree is built from the event parser of the standard library with implied
end tags and raw-text states for script and style. It never raises and lives
inside one Python worker; only flat results leave it.
"""

from __future__ import annotations

import re
from collections import defaultdict
from dataclasses import dataclass, field
from html.parser import HTMLParser

VOID = frozenset("area base br col embed hr img input link meta param source track wbr".split())
BLOCK = frozenset(
    "address article aside blockquote body center code-encode dd details dialog div dl dt fieldset figcaption figure footer form "
    "h1 h2 h3 h4 h5 h6 header hr html li main nav ol option p pre section table tbody tfoot thead tr ul".split()
)
#: An opening tag of the key closes an open tag of the values, up to a stopper.
CLOSES = {
    "li": ({"li"}, {"ul", "ol"}), "option": ({"option"}, {"select"}), "tr": ({"tr", "td", "th"}, {"table"}), "td": ({"td", "th"}, {"tr", "table"}),
    "th": ({"td", "th"}, {"tr", "table"}), "dt": ({"dt", "dd"}, {"dl"}), "dd": ({"dt", "dd"}, {"dl"}),
}


@dataclass(slots=True, eq=False)
class Node:
    """An element, or a text when ``tag`` is empty."""

    tag: str
    attrs: dict[str, str] = field(default_factory=dict)
    parent: Node | None = None
    children: list[Node] = field(default_factory=list)
    data: str = ""

    def walk(self):
        """This node and all below it, in document order."""
        stack = [self]
        while stack:
            node = stack.pop()
            yield node
            stack.extend(reversed(node.children))

    def text(self) -> str:
        return "".join(n.data for n in self.walk() if not n.tag)

    def add(self, node: Node) -> Node:
        node.parent = self
        self.children.append(node)
        return node

    def remove(self) -> None:
        if self.parent is not None:
            self.parent.children = [c for c in self.parent.children if c is not self]


class _Builder(HTMLParser):
    """Builds the tree; ``at`` has the places of the open elements by tag, so that no tag is looked for in vain."""

    def __init__(self):
        super().__init__(convert_charrefs=True)
        self.root = Node("#document")
        self.open = [self.root]
        self.at: dict[str, list[int]] = defaultdict(list)

    def _last(self, tags: set[str]) -> int:
        return max((self.at[t][-1] for t in tags if self.at[t]), default=0)

    def _close_at(self, place: int) -> None:
        while len(self.open) > place:
            self.at[self.open.pop().tag].pop()

    def _close_to(self, tags: set[str], stop: set[str]) -> None:
        place = self._last(tags)
        if place and place > self._last(stop):
            self._close_at(place)

    def handle_starttag(self, tag, attrs):
        if tag in BLOCK and tag not in ("tbody", "thead", "tr"):
            self._close_to({"p"}, {"div", "td", "th", "li", "article", "section", "table", "body"})
        if tag in CLOSES:
            self._close_to(*CLOSES[tag])
        node = self.open[-1].add(Node(tag, {k: v or "" for k, v in attrs}))
        if tag not in VOID:
            self.at[tag].append(len(self.open))
            self.open.append(node)

    def handle_startendtag(self, tag, attrs):
        self.open[-1].add(Node(tag, {k: v or "" for k, v in attrs}))

    def handle_endtag(self, tag):
        if self.at[tag]:
            self._close_at(self.at[tag][-1])

    def handle_data(self, data):
        if data:
            self.open[-1].add(Node("", data=data))


def parse(html: str | None) -> Node:
    """Tree of any text; broken markup gives some tree, never an error."""
    builder = _Builder()
    try:
        builder.feed(html or "")
        builder.close()
    except (AssertionError, ValueError):  # what the event parser raises on hopeless declarations
        pass
    return builder.root


_RULE = re.compile(r"([^{}]+)\{([^{}]*)\}")
_SIMPLE = re.compile(r"([a-z][a-z0-9]*)?(?:([.#])([\w-]+))?", re.I)


def _hides(style: str) -> bool:
    style = re.sub(r"\s+", "", style).lower()
    return "display:none" in style or "visibility:hidden" in style


def hiding_selectors(root: Node) -> set[tuple[str, str, str]]:
    """``(tag, kind, name)`` of the simple selectors (``p``, ``.c``, ``#i``, ``p.c``) that ``style`` elements hide."""
    found = set()
    for node in root.walk():
        if node.tag == "style":
            for names, body in _RULE.findall(re.sub(r"/\*.*?\*/", "", node.text(), flags=re.S)):
                if _hides(body):
                    met = (_SIMPLE.fullmatch(x.strip()) for x in names.split(","))
                    found |= {((m[1] or "").lower(), m[2] or "", m[3] or "") for m in met if m and m[0]}
    return found


def _selectors(node: Node) -> set[tuple[str, str, str]]:
    named = [(".", c) for c in node.attrs.get("class", "").split()] + [("#", i) for i in node.attrs.get("id", "").split()]
    return {(node.tag, "", "")} | {(tag, kind, name) for tag in ("", node.tag) for kind, name in named}


def strip_hidden(root: Node, style_rules: bool = False) -> int:
    """Drop elements hidden by attribute or inline style; returns their characters.

    With ``style_rules`` also those that the page's own ``style`` elements hide by a simple selector.
    """
    gone, rules = 0, hiding_selectors(root) if style_rules else set()
    stack = [root]
    while stack:
        node = stack.pop()
        seen = []
        for child in node.children:
            hidden = child.attrs.get("aria-hidden", "").lower() == "true" or _hides(child.attrs.get("style", ""))
            if hidden or rules and child.tag and not rules.isdisjoint(_selectors(child)):
                gone += len(child.text())
                child.parent = None
            else:
                seen.append(child)
        node.children = seen
        stack.extend(seen)
    return gone


def linearize(root: Node, keep_title: bool = False) -> str:
    """Everything visible as text: blocks on lines, table cells apart by tabs, protected elements as they are."""
    out: list[str] = []
    stack: list[tuple[Node | str, bool]] = [(root, False)]  # a text on the stack is what follows an element
    while stack:
        node, pre = stack.pop()
        if isinstance(node, str):
            out.append(node)
        elif not node.tag:
            out.append(node.data.replace("\n", "\0") if pre else re.sub(r"[ \t\r\n\f]+", " ", node.data))
        elif node.tag in ("script", "style", "noscript", "template") or node.tag == "head" and not keep_title:
            continue
        elif node.tag == "br":
            out.append("\n")
        else:
            edge, code = "\n" * (node.tag in BLOCK), node.tag == "code-encode"
            out.append(edge + "\t" * (node.tag in ("td", "th")) + "<code-encode>" * code)
            stack.append(("</code-encode>" * code + edge, pre))
            inner = pre or node.tag in ("pre", "code-encode", "textarea")
            stack.extend((child, inner) for child in reversed(node.children))
    # Line feeds of preformatted text are hidden while the other lines are trimmed.
    lines = (line.strip(" \t") for line in "".join(out).split("\n"))
    return "\n".join(line for line in lines if line.strip(" \t\0")).replace("\0", "\n")


_SKIP = frozenset("nav header footer aside form script style noscript template button select".split())
_SKIP_NAME = re.compile(r"(^|[-_ ])(ads?|advert|banner|menu|sidebar|cookie|breadcrumb|share|social)([-_ ]|$)", re.I)


def main_content(html: str | None, *, min_block_chars: int = 25, max_link_density: float = 0.5, favor: str = "precision") -> str:
    """Body text of a page: dense, link-poor blocks of its article or best subtree."""
    root = parse(html)
    nodes = [root]
    for node in nodes:  # grows by what stays, parents first
        node.children = [c for c in node.children if not (c.tag in _SKIP or c.tag == "head" or _SKIP_NAME.search(c.attrs.get("class", "") + " " + c.attrs.get("id", "")))]
        nodes += node.children
    size: dict[int, int] = {}
    for node in reversed(nodes):
        size[id(node)] = len(node.data) * (not node.tag) + sum(size[id(c)] for c in node.children)
    whole = max(1, size[id(root)])
    best = next((n for n in root.walk() if n.tag in ("article", "main") and size[id(n)] >= 0.3 * whole), root)
    kept: list[str] = []
    heading = ""
    for line, linked, head in _blocks(best):
        if head:
            heading = line
            continue
        dense = linked / max(1, len(line))
        if dense < max_link_density and (len(line) >= min_block_chars or line[-1:] in ".!?"):
            kept += [heading] * bool(heading) + [line]
        heading = ""
    return "\n".join(kept) or (linearize(root) if favor == "recall" else "")


def _blocks(root: Node):
    """Lines of text with the characters under links and whether they are headings."""
    state = {"text": [], "linked": 0, "head": False}

    def flush():
        line = re.sub(r"\s+", " ", "".join(state["text"])).strip()
        got = (line, state["linked"], state["head"])
        state.update(text=[], linked=0)
        return [got] if line else []

    stack: list[tuple[Node, bool, bool]] = [(root, False, False)]  # node, under a link, its end
    while stack:
        node, link, end = stack.pop()
        if not node.tag:
            state["text"].append(node.data)
            state["linked"] += len(node.data) * link
            continue
        edge = node.tag in BLOCK or node.tag == "br"
        if edge:
            yield from flush()
            state["head"] = not end and (node.tag in ("h1", "h2", "h3", "h4", "h5", "h6") or state["head"] and node.tag == "br")
        if not end:
            stack += [(node, link, True)] * edge
            stack.extend((child, link or node.tag == "a", False) for child in reversed(node.children))
    yield from flush()


def title(root: Node) -> str:
    node = next((n for n in root.walk() if n.tag == "title"), None)
    return re.sub(r"\s+", " ", node.text()).strip() if node else ""


def links(root: Node) -> list[str]:
    return [n.attrs["href"] for n in root.walk() if n.tag == "a" and "href" in n.attrs]
