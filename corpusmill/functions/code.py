"""Code snippets in a page: roots, tests, line numbers, language tags."""

from __future__ import annotations

import math
import re

from .html import Node, linearize, parse, strip_hidden

# Fixed values of our own: four families of signs of code. Each is a plain regular expression that Java and RE2 read alike.
FAMILIES = {
    "keyword": r"(^|[\n;{}]|\s)(def|class|import|function|return|public|private|static|void|const|let|var|elif|struct|typedef|#include|SELECT)\s+[A-Za-z_<(*]",
    "indicator": r"(;\s*(\n|$)|\{\s*(\n|$)|=>|::|->|//|/\*|#!|</|&&|\|\||!=|==)",
    "call": r"[A-Za-z_][A-Za-z0-9_.]*\([^()\n]*\)",
    "assignment": r"(^|[\n;{(]|\s)[A-Za-z_][A-Za-z0-9_.\[\]]*\s*(=|:=|\+=|-=|\*=)\s*[A-Za-z0-9_\"'(\[{-]",
}
_COMPILED = {k: re.compile(v) for k, v in FAMILIES.items()}
# Fixed values of our own: marks that vote for a language.
MARKS = {
    "python": (r"\bdef \w+\(", r"\bimport \w+", r"\belif\b", r":\s*\n\s+", r"\bself\b", r"\bprint\("),
    "javascript": (r"\bfunction\b", r"\b(const|let|var) ", r"=>", r"===", r"console\.log"),
    "java": (r"\bpublic (static )?", r"\bprivate ", r"System\.out", r"\bnew \w+\("),
    "c": (r"#include", r"\bint main\b", r"\bprintf\(", r"\bstruct \w+", r"->"),
    "cpp": (r"std::", r"\btemplate\s*<", r"\bcout\b", r"::"),
    "go": (r"\bfunc \w+\(", r":=", r"\bpackage \w+", r"fmt\."),
    "rust": (r"\bfn \w+", r"\blet mut\b", r"println!", r"::<"),
    "sql": (r"(?i)\bselect\b.+\bfrom\b", r"(?i)\binsert into\b", r"(?i)\bgroup by\b"),
    "html": (r"</\w+>", r"<div", r"<!DOCTYPE"),
    "shell": (r"^#!", r"\becho ", r"\$\{?\w+", r"\bsudo "),
}


def looks_like_code(text: str) -> dict[str, bool]:
    return {k: bool(p.search(text)) for k, p in _COMPILED.items()}


def code_roots(root: Node) -> list[Node]:
    """Roots of snippets in document order: the parent of a ``code`` when it is ``pre`` or ``tbody``, else the element itself."""
    found: dict[int, Node] = {}
    for node in root.walk():
        if node.tag == "code":
            top = node.parent if node.parent is not None and node.parent.tag in ("pre", "tbody") else node
            found.setdefault(id(top), top)
    return list(found.values())


def strip_line_numbers(snippet: str, least: int = 3) -> str:
    """Drop number-only lines that count up by one on consecutive or alternating lines, in runs of ``least`` or more."""
    lines = snippet.split("\n")
    number = {i: int(x) for i, x in enumerate(lines) if re.fullmatch(r"\s*[0-9]{1,9}\s*", x)}
    gone: set[int] = set()
    for gap in (1, 2):
        for i in number:
            if number.get(i - gap) == number[i] - 1:
                continue
            run = [i]
            while number.get(run[-1] + gap) == number[run[-1]] + 1:
                run.append(run[-1] + gap)
            if len(run) >= least:
                gone |= set(run)
    return "\n".join(x for i, x in enumerate(lines) if i not in gone)


def merge_adjacent(text: str) -> str:
    """Join snippets with nothing but white space between them."""
    return re.sub(r"</code-encode>(\s*)<code-encode>", lambda m: "\n" if "\n" in m[1] or not m[1] else m[1], text)


def code_language(snippet: str) -> tuple[str, float]:
    """Language with the most marks and its softmax share."""
    votes = {k: sum(bool(re.search(p, snippet, re.M)) for p in marks) for k, marks in MARKS.items()}
    best = max(votes, key=lambda k: (votes[k], k))
    if not votes[best]:
        return "unknown", 0.0
    return best, round(math.exp(votes[best]) / sum(math.exp(v) for v in votes.values()), 2)


def code_page(html: str | None) -> dict:
    """The whole code pass over a page: hide, find, test, retag, number, merge, linearise."""
    root = parse(html)
    hidden = strip_hidden(root)
    roots = code_roots(root)
    kinds = [r.tag for r in roots]
    for top in roots:
        text = top.text()
        if not any(looks_like_code(text).values()):
            continue
        clean = strip_line_numbers("\n".join(c.text() for c in top.children if c.tag == "code") if top.tag == "tbody" else text)
        if top.tag == "code" and top.parent is not None and any(p is not top and p.tag == "code-encode" for p in _above(top)):
            continue
        top.tag, top.attrs, top.children = "code-encode", {}, []
        top.add(Node("", data=clean.strip("\n")))
    text = merge_adjacent(linearize(root))
    snippets = re.findall(r"<code-encode>(.*?)</code-encode>", text, re.S)
    return {"hidden_chars": hidden, "roots": len(roots), "pre_roots": kinds.count("pre"), "tbody_roots": kinds.count("tbody"), "snippets": snippets, "text": text}


def _above(node: Node):
    while node.parent is not None:
        node = node.parent
        yield node
