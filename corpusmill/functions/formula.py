"""Formulas in a page: where they are, whether they parse, one form of each."""

from __future__ import annotations

import re
import xml.etree.ElementTree as ET

from .html import Node, linearize, parse, strip_hidden

# Arity of common macros, and environments with alignment marks.
ARITY = {"frac": 2, "dfrac": 2, "tfrac": 2, "binom": 2, "sqrt": 1, "text": 1, "mathrm": 1, "mathbf": 1, "mathbb": 1, "mathcal": 1, "hat": 1, "bar": 1, "vec": 1, "overline": 1, "underline": 1, "tilde": 1, "dot": 1, "operatorname": 1, "overset": 2, "underset": 2, "stackrel": 2}
ALIGNED = frozenset("array matrix pmatrix bmatrix vmatrix cases align align* aligned split gather tabular".split())
_TOKEN = re.compile(r"\\[A-Za-z]+\*?|\\.|%[^\n]*|\$\$|[{}\[\]$&^_]|[^\\%${}\[\]&^_]+", re.S)


def check_latex(source: str | None) -> tuple[bool, str]:
    """Whether a formula parses, and the first reason why not."""
    if not source or not source.strip():
        return False, "empty"
    if re.search(r"\\$", source):
        return False, "dangling backslash"
    tokens = [t for t in _TOKEN.findall(source) if not t.startswith("%")]
    stack: list[str] = []
    k = 0
    while k < len(tokens):
        t = tokens[k]
        if t in ("\\begin", "\\end"):
            name = tokens[k + 2].strip() if k + 3 < len(tokens) and tokens[k + 1] == "{" and tokens[k + 3] == "}" else None
            if name is None:
                return False, "environment without name"
            if t == "\\begin":
                stack.append("env:" + name)
            elif not stack or stack.pop() != "env:" + name:
                return False, "environment mismatch"
            k += 4
            continue
        if t == "{":
            stack.append("{")
        elif t == "}":
            if not stack or stack.pop() != "{":
                return False, "unbalanced brace"
        elif t == "\\left":
            stack.append("left")
        elif t == "\\right":
            if not stack or stack.pop() != "left":
                return False, "left and right"
        elif t == "&" and not any(s.startswith("env:") and s[4:] in ALIGNED for s in stack):
            return False, "stray alignment"
        elif t in ("^", "_"):
            rest = [x for x in tokens[k + 1 : k + 3] if x.strip()]
            if not rest or rest[0] in ("^", "_", "}", "&"):
                return False, "script without base"
        elif t[0] == "\\" and t[1:] in ARITY:
            at, need = k + 1, ARITY[t[1:]]
            if t == "\\sqrt" and at < len(tokens) and tokens[at] == "[":
                at = next((i + 1 for i in range(at, len(tokens)) if tokens[i] == "]"), len(tokens))
            for _ in range(need):
                while at < len(tokens) and not tokens[at].strip():
                    at += 1
                if at >= len(tokens) or tokens[at] == "}":
                    return False, "missing argument"
                if tokens[at] == "{":
                    depth = 0
                    while at < len(tokens):
                        depth += (tokens[at] == "{") - (tokens[at] == "}")
                        at += 1
                        if not depth:
                            break
                elif tokens[at][0] != "\\" and len(tokens[at].strip()) > 1:
                    tokens[at] = tokens[at].strip()[1:]  # one character is an argument of its own
                else:
                    at += 1
        k += 1
    return (False, "unclosed " + stack[-1].split(":")[0]) if stack else (True, "")


def check_mathml(source: str) -> tuple[bool, str]:
    try:
        ET.fromstring(source)
    except ET.ParseError:
        return False, "not well-formed"
    return True, ""


def _xml(node: Node) -> str:
    if not node.tag:
        return node.data.replace("&", "&amp;").replace("<", "&lt;")
    return f"<{node.tag}>" + "".join(map(_xml, node.children)) + f"</{node.tag}>"


def formulas_of(root: Node) -> list[tuple[Node, str, str, bool]]:
    """``(node, dialect, source, display)`` of each formula once: an annotation stands for its MathML, a script for its picture."""
    found, inside = [], set()
    for node in root.walk():
        if id(node) in inside:
            continue
        kind = node.attrs.get("type", "").lower().replace(" ", "")
        if node.tag == "math":
            inside |= {id(x) for x in node.walk()}
            note = next((x for x in node.walk() if x.tag == "annotation" and "x-tex" in x.attrs.get("encoding", "")), None)
            display = node.attrs.get("display") == "block"
            found.append((node, "latex", note.text().strip(), display) if note else (node, "mathml", _xml(node), display))
        elif node.tag == "script" and kind.startswith(("math/tex", "math/latex")):
            found.append((node, "latex", node.text().strip(), "mode=display" in kind))
        elif node.tag == "script" and kind.startswith("math/asciimath"):
            found.append((node, "asciimath", node.text().strip(), False))
        elif node.tag == "script" and kind.startswith("math/mml"):
            found.append((node, "mathml", node.text().strip(), False))
        elif node.tag == "span" and "math-formula" in node.attrs.get("class", "").split():
            inside |= {id(x) for x in node.walk()}
            found.append((node, "latex", node.text().strip(), False))
        elif node.tag == "annotation" and "x-tex" in node.attrs.get("encoding", ""):
            found.append((node, "latex", node.text().strip(), False))
    return found


def math_page(html: str | None, on_error: str = "drop_page") -> dict:
    """The whole markup-math pass over a page."""
    root = parse(html)
    strip_hidden(root)
    rows, bad = [], 0
    for node, dialect, source, display in formulas_of(root):
        ok, reason = check_latex(source) if dialect == "latex" else check_mathml(source) if dialect == "mathml" else (bool(source), "")
        bad += not ok
        rows.append((dialect, source, display, ok, reason))
        same = re.sub(r"\s+", "", source)
        for sibling in list(node.parent.children) if node.parent else []:
            if sibling.tag == "img" and re.sub(r"\s+", "", sibling.attrs.get("alt", "")) == same:
                sibling.remove()
        if ok:
            inner = re.sub(r"<[^>]+>", " ", source) if dialect == "mathml" else source
            node.tag, node.attrs, node.children = "span", {}, []
            node.add(Node("", data=f"\\[{inner}\\]" if display else f"\\({inner}\\)"))
        else:
            node.remove()
    keep = bool(rows) and (not bad if on_error == "drop_page" else bad < len(rows))
    return {"formulas": rows, "valid": len(rows) - bad, "keep": keep, "text": linearize(root)}
