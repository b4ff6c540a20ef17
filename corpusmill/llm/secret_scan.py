"""Secret scans with multipart credential linking.

Three base kinds are found by pattern: assignments, access identifiers and
long hex runs. Weak parts, which alone are no finding, are looked for too:
mixed secret-like strings and service endpoints. An interval join then links
parts: every access identifier opens a scope of characters around it, and a
weak secret counts only in a scope, an endpoint only in a scope that holds a
secret as well. Scopes and parts are both sorted, so the join of a document is
a binary search per scope and never a list of all pairs.

Edge cases: null counts as empty; positions are code points, ends exclusive;
touching or equal spans of different kinds are all kept; repeated rows are
scanned each; other columns are ignored by ``scan`` and kept by ``redact``.
"""

from __future__ import annotations

import hashlib
import itertools
import re
from bisect import bisect_left
from collections.abc import Iterator

import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ._spark import lean, map_frames

KINDS = ("assign", "access", "hex", "secret", "endpoint")
SCOPE = 400
_ASSIGN = re.compile(r"""(password|passwd|secret|token|api_?key)["']?\x20*[:=]\x20*["']?([A-Za-z0-9+/_.=-]+)""", re.I | re.A)
_ACCESS = re.compile(r"AKIA[A-Z0-9]{16,}")
_HEX = re.compile(r"[0-9a-f]{24,}")
_WEAK = re.compile(r"[A-Za-z0-9+/_=-]{30,}")
_ENDPOINT = re.compile(r"https?://[A-Za-z0-9.-]+\.[A-Za-z]{2,}[A-Za-z0-9./_-]*")


def base_spans(text: str) -> list[tuple[int, int, int]]:
    """``(start, kind, end)`` of the base kinds, by start then kind."""
    found = []
    if "=" in text or ":" in text:
        found += [(m.start(), 0, m.end()) for m in _ASSIGN.finditer(text) if len(m[2]) >= 6]
    if "AKIA" in text:
        found += [(m.start(), 1, m.end()) for m in _ACCESS.finditer(text)]
    found += [(m.start(), 2, m.end()) for m in _HEX.finditer(text)]
    return sorted(found)


def _mixed(s: str) -> bool:
    return any(c.isdigit() for c in s) and any(c.isupper() for c in s) and any(c.islower() for c in s)


def linked_spans(text: str, base: list[tuple[int, int, int]], scope: int = SCOPE) -> list[tuple[int, int, int]]:
    """Weak parts that complete an access identifier within its scope."""
    anchors = [(s, e) for s, kind, e in base if kind == 1]
    if not anchors:
        return []
    starts = [s for s, _, _ in base]  # sorted
    reach = list(itertools.accumulate((e for _, _, e in base), max))
    free = lambda s, e: not (k := bisect_left(starts, e)) or reach[k - 1] <= s
    weak = [(m.start(), m.end()) for m in _WEAK.finditer(text) if free(m.start(), m.end()) and _mixed(m[0])]
    ends = [(m.start(), m.end()) for m in _ENDPOINT.finditer(text)]
    strong = [(s, e) for s, kind, e in base if kind != 1]
    inside = lambda parts, lo, hi: [p for p in parts[bisect_left(parts, (lo, 0)) : bisect_left(parts, (hi, 0))] if p[1] <= hi]
    out = set()
    for s, e in anchors:
        lo, hi = s - scope, e + scope
        near = inside(weak, lo, hi)
        out |= {(a, 3, b) for a, b in near}
        if near or inside(strong, lo, hi):
            out |= {(a, 4, b) for a, b in inside(ends, lo, hi)}
    return sorted(out)


def _joined(spans: list[tuple[int, int, int]]) -> str:
    return ",".join(f"{KINDS[k]}:{s}:{e}" for s, k, e in spans)


def scan(docs: DataFrame, scope: int = SCOPE) -> DataFrame:
    """Rows ``(doc_id, n_assign, n_access, n_hex, base_sha256, spans)``."""

    @lean
    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for b in batches:
            rows = []
            for text in b["text"]:
                base = base_spans(text or "")
                every = sorted([*base, *linked_spans(text or "", base, scope)])
                counts = [sum(k == kind for _, k, _ in base) for kind in range(3)]
                rows.append((*counts, hashlib.sha256(_joined(base).encode()).hexdigest(), _joined(every)))
            got = pd.DataFrame(rows, columns=["n_assign", "n_access", "n_hex", "base_sha256", "spans"], index=b.index)
            yield pd.concat([b[["doc_id"]], got], axis=1)

    return map_frames(
        docs.select(F.col("doc_id").cast("long"), F.col("text").cast("string")), run, "doc_id long, n_assign long, n_access long, n_hex long, base_sha256 string, spans string"
    )


def redact_text(text: str | None, scope: int = SCOPE) -> str | None:
    """The text with each found stretch replaced by its first kind in brackets."""
    if not text:
        return text
    base = base_spans(text)
    out, at = [], 0
    for s, k, e in sorted([*base, *linked_spans(text, base, scope)]):
        if e > at:
            if s >= at:
                out += [text[at:s], f"[{KINDS[k]}]"]
            at = e
    return "".join([*out, text[at:]])


def redact(docs: DataFrame, scope: int = SCOPE) -> DataFrame:
    """All rows and columns of ``docs``, secrets replaced; ``n_chars`` follows where it is a column."""
    masked = F.pandas_udf(lambda s: s.map(lambda t: redact_text(t, scope)), "string")
    out = docs.withColumn("text", masked("text"))
    return out.withColumn("n_chars", F.length("text").cast(docs.schema["n_chars"].dataType)) if "n_chars" in docs.columns else out
