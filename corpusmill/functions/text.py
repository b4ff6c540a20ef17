"""Segmentation and hashing: column expressions, and the same in plain Python.

White space is space, tab, line feed, carriage return and form feed. Paragraphs
are non-empty lines; sentences are paragraphs cut after . ! ? before a space.
"""

from __future__ import annotations

import hashlib
import re

from pyspark.sql import Column
from pyspark.sql import functions as F

SPACE = r"[ \t\r\n\f]+"
_EDGES = r"^[ \t\r\f]+|[ \t\r\f]+$"


def words(text: Column) -> Column:
    return F.filter(F.split(text, SPACE), lambda w: w != "")


def _lines(text: Column) -> Column:
    return F.filter(F.transform(F.split(text, "\n"), lambda p: F.regexp_replace(p, _EDGES, "")), lambda p: p != "")


def paragraphs(text: Column) -> Column:
    return _lines(text)


def sentences(text: Column) -> Column:
    return _lines(F.regexp_replace(text, r"([.!?])" + SPACE, "$1\n"))


def hash60(value: Column) -> Column:
    """Sixty bits of md5 as a non-negative long; DuckDB and Python can say the same."""
    return F.conv(F.substring(F.md5(value), 1, 15), 16, 10).cast("long")


def py_hash60(value: str) -> int:
    return int(hashlib.md5(value.encode("utf-8")).hexdigest()[:15], 16)


def py_words(text: str | None) -> list[str]:
    return [w for w in re.split(SPACE, text or "") if w]


def py_paragraphs(text: str | None) -> list[str]:
    return [p for p in (x.strip(" \t\r\f") for x in (text or "").split("\n")) if p]


def py_sentences(text: str | None) -> list[str]:
    return py_paragraphs(re.sub(r"([.!?])[ \t\r\n\f]+", "\\1\n", text or ""))


#: The same in DuckDB, over a column ``text``.
SQL_WORDS = r"list_filter(string_split_regex(text, '[ \t\r\n\f]+'), lambda w: w <> '')"
_SQL_LINES = r"list_filter(list_transform(string_split({}, chr(10)), lambda p: regexp_replace(p, '^[ \t\r\f]+|[ \t\r\f]+$', '', 'g')), lambda p: p <> '')"
SQL_PARAGRAPHS = _SQL_LINES.format("text")
SQL_SENTENCES = _SQL_LINES.format(r"regexp_replace(text, '([.!?])[ \t\r\n\f]+', '\1' || chr(10), 'g')")
