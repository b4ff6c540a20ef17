"""Page passes: each is one Arrow pass that returns all its columns, after pushed-down prefilters."""

from __future__ import annotations

from collections.abc import Iterator

import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions import choice as C
from ..functions import html as H
from ..functions.code import code_language, code_page
from ..functions.formula import math_page


def _scalar(fn, kind: str, df: DataFrame, column: str, out: str) -> DataFrame:
    udf = F.pandas_udf(lambda s: pd.Series([fn(x) for x in s], dtype=object), kind)
    return df.withColumn(out, udf(column))


def linearize_html(df: DataFrame, html: str = "html", out: str = "text") -> DataFrame:
    """Full-text route: everything visible."""
    return _scalar(lambda x: H.linearize(H.parse(x)), "string", df, html, out)


def extract_main_content(df: DataFrame, html: str = "html", out: str = "text", *, min_block_chars: int = 25, max_link_density: float = 0.5, favor: str = "precision") -> DataFrame:
    """Main-content route: dense blocks only."""
    return _scalar(lambda x: H.main_content(x, min_block_chars=min_block_chars, max_link_density=max_link_density, favor=favor), "string", df, html, out)


def _pass(df: DataFrame, keep: list[str], column: str, kind: str, rows) -> DataFrame:
    """``rows(value)`` gives result rows for one page; ``keep`` columns go along."""
    names = [x.split(" ")[0] for x in kind.split(", ")]

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for b in batches:
            out = [(*left, *row) for *left, value in zip(*[b[k] for k in keep], b[column], strict=True) for row in rows(value)]
            yield pd.DataFrame(out, columns=[*keep, *names])

    types = ", ".join(f"{k} {df.schema[k].dataType.simpleString()}" for k in keep)
    return df.select(*keep, column).mapInPandas(run, f"{types}, {kind}")


def code_pass(pages: DataFrame) -> DataFrame:
    """Rows ``(page_id, has_code, snippets, hidden_chars, roots, ..., text)`` of prefiltered pages."""

    def rows(html):
        got = code_page(html)
        langs = [code_language(s) for s in got["snippets"]]
        yield (
            bool(got["snippets"]), len(got["snippets"]), got["hidden_chars"], got["roots"], got["pre_roots"], got["tbody_roots"],
            got["text"], got["snippets"], [x[0] for x in langs], [x[1] for x in langs],
        )

    kind = "has_code boolean, n_snippets long, hidden_chars long, roots long, pre_roots long, tbody_roots long, text string, snippets array<string>, langs array<string>, probs array<double>"
    return _pass(pages, ["page_id"], "html", kind, rows)


def math_pass(pages: DataFrame, on_error: str = "drop_page") -> DataFrame:
    """Rows ``(page_id, n_formulas, valid, keep, text)``."""

    def rows(html):
        got = math_page(html, on_error)
        yield len(got["formulas"]), got["valid"], got["keep"], got["text"]

    return _pass(pages, ["page_id"], "html", "n_formulas long, valid long, keep boolean, text string", rows)


def formula_rows(pages: DataFrame) -> DataFrame:
    """One row per located formula."""

    def rows(html):
        for i, (dialect, source, display, ok, reason) in enumerate(math_page(html)["formulas"]):
            yield i, dialect, source, display, ok, reason

    return _pass(pages, ["page_id"], "html", "pos long, dialect string, source string, display boolean, ok boolean, reason string", rows)


def choice_rows(df: DataFrame, answer_position: str = "after") -> DataFrame:
    """One row per multiple-choice question, with its standard form."""

    def rows(text):
        for q in C.choice_questions(text, answer_position):
            yield q.first, q.style, q.stem, "|".join(q.options), q.answer, q.explanation, C.format_question(q)

    return _pass(df, ["doc_id"], "text", "first long, style string, stem string, options string, answer string, explanation string, formatted string", rows)


def choice_run_rows(df: DataFrame) -> DataFrame:
    """One row per option run."""

    def rows(text):
        lines = [x for x in (text or "").split("\n") if x.strip()]
        for start, _end, style, options in C.choice_runs(lines):
            yield start, style, len(options)

    return _pass(df, ["doc_id"], "text", "first long, style string, n_options long", rows)
