"""Rule scores of the web track: length, repetition, document and sentence rules.

Every ``score_*`` keeps all rows and adds integer inputs and flags; ``keep_*``
is the matching filter. Flags compare integers, so equality never flags.
"""

from __future__ import annotations

import re
from collections import Counter
from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..functions import text as T

# Shares in hundredths by n-gram size, stop words, bullets.
TOP_NGRAM = {2: 20, 3: 18, 4: 16}
DUP_NGRAM = {5: 15, 6: 14, 7: 13, 8: 12, 9: 11, 10: 10}
STOP_WORDS = ("the", "be", "to", "of", "and", "that", "have", "with")
BULLETS = ("-", "*", "•", "‣", "▪", "●", "–")


def score_length(df: DataFrame, least: int = 300, unit: str = "chars") -> DataFrame:
    """Texts shorter than ``least`` fail; ``n_chars`` is used where the table has it, so the filter reaches the scan."""
    size = F.size(T.words(F.col("text"))) if unit == "words" else F.col("n_chars") if "n_chars" in df.columns else F.length("text")
    return df.withColumn("keep_length", size >= least)


def score_document_rules(df: DataFrame, stop_least: int = 2) -> DataFrame:
    """Seven document rules on built-in expressions only."""
    n = df.withColumn("_w", T.words(F.col("text"))).withColumn("_s", T.sentences(F.col("text")))
    low = F.transform("_w", lambda w: F.regexp_replace(F.lower(w), r"^[.,;:!?]+|[.,;:!?]+$", ""))
    first = lambda s: F.substring(s, 1, 1)
    n = n.select(
        *df.columns,
        F.size("_w").cast("long").alias("n_words"),
        F.aggregate("_w", F.lit(0), lambda a, w: a + F.length(w)).cast("long").alias("word_chars"),
        (F.regexp_count("text", F.lit("#")) + F.regexp_count("text", F.lit(r"\.\.\.")) + F.regexp_count("text", F.lit("…"))).cast("long").alias("symbols"),
        F.size("_s").cast("long").alias("n_sentences"),
        F.size(F.filter("_s", lambda s: first(s).isin(*BULLETS))).cast("long").alias("bullets"),
        F.size(F.filter("_s", lambda s: s.endswith("...") | s.endswith("…"))).cast("long").alias("ellipses"),
        F.size(F.filter("_w", lambda w: ~w.rlike(r"\p{L}"))).cast("long").alias("no_alpha"),
        F.size(F.array_intersect(F.array(*map(F.lit, STOP_WORDS)), low)).cast("long").alias("stops"),
    )
    c = F.col
    flags = {
        "f_words": (c("n_words") < 50) | (c("n_words") > 100_000),
        "f_mean_word": (c("word_chars") < 3 * c("n_words")) | (c("word_chars") > 10 * c("n_words")),
        "f_symbols": 10 * c("symbols") > c("n_words"),
        "f_bullets": 10 * c("bullets") > 9 * c("n_sentences"),
        "f_ellipses": 10 * c("ellipses") > 3 * c("n_sentences"),
        "f_no_alpha": 5 * c("no_alpha") > c("n_words"),
        "f_stops": c("stops") < stop_least,
    }
    empty = {"f_symbols", "f_bullets", "f_ellipses", "f_no_alpha", "f_mean_word"}
    return n.withColumns({k: v & (c("n_words") > 0) if k in empty else v for k, v in flags.items()})


def ngram_counts(words: list[str], sizes: dict[int, int], tops: dict[int, int]) -> tuple[dict[int, int], dict[int, int], dict[int, int]]:
    """``(best count, top characters, covered characters)`` by n-gram size."""
    index: dict[str, int] = {}
    ids = np.fromiter((index.setdefault(w, len(index)) for w in words), np.int64, len(words))
    chars = np.fromiter(map(len, words), np.int64, len(words))
    total = np.concatenate([[0], np.cumsum(chars)])
    best, top, cover = {}, {}, {}
    codes = ids
    for n in range(2, max([*sizes, *tops]) + 1):
        m = len(ids) - n + 1
        if m < 1:
            codes = np.empty(0, np.int64)
        else:
            codes = np.unique(codes[:m] * (len(index) + 1) + ids[n - 1 :], return_inverse=True)[1]
        k = np.bincount(codes)[codes] if len(codes) else np.empty(0, np.int64)
        most = int(k.max()) if len(k) else 0
        if n in tops:
            best[n] = most
            at = np.flatnonzero(k == most) if most >= 2 else []
            top[n] = int(most * (total[np.asarray(at) + n] - total[at]).max()) if len(at) else 0
        if n in sizes:
            edge = np.zeros(len(words) + 1, np.int64)
            hit = np.flatnonzero(k >= 2)
            np.add.at(edge, hit, 1)
            np.add.at(edge, hit + n, -1)
            cover[n] = int(chars[np.cumsum(edge)[:-1] > 0].sum())
    return best, top, cover


def _repeats(parts: list[str]) -> tuple[int, int, int]:
    seen = Counter(parts)
    return len(parts), len(parts) - len(seen), sum(len(p) * (k - 1) for p, k in seen.items())


def repetition_of(text: str | None) -> dict[str, int]:
    """All integer inputs of the repetition rules for one text."""
    s, p = _repeats(T.py_sentences(text)), _repeats(T.py_paragraphs(text))
    best, top, cover = ngram_counts(T.py_words(text), DUP_NGRAM, TOP_NGRAM)
    out = {"n_text": len(text or ""), "n_sent": s[0], "dup_sent": s[1], "dup_sent_chars": s[2], "n_para": p[0], "dup_para": p[1], "dup_para_chars": p[2]}
    return out | {f"best_{n}": v for n, v in best.items()} | {f"top_{n}": v for n, v in top.items()} | {f"cover_{n}": v for n, v in cover.items()}


_REPETITION = list(repetition_of(""))


def too_many_paragraphs(denominator: str) -> Column:
    """Repeated paragraphs over 30 % of the sentences (as printed) or of the paragraphs."""
    return 10 * F.col("dup_para") > 3 * F.col("n_sent" if denominator == "sentence" else "n_para")


def score_repetition(df: DataFrame, para_denominator: str = "sentence") -> DataFrame:
    """Thirteen repetition rules in one Arrow pass over the text. ``para_denominator`` is ``sentence`` (as printed) or ``paragraph``."""

    def run(batches: Iterator[pd.Series]) -> Iterator[pd.DataFrame]:
        for b in batches:
            yield pd.DataFrame([repetition_of(t) for t in b], columns=_REPETITION)

    udf = F.pandas_udf(run, ", ".join(f"{c} long" for c in _REPETITION))
    out = df.withColumn("_r", udf("text")).select(*df.columns, "_r.*")
    c = F.col
    flags = {
        "f_dup_sent": 10 * c("dup_sent") > 3 * c("n_sent"),
        "f_dup_sent_chars": 5 * c("dup_sent_chars") > c("n_text"),
        "f_dup_para": too_many_paragraphs(para_denominator),
        "f_dup_para_chars": 5 * c("dup_para_chars") > c("n_text"),
    }
    flags |= {f"f_top_{n}": 100 * c(f"top_{n}") > share * c("n_text") for n, share in TOP_NGRAM.items()}
    flags |= {f"f_cover_{n}": 100 * c(f"cover_{n}") > share * c("n_text") for n, share in DUP_NGRAM.items()}
    return out.withColumns(flags)


SENTENCE_RULES = ("upper", "numeric", "counter", "one_word", "sign_in", "read_more", "items_in_card")
_NUMERIC = re.compile(r"[0-9 \t.,]*[0-9][0-9 \t.,]*")
_COUNTER = re.compile(r"[0-9]+[ \t]+[a-zA-Z]+")
_SIGN, _MORE, _CARD = re.compile("sign-in", re.I), re.compile(r"read more.{3}$", re.I), re.compile("items in card", re.I)


def sentence_hits(s: str) -> list[bool]:
    """Which of the seven sentence rules a sentence meets."""
    letters = [c for c in s if c.isalpha()]
    upper = sum(c.isupper() for c in letters)
    return [
        10 * upper > 6 * len(letters), bool(_NUMERIC.fullmatch(s)), bool(_COUNTER.fullmatch(s)), len(T.py_words(s)) == 1,
        bool(_SIGN.match(s)), bool(_MORE.search(s)), bool(_CARD.search(s)),
    ]


def clean_sentences(text: str | None) -> tuple[str, int, int, list[int]]:
    """``(text without the sentences that meet a rule, words, removed words, hits by rule)``."""
    kept, words, removed, hits = [], 0, 0, [0] * len(SENTENCE_RULES)
    for paragraph in T.py_paragraphs(text):
        left = []
        for s in T.py_sentences(paragraph):
            n, met = len(T.py_words(s)), sentence_hits(s)
            words += n
            hits = [a + b for a, b in zip(hits, met, strict=True)]
            if any(met):
                removed += n
            else:
                left.append(s)
        if left:
            kept.append(" ".join(left))
    return "\n".join(kept), words, removed, hits


def apply_sentence_rules(df: DataFrame, most_removed_percent: int = 5) -> DataFrame:
    """Adds ``text_clean``, ``words_all``, ``words_removed``, ``hit_*`` and ``f_sentences`` (too much removed)."""

    def run(batches: Iterator[pd.Series]) -> Iterator[pd.DataFrame]:
        for b in batches:
            rows = [(t, w, r, *h) for t, w, r, h in map(clean_sentences, b)]
            yield pd.DataFrame(rows, columns=["text_clean", "words_all", "words_removed", *[f"hit_{r}" for r in SENTENCE_RULES]])

    udf = F.pandas_udf(run, "text_clean string, words_all long, words_removed long, " + ", ".join(f"hit_{r} long" for r in SENTENCE_RULES))
    out = df.withColumn("_r", udf("text")).select(*df.columns, "_r.*")
    return out.withColumn("f_sentences", 100 * F.col("words_removed") > most_removed_percent * F.col("words_all"))


def any_flag(columns: list[str]) -> Column:
    out = F.lit(False)
    for c in columns:
        if c.startswith("f_"):
            out = out | F.col(c)
    return out


def keep(df: DataFrame) -> DataFrame:
    """Rows without a raised flag."""
    return df.where(~any_flag(df.columns))
