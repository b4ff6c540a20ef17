"""Quality rules with thresholds taken from mergeable quantile sketches.

Each metric of a document is an integer (a share in thousandths, a mean in
hundredths). A sketch is a histogram over log-linear buckets: exact below 128,
64 buckets an octave above, so a quantile is off by less than 1/64 of itself.
Sketches merge by adding counts, which makes them one ``groupBy`` with map-side
sums: a hot source costs no more than a cold one, and reruns agree exactly.
Only documents that pass the base rule are sketched: the others are gone anyway.

The sketch of a (language, source) group is merged with that of its language,
and this one with that of all documents, each weighted as ``PRIOR`` documents.
A large group follows its own documents, a small one those of its parents, and
nothing changes suddenly at any size.

A fence is ``q + reach * |q - median|`` beyond an inner quantile ``q``: it has no
unit, so a group whose values are shifted or scaled has its fences shifted or
scaled likewise. A share fails only if its count is beyond what the fence allows
by ``NOISE`` standard deviations of that count, so one stray symbol is no failure
where most texts have none.

Edge cases: null or empty text has no words and fails the base rule; null
language or source is a group of its own; a group without a document that passes
the base rule has its parents' fences; repeated rows count each; other columns,
also clashing ones, are carried only by ``judge``.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ._spark import lean, map_frames, settle

SYMBOLS = "#*$%&|<>"
#: metric: (counted, out of, scale, upper quantile and reach, the same below)
METRICS = {
    "symbol_share": ("n_symbols", "n_words", 1000, (0.8, 3), None),
    "repeat_share": ("n_repeat_words", "n_words", 1000, (0.99, 1), None),
    "dup_line_share": ("n_dup_lines", "n_lines", 1000, (0.99, 1), None),
    "word_length": ("word_chars", "n_words", 100, (0.9, 2), (0.1, 2)),
}
PRIOR = 50  # documents that a parent's sketch counts as
NOISE = 3
MOST_BROADCAST = 50_000  # groups whose fences go to every task; more are joined by shuffles
BASE_FAILED = "n_words < 50 or n_repeat_words * 100 > n_words * 50"


def _value(metric: str) -> Column:
    counted, out_of, scale, *_ = METRICS[metric]
    return F.expr(f"{scale} * {counted} div greatest({out_of}, 1)")


def _repeat_words(words: list[bytes]) -> int:
    """Words inside three-word windows that occur at least twice in the text."""
    if len(words) < 4:
        return 0
    index: dict[bytes, int] = {}
    ids = np.fromiter((index.setdefault(w, len(index)) for w in words), np.int64, len(words))
    n = len(index)
    pair = ids[:-1] * n + ids[1:]
    if n > 1_000_000:
        pair = np.unique(pair, return_inverse=True)[1]
    key = pair[:-1] * n + ids[2:]
    order = np.argsort(key, kind="stable")
    same = key[order][1:] == key[order][:-1]
    again = np.zeros(len(key), bool)
    again[order[1:][same]] = again[order[:-1][same]] = True
    cover = np.zeros(len(ids), bool)
    for k in range(3):
        cover[k : k + len(key)] |= again
    return int(cover.sum())


def _metrics(text: str | None) -> tuple[int, ...]:
    if not text:
        return 0, 0, 0, 0, 0, 0
    raw = text.encode("utf-8")
    words = raw.split()
    chars = len(b"".join(words).decode("utf-8"))
    symbols = len(raw) - len(raw.translate(None, SYMBOLS.encode()))
    lines = [x for x in raw.split(b"\n") if x.strip()]
    return len(words), chars, symbols, len(lines) - len(set(lines)), _repeat_words(words), len(lines)


def measure(docs: DataFrame) -> DataFrame:
    """One narrow pass over whole texts: the integer base columns per document."""
    names = ["n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", "n_lines"]

    @lean
    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for b in batches:
            got = pd.DataFrame([_metrics(t) for t in b.pop("text")], columns=names, index=b.index)
            yield pd.concat([b, got], axis=1)

    picked = docs.select(F.col("doc_id").cast("long"), "lang", "source", F.col("text").cast("string"))
    return map_frames(picked, run, "doc_id long, lang string, source string, " + ", ".join(f"{n} long" for n in names))


def bucket(v: Column) -> Column:
    """Log-linear bucket of a non-negative integer: its six leading bits and its size."""
    shift = F.greatest(F.length(F.bin(v)) - 7, F.lit(0))
    return F.expr("0").cast("long") + (shift * 64).cast("long") + F.floor(v / F.pow(F.lit(2.0), shift)).cast("long")


def bucket_floor(b: Column) -> Column:
    """Smallest value of a bucket."""
    shift = F.greatest(F.floor(b / 64) - 1, F.lit(0)).cast("long")
    return ((b - shift * 64) * F.pow(F.lit(2.0), shift)).cast("long")


def sketches(measured: DataFrame) -> DataFrame:
    """Mergeable sketches ``(lang, source, metric, bucket, n)`` of the documents that pass the base rule."""
    pairs = F.array(*[F.struct(F.lit(m).alias("metric"), bucket(_value(m)).alias("bucket")) for m in METRICS])
    passing = measured.where(f"not ({BASE_FAILED})").select("lang", "source", F.explode(pairs).alias("m"))
    return passing.groupBy("lang", "source", "m.metric", "m.bucket").agg(F.count("*").alias("n"))


def _listed(sketch: DataFrame, by: list[str]) -> DataFrame:
    """One row a group and metric: its merged sketch as an array, and its documents."""
    merged = sketch.groupBy(*by, "metric", "bucket").agg(F.sum("n").alias("n"))
    weighed = F.struct("bucket", F.col("n").cast("double").alias("w"))
    return merged.groupBy(*by, "metric").agg(F.array_sort(F.collect_list(weighed)).alias("h"), F.sum("n").cast("double").alias("docs"))


def _blended(own: Column, parent: Column, parent_docs: Column, prior: float) -> Column:
    """A sketch and its parent's, the latter weighted as ``prior`` documents."""
    return F.concat(own, F.transform(parent, lambda x: F.struct(x["bucket"], (x["w"] * prior / parent_docs).alias("w"))))


def _quantile(q: float) -> Column:
    """Floor of the first bucket at which the running weight of the sorted sketch ``h`` reaches ``q`` of all."""
    step = lambda s, x: F.struct(
        (s["seen"] + x["w"]).alias("seen"),
        F.when(s["found"] >= 0, s["found"]).when(s["seen"] + x["w"] >= F.col("docs") * (q - 1e-9), x["bucket"]).otherwise(s["found"]).alias("found"),
    )
    zero = F.struct(F.lit(0.0).alias("seen"), F.lit(-1).cast("long").alias("found"))
    return bucket_floor(F.aggregate("h", zero, step, lambda s: s["found"]))


def _fence(side: int) -> Column:
    """Upper (3) or lower (4) fence of the metric of a row; null where it has none."""
    found = F.lit(None).cast("double")
    for m, rule in METRICS.items():
        if rule[side]:
            q, reach = rule[side]
            found = F.when(F.col("metric") == m, _quantile(q) + (_quantile(q) - _quantile(0.5)) * float(reach)).otherwise(found)
    return found


def thresholds(sketch: DataFrame, groups: DataFrame, prior: float = PRIOR) -> DataFrame:
    """Fences ``(lang, source, metric, low, high)`` of every row ``(lang, source)`` of ``groups``."""
    every = _listed(sketch, []).withColumnsRenamed({"h": "e_h", "docs": "e_docs"})
    lang = _listed(sketch, ["lang"]).select(F.col("lang").alias("l_lang"), F.col("metric").alias("l_metric"), F.col("h").alias("l_h"), F.col("docs").alias("l_docs"))
    own = _listed(sketch, ["lang", "source"]).withColumnsRenamed({"lang": "o_lang", "source": "o_source", "metric": "o_metric", "h": "o_h", "docs": "o_docs"})
    is_lang = F.col("lang").eqNullSafe(F.col("l_lang")) & (F.col("metric") == F.col("l_metric"))
    is_own = F.col("lang").eqNullSafe(F.col("o_lang")) & F.col("source").eqNullSafe(F.col("o_source")) & (F.col("metric") == F.col("o_metric"))
    none = F.array().cast(every.schema["e_h"].dataType)
    zero = lambda c: F.coalesce(c, F.lit(0.0))
    metrics = groups.select("lang", "source", F.explode(F.array(*map(F.lit, METRICS))).alias("metric"))
    joined = metrics.join(every, "metric").join(lang, is_lang, "left").join(own, is_own, "left")
    up = _blended(F.coalesce("l_h", none), F.col("e_h"), F.col("e_docs"), prior)
    joined = joined.withColumn("u_h", up).withColumn("u_docs", zero(F.col("l_docs")) + prior)
    down = _blended(F.coalesce("o_h", none), F.col("u_h"), F.col("u_docs"), prior)
    merged = joined.select("lang", "source", "metric", F.array_sort(down).alias("h"), (zero(F.col("o_docs")) + prior).alias("docs"))
    return merged.select("lang", "source", "metric", _fence(4).alias("low"), _fence(3).alias("high"))


def _beyond(metric: str) -> Column:
    """Whether a document lies beyond the fences of its group."""
    counted, out_of, scale, upper, lower = METRICS[metric]
    n, high, low = F.expr(f"greatest({out_of}, 1)"), F.col(f"high_{metric}"), F.col(f"low_{metric}")
    if lower:
        return (_value(metric) > high) | (_value(metric) < low)
    return F.col(counted) - NOISE * F.sqrt(counted) > n * high / scale


def judge(measured: DataFrame, fences: DataFrame) -> DataFrame:
    """Join every document with its group's fences: adds ``base_failed`` and ``kept``."""
    wide = fences.groupBy("lang", "source").agg(
        *[F.max(F.when(F.col("metric") == m, F.col(c))).alias(f"{c}_{m}") for m in METRICS for c in ("low", "high")]
    )
    f = wide.withColumnsRenamed({"lang": "f_lang", "source": "f_source"})
    if fences.count() <= MOST_BROADCAST * len(METRICS):
        f = F.broadcast(f)
    joined = measured.join(f, F.col("lang").eqNullSafe(F.col("f_lang")) & F.col("source").eqNullSafe(F.col("f_source")), "left")
    bad = F.lit(False)
    for m in METRICS:
        bad = bad | F.coalesce(_beyond(m), F.lit(False))
    base = F.expr(BASE_FAILED)
    return joined.withColumn("base_failed", base).withColumn("kept", ~base & ~bad).select(*measured.columns, "base_failed", "kept")


def quality_verdicts(docs: DataFrame) -> DataFrame:
    """Base metrics, ``base_failed`` and ``kept`` for every row of ``docs``."""
    measured = settle(measure(docs))  # narrow rows: the texts are read once
    groups = measured.select("lang", "source").distinct()
    return judge(measured, settle(thresholds(sketches(measured), groups)))
