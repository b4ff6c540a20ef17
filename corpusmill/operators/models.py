"""Language tagging, sampling, and linear text classifiers."""

from __future__ import annotations

import functools
from collections.abc import Callable, Iterator

import numpy as np
import pandas as pd
from pyspark.ml import Pipeline, PipelineModel
from pyspark.ml.classification import LogisticRegression
from pyspark.ml.feature import HashingTF, NGram, RegexTokenizer, VectorAssembler
from pyspark.ml.functions import vector_to_array
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..functions.text import hash60
from .joins import salted_join

SHARPNESS, BLOCK, SALTS = 12.0, 2**18, 16
#: Counts a driver and a worker can hold; a larger model stays a table and is joined.
BROADCAST_COUNTS = 500_000
_BITS = np.uint64(21)


@functools.cache
def _alphabet() -> np.ndarray:
    return np.fromiter((chr(c).isalpha() for c in range(0x110000)), bool, 0x110000)


def _merged(keys: np.ndarray, n: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    if not len(keys):
        return keys, n
    order = np.argsort(keys, kind="stable")
    keys, n = keys[order], n[order]
    starts = np.flatnonzero(np.concatenate([[True], keys[1:] != keys[:-1]]))
    return keys[starts], np.add.reduceat(n, starts)


def gram_counts(text: str | None) -> tuple[np.ndarray, np.ndarray]:
    """Character 1-3-grams of a whole text as sorted numbers, and how often each occurs.

    Letters are lower-cased, runs of all else are one space. A gram is its code
    points, 21 bits each. Texts are counted block by block.
    """
    codes = np.frombuffer((text or "").lower().encode("utf-32-le", "surrogatepass"), np.uint32)
    letter = _alphabet()[codes]
    codes = np.where(letter, codes, np.uint32(32))[letter | np.concatenate([[False], letter[:-1]])[: len(letter)]]
    if len(codes) and codes[-1] == 32:
        codes = codes[:-1]
    found = [(np.empty(0, np.int64), np.empty(0, np.int64))]
    for at in range(0, len(codes), BLOCK):
        w = np.zeros(min(BLOCK, len(codes) - at) + 2, np.uint64)
        part = codes[at : at + BLOCK + 2]
        w[: len(part)] = part
        found.append(np.unique((w[:-2] | w[1:-1] << _BITS | w[2:] << _BITS * np.uint64(2)).view(np.int64), return_counts=True))
    threes, n = _merged(*map(np.concatenate, zip(*found, strict=True)))
    # A text ends in empty places, so its grams of one and two are those that its threes begin with.
    heads = [(threes & (2**21 - 1), n)] + [(threes[has] & mask, n[has]) for has, mask in ((threes >> 21 > 0, 2**42 - 1), (threes >> 42 > 0, -1))]
    return _merged(*map(np.concatenate, zip(*heads, strict=True)))


def _count_grams(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
    """Partial counts by label; handed on whenever they have grown large."""
    for b in batches:
        for label, texts in b.groupby("label")["text"]:
            kept, size = [], 0
            for k, t in enumerate(texts, 1):
                kept.append(gram_counts(t))
                size += len(kept[-1][0])
                if size > 2**20 or k == len(texts):
                    g, n = _merged(*map(np.concatenate, zip(*kept, strict=True)))
                    yield pd.DataFrame({"label": label, "g": g, "n": n})
                    kept, size = [], 0


def train_language_model(df: DataFrame, label: str = "lang") -> dict:
    """Log probabilities of all character 1-3-grams of whole texts, counted in Spark.

    Up to ``BROADCAST_COUNTS`` counts make arrays; beyond that the model holds
    a table with one row a gram.
    """
    texts = df.where(F.col(label).isNotNull()).select(F.col(label).cast("string").alias("label"), "text")
    counts = texts.mapInPandas(_count_grams, "label string, g long, n long").groupBy("label", "g").agg(F.sum("n").alias("n"))
    rows = counts.limit(BROADCAST_COUNTS + 1).collect()
    if len(rows) > BROADCAST_COUNTS:
        return _language_table(counts)
    langs = sorted({r.label for r in rows})
    grams, row = np.unique(np.array([r.g for r in rows], np.int64), return_inverse=True)
    at = {k: i for i, k in enumerate(langs)}
    table = np.zeros((len(grams), len(langs)))
    table[row, [at[r.label] for r in rows]] = [r.n for r in rows]
    return {"langs": langs, "grams": grams, "logs": np.log((table + 0.5) / (table.sum(axis=0) + 0.5 * len(grams)))}


def _language_table(counts: DataFrame) -> dict:
    totals = {r.label: r.t for r in counts.groupBy("label").agg(F.sum("n").alias("t")).collect()}
    langs = sorted(totals)
    grams = counts.select("g").distinct().count()
    n = lambda k: F.coalesce(F.sum(F.when(F.col("label") == k, F.col("n"))), F.lit(0))
    logs = [F.log((n(k) + 0.5) / F.lit(totals[k] + 0.5 * grams)).alias(f"w{i}") for i, k in enumerate(langs)]
    return {"langs": langs, "table": counts.groupBy("g").agg(*logs)}


def _verdict(mean: np.ndarray, langs: list[str]) -> tuple[str, float]:
    p = np.exp((mean - mean.max()) * SHARPNESS)
    p /= p.sum()
    best = int(p.argmax())
    return langs[best], float(p[best])


def language_of(text: str | None, model: dict) -> tuple[str, float]:
    """Language and confidence: softmax over sharpened mean log-likelihoods of a whole text."""
    g, n = gram_counts(text)
    known = model["grams"]
    at = np.searchsorted(known, g)
    hit = at < len(known)
    hit[hit] = known[at[hit]] == g[hit]
    if not hit.any():
        return "und", 0.0
    return _verdict(n[hit] @ model["logs"][at[hit]] / n[hit].sum(), model["langs"])


def score_language(df: DataFrame, model: dict) -> DataFrame:
    """Adds ``lang_pred`` and ``lang_prob``: arrays of a model are broadcast, its table is joined."""
    if "table" in model:
        return _score_by_join(df, model)
    shared = df.sparkSession.sparkContext.broadcast(model)

    def run(batches: Iterator[pd.Series]) -> Iterator[pd.DataFrame]:
        m = shared.value
        for b in batches:
            yield pd.DataFrame([language_of(t, m) for t in b], columns=["lang_pred", "lang_prob"])

    return df.withColumn("_l", F.pandas_udf(run, "lang_pred string, lang_prob double")("text")).select(*df.columns, "_l.*")


def _score_by_join(df: DataFrame, model: dict) -> DataFrame:
    """Texts are scored once each, under their digest; their grams meet the table in a salted join."""
    langs = model["langs"]
    digest = F.sha2(F.coalesce("text", F.lit("")), 256)

    def grams(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for b in batches:
            for h, t in zip(b["_h"], b["text"], strict=True):
                g, n = gram_counts(t)
                yield pd.DataFrame({"_h": h, "g": g, "n": n})

    texts = df.select(digest.alias("_h"), "text").dropDuplicates(["_h"])
    met = salted_join(texts.mapInPandas(grams, "_h string, g long, n long"), model["table"], ["g"], SALTS, F.xxhash64("_h"))
    means = F.array(*[F.sum(F.col("n") * F.col(f"w{i}")) / F.sum("n") for i in range(len(langs))])
    scored = met.groupBy("_h").agg(means.alias("_m"))
    verdict = F.pandas_udf(lambda s: pd.DataFrame([_verdict(np.asarray(m), langs) for m in s], columns=["lang_pred", "lang_prob"]), "lang_pred string, lang_prob double")
    told = scored.select("_h", verdict("_m").alias("_l")).select("_h", "_l.*")
    out = df.withColumn("_h", digest).join(told, "_h", "left")
    return out.select(*df.columns, F.coalesce("lang_pred", F.lit("und")).alias("lang_pred"), F.coalesce("lang_prob", F.lit(0.0)).alias("lang_prob"))


def keep_language(df: DataFrame, lang: str = "en", threshold: float = 0.5) -> DataFrame:
    return df.where((F.col("lang_pred") == lang) & (F.col("lang_prob") >= threshold))


def annotate(df: DataFrame, labels: DataFrame, annotator: Callable[[DataFrame], DataFrame] | None = None) -> DataFrame:
    """Adds ``label``: from the given labels, or from any function of the DataFrame in place of an LLM."""
    return annotator(df) if annotator else df.join(labels.select("doc_id", F.col("quality").cast("int").alias("label")), "doc_id")


def balanced_sample(df: DataFrame, label: str, n_per_class: int, id: str = "doc_id") -> DataFrame:
    """The first ``n_per_class`` rows of each class in hash order: the same rows under any partitioning."""
    order = Window.partitionBy(label).orderBy(hash60(F.col(id).cast("string")), id)
    return df.where(F.col(label).isNotNull()).withColumn("_r", F.row_number().over(order)).where(F.col("_r") <= n_per_class).drop("_r")


def stratified_sample(df: DataFrame, label: str, stratum: str, n_per_stratum: int, id: str = "doc_id") -> DataFrame:
    order = Window.partitionBy(label, stratum).orderBy(hash60(F.col(id).cast("string")), id)
    return df.withColumn("_r", F.row_number().over(order)).where(F.col("_r") <= n_per_stratum).drop("_r")


def held_out(id: str = "doc_id", parts: int = 5) -> Column:
    return hash60(F.col(id).cast("string")) % parts == 0


def train_text_classifier(df: DataFrame, dims: int = 2**16, l2: float = 0.01) -> PipelineModel:
    """Logistic regression on hashed word 1-2-grams of ``(text, label)``."""
    stages = [
        RegexTokenizer(inputCol="text", outputCol="_w", pattern=r"[\s]+", toLowercase=True),
        NGram(n=2, inputCol="_w", outputCol="_b"),
        HashingTF(inputCol="_w", outputCol="_f1", numFeatures=dims, binary=True),
        HashingTF(inputCol="_b", outputCol="_f2", numFeatures=dims, binary=True),
        VectorAssembler(inputCols=["_f1", "_f2"], outputCol="features"),
        LogisticRegression(featuresCol="features", labelCol="label", maxIter=25, regParam=l2),
    ]
    return Pipeline(stages=stages).fit(df.select(F.coalesce("text", F.lit("")).alias("text"), F.col("label").cast("double")))


def score_model(df: DataFrame, model: PipelineModel, out: str = "p_quality") -> DataFrame:
    """Adds the probability of label 1; narrow, no shuffle."""
    got = model.transform(df.withColumn("text", F.coalesce("text", F.lit(""))))
    return got.select(*df.columns, vector_to_array("probability")[1].alias(out))


class Scorer:
    """Protocol of heavy models: loaded once per Python worker, then fed with batches."""

    def load(self) -> None: ...

    def score(self, texts: list[str]) -> list[float]:
        raise NotImplementedError


def score_with(df: DataFrame, scorer: Scorer, out: str = "p_quality") -> DataFrame:
    """Score with any ``Scorer``."""

    def run(batches: Iterator[pd.Series]) -> Iterator[pd.Series]:
        scorer.load()
        for b in batches:
            yield pd.Series(scorer.score([t or "" for t in b]), dtype="float64")

    return df.withColumn(out, F.pandas_udf(run, "double")("text"))


def binary_report(df: DataFrame, label: str, predicted: str) -> DataFrame:
    """Counts of the four outcomes in one aggregate."""
    y, p = F.col(label) == 1, F.col(predicted)
    return df.agg(*[F.count_if(c).alias(n) for n, c in (("tp", y & p), ("fp", ~y & p), ("tn", ~y & ~p), ("fn", y & ~p))])


def build_math_training(pos: DataFrame, pool: DataFrame, n: int) -> DataFrame:
    """Half positives from the markup track, half random texts of the pool that are none of them."""
    order = hash60(F.col("text"))
    yes = pos.select("text").distinct().withColumn("h", order).orderBy("h").limit(n).select("text", F.lit(1).alias("label"))
    no = pool.select("text").join(pos.select("text"), "text", "left_anti").distinct().withColumn("h", order).orderBy("h").limit(n).select("text", F.lit(0).alias("label"))
    return yes.unionByName(no)
