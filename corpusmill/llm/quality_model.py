"""Quality classifier learned from pairwise preferences (Bradley-Terry).

Every text becomes a row of integers-free numeric features in one narrow pass.
A document marked good is preferred to one marked bad; weights are learned by
logistic loss on differences of features, so they rank documents rather than
fit label shares. The cut is a quantile of the training scores, at the share of
bad labels there, and scores are carried to 0..1 so that it lies at 0.3.

Training uses a bounded sample: ``most_labels`` labelled rows in hash order and
``most_pairs`` preference pairs. Scoring covers every row.

Edge cases: null counts as empty and gets a score; labels that are null or
without a text are ignored; with no pair of labels every score is 0.5; repeated
rows are scored each; language, source and ids are never features.
"""

from __future__ import annotations

import math
from collections import Counter
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ._spark import lean, map_frames, settle

CUT = 0.3
FEATURES = (
    "log_words", "word_length", "long_words", "short_words", "symbols", "marks", "bars", "upper", "digits",
    "stops", "commas", "distinct", "top_word", "top_pair", "repeat_triples", "dup_lines", "words_per_line", "letters", "entropy",
)
_UPPER = bytes(range(65, 91))
_LOWER = bytes(range(97, 123))


def features(text: str | None) -> list[float]:
    """Numbers about a whole text, most of them shares."""
    raw = (text or "").encode("utf-8")
    words = raw.split()
    n, size = len(words), max(1, len(raw))
    if not n:
        return [0.0] * len(FEATURES)
    count = lambda chars: (len(raw) - len(raw.translate(None, chars))) / size
    lengths = np.fromiter(map(len, words), np.int64, n)
    seen = Counter(words)
    times = np.fromiter(seen.values(), np.float64, len(seen))
    index = dict(zip(seen, range(len(seen)), strict=True))
    ids = np.fromiter(map(index.__getitem__, words), np.int64, n)
    pair = ids[:-1] * len(seen) + ids[1:]
    pairs = np.unique(pair, return_counts=True)[1] if n > 1 else np.zeros(1)
    triple = pair[:-1] * len(seen) + ids[2:] if n > 2 else np.zeros(0, np.int64)
    lines = [x for x in raw.split(b"\n") if x.strip()]
    upper, lower = count(_UPPER), count(_LOWER)
    share = times / n
    return [
        math.log(n), float(lengths.mean()), float((lengths > 12).mean()), float((lengths < 4).mean()), count(b"#*$%&<>"), count(b"!?"), count(b"|"),
        upper / max(1e-9, upper + lower), count(b"0123456789"), count(b"."), count(b",;:"), len(seen) / n, float(times.max()) / n, float(pairs.max()) / n,
        1 - len(np.unique(triple)) / max(1, len(triple)), 1 - len(set(lines)) / max(1, len(lines)), n / max(1, len(lines)), upper + lower, float(-(share * np.log(share)).sum()),
    ]


def with_features(docs: DataFrame) -> DataFrame:
    """Rows ``(doc_id, x)``, one per row of ``docs``."""

    @lean
    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for b in batches:
            yield pd.DataFrame({"doc_id": b["doc_id"], "x": [features(t) for t in b["text"]]})

    return map_frames(docs.select(F.col("doc_id").cast("long"), F.col("text").cast("string")), run, "doc_id long, x array<double>")


@dataclass
class PreferenceModel:
    """Additive scores over quantile steps of the features."""

    steps: list[np.ndarray]
    centre: np.ndarray
    scale: np.ndarray
    weights: np.ndarray
    cut: float = 0.0
    slope: float = 1.0

    def design(self, x: np.ndarray) -> np.ndarray:
        cols = [np.clip((x - self.centre) / self.scale, -4, 4)]
        cols += [(x[:, [k]] > s[None, :]).astype(float) for k, s in enumerate(self.steps) if len(s)]
        return np.hstack(cols)

    def raw(self, x: np.ndarray) -> np.ndarray:
        return self.design(x) @ self.weights

    def score(self, x: np.ndarray) -> np.ndarray:
        z = self.slope * (self.raw(x) - self.cut) + math.log(CUT / (1 - CUT))
        return 1 / (1 + np.exp(-np.clip(z, -40, 40)))


def _newton(d: np.ndarray, ridge: float, rounds: int = 12) -> np.ndarray:
    """Weights of logistic loss on differences: every row should come out positive."""
    w = np.zeros(d.shape[1])
    for _ in range(rounds):
        p = 1 / (1 + np.exp(np.clip(d @ w, -30, 30)))
        step = np.linalg.solve((d * (p * (1 - p))[:, None]).T @ d / len(d) + ridge * np.eye(len(w)), (p @ d) / len(d) - ridge * w)
        w += step
        if np.abs(step).max() < 1e-6:
            break
    return w


def learn(x: np.ndarray, good: np.ndarray, *, most_pairs: int = 20_000, ridge: float = 1e-3, seed: int = 3) -> PreferenceModel | None:
    """Bradley-Terry weights from feature rows and 0/1 labels; None without a pair."""
    if not good.any() or good.all():
        return None
    qs = np.linspace(0.05, 0.95, 10)
    steps = [np.unique(np.quantile(x[:, k], qs)) for k in range(x.shape[1])]
    scale = x.std(axis=0)
    model = PreferenceModel(steps, x.mean(axis=0), np.where(scale > 0, scale, 1), np.zeros(0))
    f = model.design(x)
    rng = np.random.default_rng(seed)
    yes, no = np.flatnonzero(good), np.flatnonzero(~good)
    model.weights = _newton(f[rng.choice(yes, most_pairs)] - f[rng.choice(no, most_pairs)], ridge)
    s = f @ model.weights
    model.cut = float(np.quantile(s, (~good).mean()))
    model.slope = 1 / max(1e-6, float(np.abs(s - model.cut).mean()))
    return model


def train(featured: DataFrame, labels: DataFrame, *, most_labels: int = 20_000) -> PreferenceModel | None:
    """Model from ``labels(doc_id, quality)``, at most ``most_labels`` rows, in hash order."""
    marked = labels.where("quality is not null and doc_id is not null").select(F.col("doc_id").cast("long"), F.col("quality").cast("int"))
    chosen = marked.orderBy(F.xxhash64("doc_id"), "doc_id", "quality").limit(most_labels)
    rows = featured.join(F.broadcast(chosen), "doc_id").select("doc_id", "x", "quality").collect()
    if not rows:
        return None
    rows = sorted(set((r.doc_id, tuple(r.x), r.quality) for r in rows))
    return learn(np.array([r[1] for r in rows]), np.array([r[2] == 1 for r in rows]))


def score(featured: DataFrame, model: PreferenceModel | None) -> DataFrame:
    """Rows ``(doc_id, score, predicted)``."""
    if model is None:
        return featured.select("doc_id", F.lit(0.5).alias("score"), F.lit(1).alias("predicted"))
    apply = F.pandas_udf(lambda x: pd.Series(model.score(np.stack(x.to_numpy())) if len(x) else []), "double")
    scored = featured.select("doc_id", apply("x").alias("score"))
    return scored.withColumn("predicted", (F.col("score") >= CUT).cast("int"))


def quality_scores(docs: DataFrame, labels: DataFrame, *, most_labels: int = 20_000) -> DataFrame:
    """Rows ``(doc_id, score, predicted)`` of all documents, learned from ``labels``."""
    featured = settle(with_features(docs))
    return score(featured, train(featured, labels, most_labels=most_labels))
