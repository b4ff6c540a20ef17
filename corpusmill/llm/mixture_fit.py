"""Mixing sources to target weights by subset-sum budget fitting.

Targets come from source totals: a budget is shared by weight, and what a
source cannot take (a document may come twice at most) goes to the others.
A source takes whole passes over its documents first. The rest of its budget
is met by a subset: documents are counted by exact length, most of the budget
is filled at an even rate over all lengths, and a bounded-knapsack dynamic
programme over what is left of the counts hits the last stretch exactly where
it can be hit. Which documents of a length are taken is settled by a seeded
hash; a crowded length is first narrowed down to one of 256 hash ranges.

Edge cases: null text has size 0 and is never taken; a null source is a source
of its own, last; an empty table gives no rows; equal hashes are ordered by
doc_id; repeated rows are taken as rows of their own.
"""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ._spark import settle

WEIGHTS = (3, 1, 2)
SEED = 20


def targets(sizes: dict[str | None, int], share: float = 1.5, most: int = 2, weights: tuple[int, ...] = WEIGHTS) -> dict[str | None, float]:
    """Words each source should give: shared by weight, ``most`` times its size at most."""
    names = sorted(sizes, key=lambda s: (s is None, s or ""))
    weight = {s: weights[i % len(weights)] for i, s in enumerate(names)}
    got: dict[str | None, float] = {}
    left, open_ = share * sum(sizes.values()), list(names)
    while open_:
        whole = sum(weight[s] for s in open_)
        over = [s for s in open_ if left * weight[s] / whole > most * sizes[s]]
        if not over:
            return got | {s: left * weight[s] / whole for s in open_}
        for s in over:
            got[s] = float(most * sizes[s])
        left -= sum(got[s] for s in over)
        open_ = [s for s in open_ if s not in over]
    return got


def _subset(lengths: np.ndarray, counts: np.ndarray, budget: int) -> np.ndarray:
    """How many of each length to take so that their sum comes as near to ``budget`` as can be."""
    if budget <= 0:
        return np.zeros(len(lengths), np.int64)
    most = min(int(lengths @ counts), budget + int(lengths.max()))
    order = np.lexsort((lengths,))[::-1]
    items = []
    for k in order:
        n, unit = int(min(counts[k], most // lengths[k])), 1
        while n > 0:
            items.append((k, min(unit, n)))
            n -= unit
            unit *= 2
    reach = np.zeros(most + 1, bool)
    reach[0] = True
    by = np.full(most + 1, -1, np.int32)
    for i, (k, times) in enumerate(items):
        w = int(lengths[k]) * times
        if w <= most:
            new = ~reach
            new[:w] = False
            new[w:] &= reach[: most + 1 - w]
            reach |= new
            by[new] = i
        if budget <= most and reach[budget]:
            break
    out = np.zeros(len(lengths), np.int64)
    sums = np.flatnonzero(reach)
    at = int(sums[np.argmin(np.abs(sums - budget))])
    while at:
        k, times = items[by[at]]
        out[k] += times
        at -= int(lengths[k]) * times
    return out


def fit_lengths(lengths: np.ndarray, counts: np.ndarray, budget: int) -> np.ndarray:
    """Documents to take of each length: an even rate first, then the dynamic programme."""
    total = int(lengths @ counts)
    if budget >= total:
        return counts.copy()
    longest = int(lengths.max())
    take = np.floor(counts * (max(0, budget - 8 * longest) / max(1, total))).astype(np.int64)
    left = budget - int(lengths @ take)
    # One more of each length, in a fixed order, until the rest is small enough for exact fitting.
    for k in np.random.default_rng(SEED).permutation(len(lengths)):
        if left <= 8 * longest:
            break
        if take[k] < counts[k] and lengths[k] <= left:
            take[k] += 1
            left -= int(lengths[k])
    return take + _subset(lengths, counts - take, left)


def mix(docs: DataFrame, *, share: float = 1.5, most: int = 2, weights: tuple[int, ...] = WEIGHTS, seed: int = SEED) -> DataFrame:
    """Rows ``(doc_id, source, size, source_size, target, copies)``.

    ``copies`` is how often the mix takes the document. The driver holds one
    total per source; counts by length stay distributed.
    """
    spark = docs.sparkSession
    sized = settle(
        docs.select(
            F.col("doc_id").cast("long"),
            F.col("source").cast("string"),
            F.coalesce(F.regexp_count(F.col("text").cast("string"), F.lit("[^\\x20\\x09-\\x0D]+")), F.lit(0)).cast("long").alias("size"),
            F.xxhash64(F.col("doc_id").cast("long"), F.lit(seed)).alias("h"),
        ).withColumn("slot", F.shiftrightunsigned("h", 56).cast("int"))
    )
    totals = {r.source: r.n for r in sized.groupBy("source").agg(F.sum("size").alias("n")).collect()}
    goal = targets(totals, share, most, weights)
    plan = [(s, n, float(goal[s]), round(goal[s]) // n if n else 0, round(goal[s]) % n if n else 0) for s, n in totals.items()]
    plan_df = spark.createDataFrame(plan, "p_source string, source_size long, target double, passes long, rest long")
    by_length = sized.where("size > 0").groupBy("source", "size").agg(F.count("*").alias("n"))

    def fit(part: pd.DataFrame) -> pd.DataFrame:
        part = part.sort_values("size")
        part["extra"] = fit_lengths(part["size"].to_numpy(), part["n"].to_numpy(), int(part["rest"].iloc[0]))
        return part[["source", "size", "extra"]]

    same = F.col("source").eqNullSafe(F.col("p_source"))
    extra = by_length.join(plan_df, same).select("source", "size", "n", "rest").groupBy("source").applyInPandas(fit, "source string, size long, extra long")
    e = extra.where("extra > 0").select(F.col("source").alias("e_source"), F.col("size").alias("e_size"), "extra")
    slots = sized.where("size > 0").groupBy("source", "size", "slot").agg(F.count("*").alias("n"))
    before = F.sum("n").over(Window.partitionBy("source", "size").orderBy("slot").rowsBetween(Window.unboundedPreceding, -1))
    quota = (
        slots.withColumn("before", F.coalesce(before, F.lit(0)))
        .join(e, F.col("source").eqNullSafe(F.col("e_source")) & (F.col("size") == F.col("e_size")))
        .select(
            F.col("source").alias("q_source"), F.col("size").alias("q_size"), F.col("slot").alias("q_slot"), "n",
            F.greatest(F.lit(0), F.least(F.col("n"), F.col("extra") - F.col("before"))).alias("quota"),
        )
        .where("quota > 0")
    )
    found = sized.join(
        quota, F.col("source").eqNullSafe(F.col("q_source")) & (F.col("size") == F.col("q_size")) & (F.col("slot") == F.col("q_slot")), "left"
    )
    # Only the one range of a length that the quota cuts through needs an order.
    cut = found.where("quota < n").withColumn("rank", F.row_number().over(Window.partitionBy("source", "size", "slot").orderBy("h", "doc_id")))
    rest = found.where("quota is null or quota >= n").withColumn("rank", F.lit(1))
    picked = cut.unionByName(rest).withColumn("one", F.when(F.col("rank") <= F.coalesce("quota", F.lit(0)), 1).otherwise(0))
    return picked.join(plan_df, same).select(
        "doc_id", "source", "size", "source_size", "target", F.when(F.col("size") > 0, F.col("passes") + F.col("one")).otherwise(0).cast("long").alias("copies")
    )
