"""Connected components of an edge list by alternating large-star and small-star."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ._spark import release, settle


#: Edges that one task handles: up to so many, checked by a count, a round needs no shuffle.
MOST_ALONE = 1_000_000


def _union(x: DataFrame, y: DataFrame, alone: bool) -> DataFrame:
    both = x.unionByName(y)
    return both.coalesce(1) if alone else both


def _large_star(edges: DataFrame, alone: bool) -> DataFrame:
    """Every node hands the smallest id around it to its larger neighbours."""
    both = _union(edges, edges.select(F.col("b").alias("a"), F.col("a").alias("b")), alone)
    low = both.groupBy("a").agg(F.least(F.min("b"), F.col("a")).alias("low"))
    return (
        both.join(low, "a")
        .where(F.col("b") > F.col("a"))
        .select(F.col("b").alias("a"), F.col("low").alias("b"))
        .where("a <> b")
    )


def _small_star(edges: DataFrame, alone: bool) -> DataFrame:
    """Every node hangs itself and its smaller neighbours under the smallest of them."""
    down = edges.select(F.greatest("a", "b").alias("a"), F.least("a", "b").alias("b"))
    low = down.groupBy("a").agg(F.min("b").alias("low"))
    moved = down.join(low, "a").select(F.col("b").alias("a"), F.col("low").alias("b"))
    return _union(moved, low.select("a", F.col("low").alias("b")), alone).where("a <> b").distinct()


def _settled(edges: DataFrame, alone: bool) -> bool:
    """Whether every node hangs under one head and no head hangs under another: then nothing moves any more."""
    ends = edges.select(F.col("a").alias("node"), F.lit(1).alias("up"), F.lit(0).alias("head"))
    ends = _union(ends, edges.select(F.col("b").alias("node"), F.lit(0).alias("up"), F.lit(1).alias("head")), alone)
    return ends.groupBy("node").agg((F.sum("up") + F.max("head")).alias("n"), F.max("up").alias("up")).where("up = 1 and n > 1").count() == 0


def connected_components(edges: DataFrame, most_alone: int = MOST_ALONE) -> DataFrame:
    """Rows ``(node, component)`` for every node of ``edges(a, b)``.

    ``component`` is the smallest id reachable. The driver reads one count per
    round, never edges; each round is checkpointed. Rounds are logarithmic in
    the size of the largest component, and stars need one. ``most_alone`` edges
    at most are handled in one task instead of hundreds of tiny ones, with the
    same results. Null ends and loops are ignored; an empty edge list gives an
    empty result.
    """
    now = edges.select("a", "b").where("a is not null and b is not null and a <> b")
    alone = now.count() <= most_alone
    while True:
        now = settle(_small_star(_large_star(now, alone), alone))
        if not alone:
            release(edges.sparkSession)
        if _settled(now, alone):
            break
    heads = now.select(F.col("b").alias("node"), F.col("b").alias("component"))
    heads = (heads.coalesce(1) if alone else heads).distinct()
    return _union(now.select(F.col("a").alias("node"), F.col("b").alias("component")), heads, alone)
