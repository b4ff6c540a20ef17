"""Exact deduplication of documents and of paragraphs within a scope."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..functions import text as T


def snapshot(source: Column) -> Column:
    """Snapshot of a source: five sources to one."""
    return F.floor(F.regexp_extract(source, "([0-9]+)$", 1).cast("int") / 5).cast("int")


def dedup_exact(df: DataFrame, id: str = "doc_id", text: str = "text") -> DataFrame:
    """One row per distinct text: the smallest id and the number of copies. Only digests are shuffled."""
    return df.select(id, F.sha2(text, 256).alias("digest")).groupBy("digest").agg(F.min(id).alias(id), F.count("*").alias("copies")).select(id, "copies")


def normalized(paragraph: Column) -> Column:
    """Lower case, digits as 0, no punctuation: the looser key of a paragraph."""
    return F.regexp_replace(F.regexp_replace(F.lower(paragraph), "[0-9]", "0"), r"[^\p{L}0-9 ]", "")


def dedup_paragraphs(df: DataFrame, *, scope: tuple[str, ...] = (), keep: str = "first", min_df: int = 2, key=None) -> DataFrame:
    """Drop paragraphs that repeat within ``scope`` and put the rest together again.

    Adds ``text_dedup``, ``n_kept`` and ``n_removed`` to every row. ``keep`` is
    ``first`` (by id and position) or ``none``; ``scope`` names columns, empty
    for all rows. Digests and positions are shuffled, texts only once, by id.
    """
    parts = T.paragraphs(F.col("text"))
    key = key or (lambda p: p)
    at = df.select("doc_id", *scope, F.posexplode(parts).alias("pos", "p")).select("doc_id", *scope, "pos", F.md5(key(F.col("p"))).alias("h"))
    groups = at.groupBy(*scope, "h").agg(F.min(F.struct("doc_id", "pos")).alias("first"), F.count("*").alias("n")).where(F.col("n") >= min_df)
    hit = at.join(groups, [*scope, "h"])
    if keep == "first":
        hit = hit.where(F.struct("doc_id", "pos") != F.col("first"))
    gone = hit.groupBy("doc_id").agg(F.collect_set("pos").alias("gone"))
    out = df.join(gone, "doc_id", "left").withColumn("gone", F.coalesce("gone", F.array().cast("array<int>"))).withColumn("parts", parts)
    left = F.filter("parts", lambda p, i: ~F.array_contains("gone", i))
    return out.select(
        *df.columns,
        F.array_join(left, "\n").alias("text_dedup"),
        (F.size("parts") - F.size("gone")).cast("long").alias("n_kept"),
        F.size("gone").cast("long").alias("n_removed"),
    )
