"""MinHash near-deduplication: signatures, bands, verified links, components.

Texts are lower-cased over A-Z, cut into words at space and \\x09-\\x0D, and
turned into a set of word shingles. Universal hash minima of the set form a
signature; bands of it are bucket keys. Copies with equal sets collapse to the
smallest id first, so large groups of copies cost one row from there on.

Within a bucket no list of all pairs is made. Every member is first compared
with the bucket's smallest id; what is linked so far is put into components.
In two more rounds each bucket draws a pivot of its own, and members in other
components than the pivot's are compared with it. What is then still apart in a
bucket is compared block by block inside the tasks, and only confirmed links
leave them. Two documents already in one component need no further link between
them, so nothing is lost.

Edge cases: null or empty text has an empty set and is linked with nothing;
fewer words than a shingle make one shingle of all words; a null doc_id keeps
a row with a null component; repeated rows are one node and each is returned;
extra columns are ignored.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator

import numpy as np
import pandas as pd
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ._spark import join_hot, lean, map_frames, release, settle
from .components import connected_components

HASHES, BANDS = 128, 32  # four rows a band: a pair at 0.8 is missed with probability 5e-8
SLACK = 0.25  # seven standard deviations of a signature's estimate at 0.8: a pair is missed with probability 1e-12
BLOCK = 512

_MUL = np.uint64(0x9E3779B97F4A7C15)


def _mix(x: np.ndarray) -> np.ndarray:
    """Finaliser that spreads every input bit over 64 bits."""
    x = (x ^ (x >> np.uint64(30))) * np.uint64(0xBF58476D1CE4E5B9)
    x = (x ^ (x >> np.uint64(27))) * np.uint64(0x94D049BB133111EB)
    return x ^ (x >> np.uint64(31))


class _WordHash(dict):
    """Word to 64-bit hash, filled on demand."""

    def __missing__(self, word: bytes) -> int:
        if len(self) > 200_000:
            self.clear()
        self[word] = value = xxhash.xxh3_64_intdigest(word)
        return value


def shingle_set(text: str | None, size: int, words: _WordHash) -> np.ndarray:
    """Sorted distinct 64-bit hashes of the word shingles of a whole text."""
    parts = text.encode("utf-8").lower().split() if text else []
    if not parts:
        return np.empty(0, np.uint64)
    h = np.fromiter(map(words.__getitem__, parts), np.uint64, len(parts))
    size = min(size, len(h))
    out = np.zeros(len(h) - size + 1, np.uint64)
    for k in range(size):
        out = _mix(out * _MUL + h[k : len(h) - size + 1 + k] + np.uint64(k + 1))
    return np.unique(out)


def _constants(count: int, seed: int) -> tuple[np.ndarray, np.ndarray]:
    rng = np.random.default_rng(seed)
    a, b = rng.integers(0, 2**31, (2, count), dtype=np.uint32) * np.uint32(2) + np.uint32(1)
    return a, b


def signature(shingles: np.ndarray, a: np.ndarray, b: np.ndarray) -> np.ndarray:
    """Minima of multiply-add hashes, in blocks so that long texts stay small."""
    x = (shingles >> np.uint64(32)).astype(np.uint32)
    best = np.full(len(a), 2**32 - 1, np.uint32)
    for at in range(0, len(x), 1024):
        values = a[:, None] * x[None, at : at + 1024]
        values += b[:, None]
        np.minimum(best, values.min(axis=1), out=best)
    return best


def _band_keys(sig: np.ndarray, bands: int) -> np.ndarray:
    rows = sig.astype(np.uint64).reshape(bands, -1)
    key = np.arange(1, bands + 1, dtype=np.uint64)
    for k in range(rows.shape[1]):
        key = _mix(key * _MUL + rows[:, k])
    return key.view(np.int64)


def fingerprints(docs: DataFrame, shingle: int, hashes: int, bands: int, seed: int) -> DataFrame:
    """One narrow pass over the texts: set size, set digest, signature, band keys."""

    @lean
    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        a, b = _constants(hashes, seed)
        words = _WordHash()
        for batch in batches:
            sizes, digests, sigs, keys = [], [], [], []
            for text in batch["text"]:
                s = shingle_set(text, shingle, words)
                sizes.append(len(s))
                if len(s):
                    sig = signature(s, a, b)
                    digests.append(hashlib.md5(s.tobytes()).digest())
                    sigs.append(sig.tobytes())
                    keys.append(_band_keys(sig, bands))
                else:
                    digests.append(None), sigs.append(None), keys.append(None)
            yield pd.DataFrame({"doc_id": batch["doc_id"], "n_shingles": sizes, "digest": digests, "sig": sigs, "keys": keys})

    return map_frames(
        docs.select(F.col("doc_id").cast("long"), F.col("text").cast("string")), run, "doc_id long, n_shingles long, digest binary, sig binary, keys array<long>"
    )


def _likely(pairs: DataFrame, sigs: DataFrame, percent: int) -> DataFrame:
    """Pairs whose set sizes and signatures do not rule the link out."""
    side = lambda x: sigs.select(F.col("doc_id").alias(x), F.col("n_shingles").alias(f"n_{x}"), F.col("sig").alias(f"sig_{x}"))
    joined = (
        pairs.join(side("a"), "a")
        .join(side("b"), "b")
        .where(F.least("n_a", "n_b") * 100 >= F.greatest("n_a", "n_b") * percent)
    )

    @lean
    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for p in batches:
            if not len(p):
                continue
            x = np.frombuffer(b"".join(p["sig_a"]), np.uint32).reshape(len(p), -1)
            y = np.frombuffer(b"".join(p["sig_b"]), np.uint32).reshape(len(p), -1)
            yield p.loc[(x == y).mean(axis=1) >= percent / 100 - SLACK, ["a", "b"]]

    return joined.select("a", "b", "sig_a", "sig_b").mapInPandas(run, "a long, b long")


def _linked(s: np.ndarray, t: np.ndarray, percent: int) -> bool:
    both = len(np.intersect1d(s, t, assume_unique=True))
    return both > 0 and 100 * both >= percent * (len(s) + len(t) - both)


def _confirmed(pairs: DataFrame, texts: DataFrame, shingle: int, percent: int) -> DataFrame:
    """Links of ``pairs`` that hold on the full shingle sets of ``texts``."""

    @lean
    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        words, seen = _WordHash(), {}
        for p in batches:
            keep = []
            for a, x, y in zip(p["a"], p["text_a"], p["text_b"], strict=True):
                if a not in seen:
                    if len(seen) > 64:
                        seen.clear()
                    seen[a] = shingle_set(x, shingle, words)
                keep.append(_linked(seen[a], shingle_set(y, shingle, words), percent))
            yield p.loc[keep, ["a", "b"]]

    return settle(
        pairs.join(texts.select(F.col("doc_id").alias("b"), F.col("text").alias("text_b")), "b")
        .join(texts.select(F.col("doc_id").alias("a"), F.col("text").alias("text_a")), "a")
        .select("a", "b", "text_a", "text_b")
        .mapInPandas(run, "a long, b long")
    )


def _named(members: DataFrame, labels: DataFrame) -> DataFrame:
    """Members of buckets that hold several components, with their component."""
    named = members.join(labels.withColumnRenamed("node", "doc_id"), "doc_id", "left").select(
        "key", "doc_id", F.coalesce("component", "doc_id").alias("component"), "n"
    )
    split = named.groupBy("key").agg(F.min("component").alias("x"), F.max("component").alias("y")).where("x <> y").select("key")
    return settle(named.where("n > 2").join(split, "key", "left_semi"))


def _to_pivots(named: DataFrame, *salts: int) -> DataFrame:
    """Pairs of each bucket's own random pivots, one for each salt, with the members outside their component."""
    drawn = [F.min_by(F.struct("doc_id", "component"), F.xxhash64("key", "doc_id", F.lit(salt))) for salt in salts]
    pivots = named.groupBy("key").agg(F.array(*drawn).alias("drawn"))
    apart = named.join(pivots, "key").withColumn("p", F.explode(F.array_distinct("drawn"))).where("component <> p.component")
    return apart.select(F.least("doc_id", "p.doc_id").alias("a"), F.greatest("doc_id", "p.doc_id").alias("b")).distinct()


def _links_in_blocks(named: DataFrame, texts: DataFrame, shingle: int, percent: int) -> DataFrame:
    """Confirmed links across the components of a bucket, of any size.

    Members outside a bucket's largest component meet all members, block by
    block, on full sets. A task passes on as many links as join its components.
    """
    sizes = named.groupBy("key", "component").agg(F.count("*").alias("m"))
    main = sizes.groupBy("key").agg(F.max_by("component", F.struct("m", "component")).alias("main"), F.sum("m").alias("n"), F.max("m").alias("most"))
    of = named.select("key", "doc_id", "component").join(main, "key")
    few, all_ = (F.ceil(x / BLOCK).cast("int") for x in (F.col("n") - F.col("most"), F.col("n")))
    block = lambda blocks: F.pmod(F.xxhash64("doc_id"), F.greatest(blocks, F.lit(1))).cast("int")
    spread = lambda blocks: F.explode(F.sequence(F.lit(0), F.greatest(blocks, F.lit(1)) - 1))
    cols = ["key", "lo", "hi", "outer", "doc_id", "component"]
    outer = of.where("component <> main").withColumn("lo", block(few)).withColumn("hi", spread(all_)).withColumn("outer", F.lit(True))
    every = of.withColumn("hi", block(all_)).withColumn("lo", spread(few)).withColumn("outer", F.lit(False))
    dealt = outer.select(cols).unionByName(every.select(cols)).join(texts, "doc_id")

    def compare(group: pd.DataFrame) -> pd.DataFrame:
        words, root, found = _WordHash(), {}, []

        def find(x):
            while root.setdefault(x, x) != x:
                x = root[x]
            return x

        out, rest = group[group["outer"]], group[~group["outer"]]
        if not len(out) or not len(rest):
            return pd.DataFrame([], columns=["a", "b"], dtype="int64")
        # All sets of the block in one flat array: an intersection with each is one lookup and one sum.
        sets = [shingle_set(t, shingle, words) for t in rest["text"]]
        sizes = np.array([len(x) for x in sets])
        known, codes = np.unique(np.concatenate(sets), return_inverse=True)
        starts = np.cumsum(sizes) - sizes
        ids, comp = rest["doc_id"].to_numpy(), rest["component"].to_numpy()
        for k, c, t in zip(out["doc_id"], out["component"], out["text"], strict=True):
            own = shingle_set(t, shingle, words)
            at = np.minimum(np.searchsorted(known, own), len(known) - 1)
            hit = np.zeros(len(known), np.int64)
            hit[at[known[at] == own]] = 1
            both = np.add.reduceat(hit[codes], starts)
            for j in np.flatnonzero((100 * both >= percent * (sizes + len(own) - both)) & (comp != c)):
                x, y = find(c), find(comp[j])
                if x != y:
                    root[x] = y
                    found.append((min(k, ids[j]), max(k, ids[j])))
        return pd.DataFrame(found, columns=["a", "b"], dtype="int64")

    return dealt.groupBy("key", "lo", "hi").applyInPandas(compare, "a long, b long")


def near_duplicates(
    docs: DataFrame, *, shingle: int = 5, percent: int = 80, hashes: int = HASHES, bands: int = BANDS, seed: int = 7
) -> DataFrame:
    """Rows ``(doc_id, n_shingles, component_id, kept)``, one per row of ``docs``.

    Documents are linked when ``100 * intersection >= percent * union`` of their
    shingle sets. ``component_id`` is the smallest doc_id reachable.
    """
    spark = docs.sparkSession
    prints = settle(fingerprints(docs, shingle, hashes, bands, seed))
    sets = prints.where("digest is not null and doc_id is not null")
    rows = sets.count()
    heads = sets.groupBy("digest").agg(F.min("doc_id").alias("head"), F.count("*").alias("n")).where("n > 1")
    copies = join_hot(sets.select("digest", "doc_id"), heads, "digest", rows)
    same = settle(copies.where("doc_id <> head").select("doc_id", "head").distinct())
    sigs = sets.join(same, "doc_id", "left_anti").select("doc_id", "n_shingles", "sig", "keys").dropDuplicates(["doc_id", "sig"])
    entries = sigs.select("doc_id", F.explode("keys").alias("key"))
    buckets = entries.groupBy("key").agg(F.min("doc_id").alias("first"), F.count("*").alias("n")).where("n > 1")
    members = settle(join_hot(entries.select("key", "doc_id"), buckets, "key", rows * bands).select("key", "doc_id", "first", "n"))
    del entries, buckets, heads, copies  # what nobody refers to any more frees its shuffle files at the next release
    stars = members.where("doc_id <> first").select(F.col("first").alias("a"), F.col("doc_id").alias("b")).distinct()
    slim = docs.select(F.col("doc_id").cast("long"), F.col("text").cast("string"))
    texts = settle(slim.join(members.select("doc_id").distinct(), "doc_id", "left_semi").dropDuplicates(["doc_id", "text"]))
    sigs = settle(sigs.select("doc_id", "n_shingles", "sig").join(members.select("doc_id").distinct(), "doc_id", "left_semi"))
    release(spark)
    links = _confirmed(settle(_likely(stars, sigs, percent)), texts, shingle, percent)
    del stars
    release(spark)
    labels = settle(connected_components(links))
    release(spark)
    for salt in (1, 2):
        named = _named(members, labels)
        if named.isEmpty():
            break
        links = links.unionByName(_confirmed(settle(_likely(_to_pivots(named, salt), sigs, percent)), texts, shingle, percent))
        del named
        release(spark)
        labels = settle(connected_components(links))
        release(spark)
    named = _named(members, labels)
    if not named.isEmpty():
        last = settle(_links_in_blocks(named, texts, shingle, percent))
        release(spark)
        labels = settle(connected_components(links.unionByName(last)))
        del last
    del named, links, texts, members, sigs, sets
    release(spark)
    return (
        prints.select("doc_id", "n_shingles")
        .join(same, "doc_id", "left")
        .withColumn("node", F.coalesce("head", "doc_id"))
        .join(labels, "node", "left")
        .select("doc_id", "n_shingles", F.coalesce("component", "node").alias("component_id"))
        .withColumn("kept", F.col("doc_id") == F.col("component_id"))
    )
