"""MinHash-LSH near-duplicate removal without a graph, and what it is compared with."""

from __future__ import annotations

import hashlib
import zlib
from collections.abc import Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
import regex
import xxhash
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..functions.text import py_hash60
from ..session import scratch

PRIME = 2**61 - 1
BANDS, ROWS, NGRAM = 9, 13, 5
_TOKEN = regex.compile(r"[\p{L}\p{N}]+")


def constants(count: int) -> tuple[np.ndarray, np.ndarray]:
    """Multipliers and offsets of the permutations, from md5 so that SQL can say the same."""
    a = [py_hash60(f"a:{i}") + 1 for i in range(count)]
    return np.array(a, np.uint64), np.array([py_hash60(f"b:{i}") for i in range(count)], np.uint64)


def shingles(text: str | None, n: int = NGRAM) -> list[str]:
    """Distinct word n-grams, lower case, letters and digits; fewer words make one shingle of all."""
    w = _TOKEN.findall((text or "").lower())
    if not w:
        return []
    m = min(n, len(w))
    return list(dict.fromkeys(" ".join(w[i : i + m]) for i in range(len(w) - m + 1)))


def _times(a: np.ndarray, h: np.ndarray, b: np.ndarray) -> np.ndarray:
    """(a * h + b) mod 2^61 - 1 for a, h below 2^61, in halves of 31 bits."""
    low, p = np.uint64(2**31 - 1), np.uint64(PRIME)
    a1, a0, h1, h0 = a >> np.uint64(31), a & low, h >> np.uint64(31), h & low
    mid = a1 * h0 + a0 * h1
    x = np.uint64(2) * (a1 * h1) + (mid >> np.uint64(30)) + ((mid & np.uint64(2**30 - 1)) << np.uint64(31))
    x = (x & p) + (x >> np.uint64(61)) + a0 * h0
    x = (x & p) + (x >> np.uint64(61)) + b
    x = (x & p) + (x >> np.uint64(61))
    return np.where(x >= p, x - p, x)


def signature(text: str | None, a: np.ndarray, b: np.ndarray, n: int = NGRAM) -> np.ndarray | None:
    found = shingles(text, n)
    if not found:
        return None
    h = np.fromiter(map(py_hash60, found), np.uint64, len(found))
    best = np.full(len(a), PRIME, np.uint64)
    for at in range(0, len(h), 512):
        np.minimum(best, _times(a[:, None], h[None, at : at + 512], b[:, None]).min(axis=1), out=best)
    return best


def minhash_signatures(df: DataFrame, num_perm: int = BANDS * ROWS, ngram: int = NGRAM) -> DataFrame:
    """Rows ``(doc_id, sig)``; ``sig`` is null for a text without a shingle. The text goes no further."""

    keep = ["doc_id", *[c for c in df.columns if c == "snapshot"]]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        a, b = constants(num_perm)
        for batch in batches:
            sigs = [signature(x, a, b, ngram) for x in batch.column("text").to_pylist()]
            values = pa.array([None if s is None else s.astype(np.int64) for s in sigs], pa.list_(pa.int64()))
            yield pa.RecordBatch.from_arrays([*(batch.column(c) for c in keep), values], [*keep, "sig"])

    kinds = ", ".join(f"{c} {df.schema[c].dataType.simpleString()}" for c in keep)
    return df.select(*keep, F.col("text").cast("string")).mapInArrow(run, f"{kinds}, sig array<long>")


def lsh_bands(signatures: DataFrame, bands: int = BANDS, rows: int = ROWS) -> DataFrame:
    """Rows ``(doc_id, band, key)``: md5 of each band's values joined by commas."""
    keys = [F.struct(F.lit(k).alias("band"), F.md5(F.array_join(F.slice("sig", k * rows + 1, rows).cast("array<string>"), ",")).alias("key")) for k in range(bands)]
    others = [c for c in signatures.columns if c != "sig"]
    return signatures.where("sig is not null").select(*others, F.explode(F.array(*keys)).alias("x")).select(*others, "x.band", "x.key")


def checkpointed(df: DataFrame) -> DataFrame:
    """``df`` in the folder of ``spark.checkpoint.dir``, or a temporary one where that is unset, as in tests."""
    spark = df.sparkSession
    if spark.sparkContext.getCheckpointDir() is None:
        spark.sparkContext.setCheckpointDir(scratch(spark))
    return df.checkpoint()


def dedup_lsh(bands: DataFrame, scope: tuple[str, ...] = ()) -> DataFrame:
    """Rows ``(doc_id, witness)`` to drop: a document that shares a bucket with a smaller id, and the smallest such.

    One map-side summed aggregate and one join of ids; no graph, no iteration.
    The narrow band rows are checkpointed, so that signatures are computed once.
    """
    bands = checkpointed(bands)
    by = [*scope, "band", "key"]
    least = bands.groupBy(*by).agg(F.min("doc_id").alias("witness"), F.count("*").alias("n")).where("n > 1")
    return bands.join(least, by).where("doc_id <> witness").groupBy("doc_id").agg(F.min("witness").alias("witness"))


def candidate_pairs(bands: DataFrame) -> DataFrame:
    """Unordered pairs that share a bucket, with the number of shared bands (a measure on small inputs)."""
    other = bands.select(F.col("doc_id").alias("b"), "band", "key")
    return bands.withColumnRenamed("doc_id", "a").join(other, ["band", "key"]).where("a < b").groupBy("a", "b").agg(F.count("*").alias("bands"))


def dedup_components(pairs: DataFrame, rounds: int = 100) -> DataFrame:
    """Rows ``(doc_id, component)``: minimum labels spread along ``pairs(a, b)`` until nothing changes.

    The graph variant the paper decided against. Labels also jump to the label
    of their label, so chains settle in logarithmic rounds; the driver reads one
    counter a round, and every round is checkpointed.
    """
    both = checkpointed(pairs.select("a", "b").unionByName(pairs.select(F.col("b").alias("a"), F.col("a").alias("b"))).distinct())
    labels = both.groupBy("a").agg(F.least(F.min("b"), F.col("a")).alias("label")).checkpoint()
    for _ in range(rounds):
        near = both.join(labels.select(F.col("a").alias("b"), "label"), "b").groupBy("a").agg(F.min("label").alias("seen"))
        step = labels.join(near, "a").select("a", F.least("label", "seen").alias("label"), F.col("label").alias("old"))
        jump = labels.select(F.col("a").alias("label"), F.col("label").alias("further"))
        step = step.join(jump, "label", "left").select("a", F.least("label", F.coalesce("further", "label")).alias("label"), "old").checkpoint()
        changed = step.where("label <> old").count()
        labels = step.select("a", "label")
        if not changed:
            break
    return labels.select(F.col("a").alias("doc_id"), F.col("label").alias("component"))


#: Counters of a sketch of how often shingles occur, in chunks; shingles that exchange tasks hold; sets that a block holds.
COUNTERS, CHUNK, EXCHANGED, BLOCK_SETS = 2**18, 2**12, 4_000_000, 2_000
_MUL = np.uint64(0x9E3779B97F4A7C15)


class _WordHash(dict):
    """Word to 64-bit hash, filled on demand."""

    def __missing__(self, word: str) -> int:
        if len(self) > 200_000:
            self.clear()
        self[word] = value = xxhash.xxh3_64_intdigest(word.encode("utf-8", "surrogatepass"))
        return value


def _mix(x: np.ndarray) -> np.ndarray:
    x = (x ^ (x >> np.uint64(30))) * np.uint64(0xBF58476D1CE4E5B9)
    x = (x ^ (x >> np.uint64(27))) * np.uint64(0x94D049BB133111EB)
    return x ^ (x >> np.uint64(31))


def shingle_set(text: str | None, n: int, words: _WordHash) -> np.ndarray:
    """``shingles`` as sorted distinct 64-bit hashes."""
    w = _TOKEN.findall((text or "").lower())
    if not w:
        return np.empty(0, np.uint64)
    h = np.fromiter(map(words.__getitem__, w), np.uint64, len(w))
    n = min(n, len(h))
    out = np.zeros(len(h) - n + 1, np.uint64)
    for k in range(n):
        out = _mix(out * _MUL + h[k : len(h) - n + 1 + k] + np.uint64(k + 1))
    return np.unique(out)


def _key(digest: bytes) -> int:
    return int.from_bytes(digest[:8], "little", signed=True)


def _classed(df: DataFrame, ngram: int) -> DataFrame:
    """Rows ``(doc_id, n, digest, key, least)`` of texts with a shingle, and rows ``(chunk, counts)`` of each task's sketch."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        words, seen = _WordHash(), np.zeros(COUNTERS, np.int64)
        for batch in batches:
            rows = []
            for i, text in zip(batch.column("doc_id").to_pylist(), batch.column("text").to_pylist(), strict=True):
                s = shingle_set(text, ngram, words)
                if len(s):
                    np.add.at(seen, (s & np.uint64(COUNTERS - 1)).astype(np.int64), 1)
                    digest = hashlib.md5(s.tobytes()).digest()
                    rows.append((i, len(s), digest, _key(digest), int(s[0].view(np.int64)), None, None))
            yield _batch(rows, kinds)
        yield _batch([(None, None, None, None, None, k, zlib.compress(part.tobytes(), 1)) for k, part in enumerate(seen.reshape(-1, CHUNK)) if part.any()], kinds)

    kinds = {"doc_id": pa.int64(), "n": pa.int64(), "digest": pa.binary(), "key": pa.int64(), "least": pa.int64(), "chunk": pa.int32(), "counts": pa.binary()}
    texts = df.select(F.col("doc_id").cast("long"), F.col("text").cast("string"))
    return texts.mapInArrow(run, "doc_id long, n long, digest binary, key long, least long, chunk int, counts binary")


def _batch(rows: list[tuple], kinds: dict[str, pa.DataType]) -> pa.RecordBatch:
    return pa.RecordBatch.from_arrays([pa.array([r[i] for r in rows], t) for i, t in enumerate(kinds.values())], list(kinds))


def _levels(sketches: DataFrame) -> np.ndarray:
    """A byte a counter, higher where its shingles occur more often: the order of a set's shingles, never which ones count."""

    def add(group: pd.DataFrame) -> pd.DataFrame:
        total = sum(np.frombuffer(zlib.decompress(c), np.int64) for c in group["counts"])
        level = np.floor(np.log2(total + 1.0) * 6).clip(0, 255).astype(np.uint8)
        return pd.DataFrame({"chunk": group["chunk"].iloc[:1], "level": [level.tobytes()]})

    levels = np.zeros((COUNTERS // CHUNK, CHUNK), np.uint8)
    for r in sketches.groupBy("chunk").applyInPandas(add, "chunk int, level binary").collect():
        levels[r.chunk] = np.frombuffer(r.level, np.uint8)
    return levels.reshape(-1)


def _prefixes(df: DataFrame, levels: np.ndarray, parts: int, tenths: int, ngram: int) -> DataFrame:
    """Rows ``(part, keys, sizes, counts, heads)``: the rare shingles of many sets, dealt by hash, 32 bits of each."""
    shared = df.sparkSession.sparkContext.broadcast(levels)

    def packed(found: list[tuple[int, int, np.ndarray]]) -> Iterator[tuple]:
        lengths = np.array([len(h) for *_, h in found])
        h, doc = np.concatenate([h for *_, h in found]), np.repeat(np.arange(len(found)), lengths)
        key, size = (np.array([f[i] for f in found], t) for i, t in ((0, np.int64), (1, np.int32)))
        at = ((h >> np.uint64(32)) % np.uint64(parts)).astype(np.int64)
        order = np.argsort(at, kind="stable")
        ends = np.searchsorted(at[order], np.arange(parts + 1))
        for k in range(parts):
            mine = order[ends[k] : ends[k + 1]]
            if len(mine):
                docs, count = np.unique(doc[mine], return_counts=True)
                yield k, key[docs].tobytes(), size[docs].tobytes(), count.astype(np.int32).tobytes(), h[mine].astype(np.uint32).tobytes()

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        words, level, found, held = _WordHash(), shared.value, [], 0
        for batch in batches:
            for text in batch.column("text").to_pylist():
                s = shingle_set(text, ngram, words)
                if len(s):
                    rare = np.argsort(level[(s & np.uint64(COUNTERS - 1)).astype(np.int64)], kind="stable")[: len(s) + 1 + (-len(s) * tenths // 10)]
                    found.append((_key(hashlib.md5(s.tobytes()).digest()), len(s), s[np.sort(rare)]))
                    held += len(rare)
                if held > EXCHANGED:
                    yield _batch(list(packed(found)), kinds)
                    found, held = [], 0
        if found:
            yield _batch(list(packed(found)), kinds)

    kinds = {"part": pa.int32(), "keys": pa.binary(), "sizes": pa.binary(), "counts": pa.binary(), "heads": pa.binary()}
    return df.select(F.col("text").cast("string")).mapInArrow(run, "part int, keys binary, sizes binary, counts binary, heads binary")


def _meet(tenths: int):
    """Pairs of classes whose rare shingles meet in a part, and how many do."""

    def run(group: pd.DataFrame) -> pd.DataFrame:
        one = lambda c, t: np.concatenate([np.frombuffer(x, t) for x in group[c]])
        who = np.empty(sum(len(x) for x in group["keys"]) // 8, [("n", np.int32), ("key", np.int64)])
        who["n"], who["key"] = one("sizes", np.int32), one("keys", np.int64)
        who, at = np.unique(who, return_inverse=True)  # by size, so that a run of members can stop at those too long
        rows = np.unique(one("heads", np.uint32).astype(np.uint64) << np.uint64(32) | np.repeat(at, one("counts", np.int32)).astype(np.uint64))
        h, d = rows >> np.uint64(32), (rows & np.uint64(2**32 - 1)).astype(np.int64)
        n = who["n"].astype(np.int64)
        left, kept, size, k = np.arange(len(h)), [(np.empty(0, np.int64), np.empty(0, np.int64))], 0, 0

        def merged() -> tuple[np.ndarray, np.ndarray]:
            pair, c = map(np.concatenate, zip(*kept, strict=True))
            pair, back = np.unique(pair, return_inverse=True)
            return pair, np.bincount(back, c, len(pair)).astype(np.int64)

        while len(left):
            k += 1
            left = left[left + k < len(h)]
            left = left[(h[left] == h[left + k]) & (n[d[left]] * 10 >= n[d[left + k]] * tenths)]
            kept.append((d[left] << 32 | d[left + k], np.ones(len(left), np.int64)))
            size += len(left)
            if size > 2**22:
                kept = [merged()]
                size = 0
        pair, c = merged()
        a, b = who[pair >> 32], who[pair & (2**32 - 1)]
        return pd.DataFrame({"ka": a["key"], "na": a["n"], "kb": b["key"], "nb": b["n"], "c": c})

    return run


def _shared(pairs: pd.DataFrame, sets: pd.DataFrame) -> pd.DataFrame:
    of = {i: np.frombuffer(s, np.uint64) for i, s in zip(sets["doc_id"], sets["s"], strict=True)}
    both = [len(np.intersect1d(of[a], of[b], assume_unique=True)) for a, b in zip(pairs["a"], pairs["b"], strict=True)]
    return pairs[["a", "b", "na", "nb"]].assign(both=both)


def rows_of(df: DataFrame, ids: DataFrame) -> DataFrame:
    """Rows of ``df`` with a ``doc_id`` of ``ids``; up to two million ids are broadcast, so that no text is shuffled."""
    return df.join(F.broadcast(ids) if ids.count() <= 2_000_000 else ids, "doc_id", "left_semi")


def jaccard_classes(df: DataFrame, tenths: int = 5, ngram: int = NGRAM) -> tuple[DataFrame, DataFrame]:
    """Rows ``(doc_id, rep, n, size)`` of texts by equal sets, and ``(a, b, na, nb, both)`` of classes of a similarity of at least ``tenths``.

    A set is ordered from rare to common shingles by a sketch of counts. Two
    sets that are similar enough share a shingle among the first
    ``n - ceil(n * tenths / 10) + 1`` of each, so only those are exchanged, in
    four bytes. How many of them two classes share bounds what they can share in
    all; what the bound leaves is decided on whole sets. Hashes of 32 bits may
    bring pairs together in vain, and lose none.
    """
    spark = df.sparkSession
    found = checkpointed(_classed(df, ngram))
    texts = found.where("digest is not null")
    groups = texts.groupBy("digest").agg(F.min("doc_id").alias("rep"), F.count("*").alias("size"), F.first("n").alias("n"), F.first("key").alias("key"), F.first("least").alias("least"))
    groups = checkpointed(groups)
    members = texts.select("doc_id", "digest").join(groups.select("digest", "rep", "n", "size"), "digest").drop("digest")
    total = texts.agg(F.sum(F.expr(f"n - ceil(n * {tenths} / 10) + 1"))).first()[0] or 0
    parts = max(spark.sparkContext.defaultParallelism, -(-int(total) // EXCHANGED))
    heads = _prefixes(df, _levels(found.where("chunk is not null")), parts, tenths, ngram)
    met = heads.groupBy("part").applyInPandas(_meet(tenths), "ka long, na long, kb long, nb long, c long")
    met = met.groupBy("ka", "na", "kb", "nb").agg(F.sum("c").alias("c"))
    # All that is shared lies among both prefixes or behind the one that ends first.
    most = f"c + ceil(greatest(na, nb) * {tenths} / 10) - 1"
    met = met.where(f"({most}) * {10 + tenths} >= (na + nb) * {tenths}").drop("c")
    one = lambda x: groups.select(F.col("key").alias(f"k{x}"), F.col("n").alias(f"n{x}"), F.col("rep").alias(x), F.col("least").alias(f"least_{x}"))
    met = checkpointed(met.join(one("a"), ["ka", "na"]).join(one("b"), ["kb", "nb"]).drop("ka", "kb"))
    ids = checkpointed(met.select(F.explode(F.array("a", "b")).alias("doc_id")).distinct())
    blocks = ids.count() // BLOCK_SETS + 1
    block = lambda x: F.pmod(F.xxhash64(f"least_{x}"), F.lit(blocks)).cast("int")
    met = met.select("a", "b", "na", "nb", block("a").alias("x"), block("b").alias("y"))
    needed = met.select(F.col("x").alias("to_x"), F.col("y").alias("to_y"), F.explode(F.array("a", "b")).alias("doc_id")).distinct()

    def packed(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        words = _WordHash()
        for batch in batches:
            rows = [(i, shingle_set(t, ngram, words).tobytes()) for i, t in zip(batch.column("doc_id").to_pylist(), batch.column("text").to_pylist(), strict=True)]
            yield _batch(rows, {"doc_id": pa.int64(), "s": pa.binary()})

    sets = rows_of(df.select(F.col("doc_id").cast("long"), F.col("text").cast("string")), ids).mapInArrow(packed, "doc_id long, s binary")
    sent = sets.join(needed, "doc_id")
    pairs = met.groupBy("x", "y").cogroup(sent.groupBy("to_x", "to_y")).applyInPandas(_shared, "a long, b long, na long, nb long, both long")
    return members, checkpointed(pairs.where(f"both * 10 >= (na + nb - both) * {tenths}"))


def jaccard_pairs(df: DataFrame, tenths: int = 5, ngram: int = NGRAM) -> DataFrame:
    """Exact pairs with a similarity of at least ``tenths`` (the ground truth for the bands), copies of a text included."""
    members, pairs = jaccard_classes(df, tenths, ngram)
    side = lambda x: members.select(F.col("rep").alias(x), F.col("doc_id").alias(f"doc_{x}"))
    apart = pairs.join(side("a"), "a").join(side("b"), "b")
    apart = apart.select(F.least("doc_a", "doc_b").alias("a"), F.greatest("doc_a", "doc_b").alias("b"), "both", (F.col("na") + F.col("nb") - F.col("both")).alias("either"))
    copies = members.where("size > 1")
    other = copies.select("rep", F.col("doc_id").alias("b"))
    equal = copies.select("rep", F.col("doc_id").alias("a"), "n").join(other, "rep").where("a < b")
    return apart.unionByName(equal.select("a", "b", F.col("n").alias("both"), F.col("n").alias("either")))


def collision(s: Column, bands: int = BANDS, rows: int = ROWS) -> Column:
    """Probability that a pair of similarity ``s`` shares a band."""
    return 1 - F.pow(1 - F.pow(s, F.lit(float(rows))), F.lit(float(bands)))
