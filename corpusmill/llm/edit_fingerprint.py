"""Document fingerprints by a randomised edit embedding.

A walk reads the characters of a text from the left. At step j on character c
a shared random bit says whether the pointer moves on; the embedding is the
sequence of characters under the pointer. Two texts walk together until an
edit, and chance steps bring them together again after it, so few edits mean
few differing steps: edit distance becomes Hamming distance.

The embedding of a text of n characters has about 2n steps. A fingerprint
samples 256 of all its steps: sample m is the last step at which an endless
random sequence of its own set a new minimum. That step is uniform over the
walk, and texts of similar length sample the same steps. Each sample is hashed
with the characters under the pointer to one hexadecimal digit.

Near texts are found by bands of sampled digits and verified on the whole
fingerprint. Edge cases: null counts as empty; all empty texts share one
fingerprint; texts of any length are walked to the end; repeated rows are
fingerprinted each; other columns are ignored.
"""

from __future__ import annotations

import hashlib
import itertools
import math
import zlib
from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ._spark import lean, map_frames, partitions, release, settle
from .components import connected_components
from .near_dedup import _named, _to_pivots

SAMPLES, PERIOD, CLASSES = 256, 4096, 256
BLOCK = 4096  # fingerprints of 128 bytes that a task compares with as many
_DIGITS = np.frombuffer(b"0123456789abcdef", np.uint8)


class EditEmbedding:
    """Shared randomness of the walks: one object per Python worker."""

    def __init__(self, seed: int = 11):
        rng = np.random.default_rng(seed)
        bits = rng.integers(0, 2, (CLASSES, PERIOD), dtype=np.uint8)
        bits[:, -1] = 1
        after = np.where(bits == 1, np.arange(PERIOD), PERIOD)
        after = np.minimum.accumulate(after[:, ::-1], axis=1)[:, ::-1]
        self.stay = (after - np.arange(PERIOD) + 1).tolist()  # steps spent on a character
        records = np.ones((SAMPLES, 1))
        while records[:, -1].min() < 2**45:
            u = rng.random(SAMPLES)
            records = np.column_stack([records, np.floor(records[:, -1] / u) + 1])
        self.records = records  # steps, counted from 1, that set a new minimum
        self.salt = rng.integers(0, 2**63, SAMPLES, dtype=np.uint64)

    def walk(self, codes: np.ndarray, step: int = 0) -> tuple[list[int], int]:
        """Step at which the pointer reaches each character, and the step after the last."""
        stay, mask, arrivals = self.stay, PERIOD - 1, []
        push = arrivals.append
        for c in (codes & (CLASSES - 1)).tolist():
            push(step)
            step += stay[c][step & mask]
        return arrivals, step

    def sample(self, codes: np.ndarray, arrivals: np.ndarray, steps: int) -> str:
        """The fingerprint of a walk."""
        if not len(codes):
            value = self.salt
        else:
            at = self.records[np.arange(SAMPLES), (self.records <= steps).sum(axis=1) - 1].astype(np.int64) - 1
            i = np.searchsorted(arrivals, at, "right") - 1
            wide = np.concatenate([codes, np.zeros(2, codes.dtype)]).astype(np.uint64)
            value = self.salt ^ (wide[i] + (wide[i + 1] << np.uint64(21)) + (wide[i + 2] << np.uint64(42)))
        value = (value ^ (value >> np.uint64(31))) * np.uint64(0x9E3779B97F4A7C15)
        return _DIGITS[value >> np.uint64(60)].tobytes().decode()


def likeness(a: str, b: str) -> float:
    """Share of equal steps that two fingerprints tell, chance digits taken off: 0 to 1."""
    same = np.mean(np.frombuffer(a.encode(), np.uint8) == np.frombuffer(b.encode(), np.uint8))
    return float(max(0.0, (same - 1 / 16) * 16 / 15))


_SHARED: list[EditEmbedding] = []


def _embedding() -> EditEmbedding:
    if not _SHARED:
        _SHARED.append(EditEmbedding())
    return _SHARED[0]


def _codes(text: str) -> np.ndarray:
    return np.frombuffer(text.encode("utf-32-le"), np.uint32)


def fingerprint(text: str | None) -> str:
    e, codes = _embedding(), _codes(text or "")
    arrivals, steps = e.walk(codes)
    return e.sample(codes, np.array(arrivals, np.int64), steps)


def fingerprints(docs: DataFrame) -> DataFrame:
    """Rows ``(doc_id, fingerprint)`` of whole texts."""

    @lean
    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for b in batches:
            yield pd.DataFrame({"doc_id": b["doc_id"], "fingerprint": [fingerprint(t) for t in b["text"]]})

    return map_frames(docs.select(F.col("doc_id").cast("long"), F.col("text").cast("string")), run, "doc_id long, fingerprint string")


#: Equal digits of two bytes of packed fingerprints, by their exclusive or.
_EQUAL = np.array([(x < 16) + (x % 16 == 0) for x in range(256)], np.uint8)


def _verified(pairs: DataFrame, heads: DataFrame, least: float) -> DataFrame:
    """Links of ``pairs`` that hold on whole fingerprints."""
    side = lambda x: heads.select(F.col("doc_id").alias(x), F.col("print").alias(f"f_{x}"))

    @lean
    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for p in batches:
            if len(p):
                x, y = (_matrix(p[f"f_{k}"]) for k in "ab")
                yield p.loc[_likeness_of(x, y) >= least, ["a", "b"]]

    got = pairs.join(side("a"), "a").join(side("b"), "b").select("a", "b", "f_a", "f_b").mapInPandas(run, "a long, b long")
    return settle(got)


def _matrix(prints: pd.Series) -> np.ndarray:
    return np.frombuffer(b"".join(prints), np.uint8).reshape(len(prints), SAMPLES // 2)


def _likeness_of(x: np.ndarray, y: np.ndarray) -> np.ndarray:
    same = _EQUAL[x ^ y].sum(axis=1, dtype=np.int64)
    return np.maximum(0.0, (same / SAMPLES - 1 / 16) * 16 / 15)


def _links_apart(named: DataFrame, heads: DataFrame, least: float) -> DataFrame:
    """Links between the components that share a bucket.

    Members outside a bucket's largest component meet all members, block by
    block. A task passes on as many links as join its components.
    """
    sizes = named.groupBy("key", "component").agg(F.count("*").alias("m"))
    main = sizes.groupBy("key").agg(F.max_by("component", F.struct("m", "component")).alias("main"), F.sum("m").alias("n"), F.max("m").alias("most"))
    of = named.select("key", "doc_id", "component").join(main, "key")
    few, all_ = (F.ceil(x / BLOCK).cast("int") for x in (F.col("n") - F.col("most"), F.col("n")))
    block = lambda blocks: F.pmod(F.xxhash64("doc_id"), blocks).cast("int")
    spread = lambda blocks: F.explode(F.sequence(F.lit(0), blocks - 1))
    cols = ["key", "lo", "hi", "outer", "doc_id", "component"]
    outer = of.where("component <> main").withColumn("lo", block(few)).withColumn("hi", spread(all_)).withColumn("outer", F.lit(True))
    every = of.withColumn("hi", block(all_)).withColumn("lo", spread(few)).withColumn("outer", F.lit(False))
    dealt = outer.select(cols).unionByName(every.select(cols)).join(heads, "doc_id")

    def compare(group: pd.DataFrame) -> pd.DataFrame:
        root, found = {}, []

        def find(x):
            while root.setdefault(x, x) != x:
                x = root[x]
            return x

        out, rest = group[group["outer"]], group[~group["outer"]]
        if len(out) and len(rest):
            prints, ids, comp = _matrix(rest["print"]), rest["doc_id"].to_numpy(), rest["component"].to_numpy()
            for k, c, own in zip(out["doc_id"], out["component"], _matrix(out["print"]), strict=True):
                for j in np.flatnonzero((_likeness_of(prints, own) >= least) & (comp != c)):
                    x, y = find(c), find(comp[j])
                    if x != y:
                        root[x] = y
                        found.append((min(k, ids[j]), max(k, ids[j])))
        return pd.DataFrame(found, columns=["a", "b"], dtype="int64")

    return settle(dealt.groupBy("key", "lo", "hi").applyInPandas(compare, "a long, b long"))


def bands_for(least: float, digits: int, missed: float = 2e-5) -> int:
    """Bands at which a pair of likeness ``least`` shares no bucket with a chance of ``missed`` at most."""
    shared = (least + (1 - least) / 16) ** digits
    return math.ceil(math.log(missed) / math.log1p(-shared)) if shared < 1 else 1


def print_groups(prints: DataFrame, *, least: float = 0.8, bands: int | None = None, digits: int = 6, seed: int = 5) -> DataFrame:
    """Rows ``(print, component_id)`` of the ``prints(doc_id, print)`` with a likeness of ``least`` or more.

    A print is a fingerprint packed to bytes.

    Bit-sampled banding: each band is ``digits`` random samples; there are as
    many bands as ``least`` needs, unless ``bands`` says otherwise. Members of a
    bucket are verified on whole fingerprints against its smallest id, then
    against two random pivots. What is still apart is compared block by block,
    so no link inside a bucket is lost. Equal fingerprints collapse first. A
    null doc_id takes the smallest id of its group, or null if none has one.
    """
    spark = prints.sparkSession
    rng = np.random.default_rng(seed)
    bands = bands or bands_for(least, digits)
    picks = [sorted(rng.choice(SAMPLES, digits, replace=False).tolist()) for _ in range(bands)]
    heads = settle(prints.groupBy("print").agg(F.min("doc_id").alias("doc_id")))
    known = heads.where("doc_id is not null")
    # Six digits are 24 bits: a number of a band and its digits is exact.
    code = lambda k, pick: F.conv(F.concat(*[F.substring(F.hex("print"), p + 1, 1) for p in pick]), 16, 10).cast("long") * bands + k
    entries = known.select("doc_id", F.explode(F.array(*[code(k, pick) for k, pick in enumerate(picks)])).alias("key"))
    buckets = entries.groupBy("key").agg(F.min("doc_id").alias("first"), F.count("*").alias("n")).where("n > 1")
    members = settle(entries.join(buckets, "key").select("key", "doc_id", "first", "n"))
    del entries, buckets
    release(spark)
    stars = members.where("doc_id <> first").select(F.col("first").alias("a"), F.col("doc_id").alias("b")).distinct()
    links = _verified(stars, known, least)
    labels = settle(connected_components(links))
    release(spark)
    named = _named(members, labels)
    if not named.isEmpty():
        pivots = _to_pivots(named, 1, 2)
        links = links.unionByName(_verified(pivots, known, least))
        labels = settle(connected_components(links))
        del named, pivots
        release(spark)
        named = _named(members, labels)
        if not named.isEmpty():
            labels = settle(connected_components(links.unionByName(_links_apart(named, known, least))))
    del named, members, links, stars
    release(spark)
    return heads.join(labels, F.col("doc_id") == F.col("node"), "left").select("print", F.coalesce("component", "doc_id").alias("component_id"))


def near_groups(prints: DataFrame, **options) -> DataFrame:
    """Rows ``(doc_id, component_id)``, one per row of ``prints(doc_id, fingerprint)``; options as in ``print_groups``."""
    packed = prints.select("doc_id", F.unhex("fingerprint").alias("print"))
    return packed.join(print_groups(packed, **options), "print").select("doc_id", "component_id")


def grouped_edits(docs: DataFrame) -> DataFrame:
    """``compare_edits`` with the near group of each document as ``component_id``."""
    edits = settle(_edits(docs))  # narrow rows; the shuffle files of the texts go before the groups are sought
    release(docs.sparkSession)
    groups = print_groups(edits.select("doc_id", "print"))
    return _shown(edits.join(groups, "print")).select(*RESULTS, "component_id")


RESULTS = ("doc_id", "n_chars", "edited_sha256", "fingerprint", "edited_fingerprint", "near_edited", "near_next")


def _shown(edits: DataFrame) -> DataFrame:
    """Packed digests and fingerprints as hexadecimal digits."""
    digits = {"edited_sha256": "edited_sha", "fingerprint": "print", "edited_fingerprint": "edited_print"}
    return edits.withColumns({name: F.lower(F.hex(packed)) for name, packed in digits.items()})


def compare_edits(docs: DataFrame) -> DataFrame:
    """Fingerprint every text, its edited form, and tell their likeness.

    The last quarter of a text is replaced by the beginning of the next
    document by doc_id; after the last comes the first. Rows are dealt by
    ranges of doc_id and ordered inside them; each range also gets the first
    row of the next one, so no global order of texts is made. A null doc_id
    comes last; rows with equal doc_id are ordered by text.
    """
    return _shown(_edits(docs)).select(*RESULTS)


@lean
def _pack(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
    for b in batches:
        packed = [zlib.compress(t.encode("utf-8"), 1) for t in b["text"]]
        yield b[["part", "k", "guest"]].assign(packed=pd.Series(packed, b.index, object))


def _in_order(part: pd.DataFrame) -> Iterator[bytes]:
    """Packed texts by key; those of one key by text."""
    k, packed = part["k"].to_numpy(), part["packed"].to_numpy()
    order = np.argsort(k, kind="stable")
    starts = np.flatnonzero(np.r_[True, k[order][1:] != k[order][:-1]])
    for tied in np.split(order, starts[1:]):
        yield from sorted(packed[tied], key=zlib.decompress) if len(tied) > 1 else packed[tied]


def _edits(docs: DataFrame) -> DataFrame:
    """``compare_edits`` with packed digests and fingerprints."""
    spark = docs.sparkSession
    slim = docs.select(F.coalesce(F.col("doc_id").cast("long"), F.lit(2**63 - 1)).alias("k"), F.coalesce(F.col("text").cast("string"), F.lit("")).alias("text"))
    parts = partitions(spark)
    cuts = slim.agg(F.percentile_approx("k", [x / parts for x in range(1, parts)], 10 * parts)).first()[0] if parts > 1 else None
    bounds = np.unique(np.array(cuts or [], np.int64))
    deal = F.pandas_udf(lambda k: pd.Series(np.searchsorted(bounds, k.to_numpy(), "right")), "long")
    firsts = sorted((r.part, r.k) for r in slim.select(deal("k").alias("part"), "k").groupBy("part").agg(F.min("k").alias("k")).collect())
    follow = [(p, firsts[(i + 1) % len(firsts)][1]) for i, (p, _) in enumerate(firsts)]
    guests = spark.createDataFrame(follow, "part long, k long") if follow else spark.createDataFrame([], "part long, k long")
    # One row for each range: its size is the number of ranges, whatever the input.
    rows = slim.withColumn("part", deal("k")).withColumn("guest", F.lit(False)).select("part", "k", "text", "guest")
    extra = slim.join(F.broadcast(guests), "k").withColumn("guest", F.lit(True)).select("part", "k", "text", "guest")
    dealt = rows.unionByName(extra).mapInPandas(_pack, "part long, k long, guest boolean, packed binary")

    def run(part: pd.DataFrame) -> pd.DataFrame:
        e = _embedding()
        own = part[~part["guest"]]
        texts = itertools.chain(_in_order(own), itertools.islice(_in_order(part[part["guest"]]), 1))  # unpacked one by one
        unpacked = (zlib.decompress(t).decode("utf-8") for t in texts)
        out = []
        following = next(unpacked)
        codes = _codes(following)
        arrivals, steps = e.walk(codes)
        print_ = e.sample(codes, np.array(arrivals, np.int64), steps)
        for k in np.sort(own["k"].to_numpy()):
            text, following = following, next(unpacked)
            n = len(text)
            cut = n - n // 4
            tail = _codes(following[: n // 4])
            more, total = e.walk(tail, arrivals[cut] if cut < n else steps)
            edited = np.concatenate([codes[:cut], tail])
            edited_print = e.sample(edited, np.array(arrivals[:cut] + more, np.int64), total)
            sha = hashlib.sha256((text[:cut] + following[: n // 4]).encode("utf-8")).digest()
            codes = _codes(following)
            arrivals, steps = e.walk(codes)
            next_print = e.sample(codes, np.array(arrivals, np.int64), steps)
            out.append((k, n, sha, bytes.fromhex(print_), bytes.fromhex(edited_print), likeness(print_, edited_print), likeness(print_, next_print)))
            print_ = next_print
        names = ["doc_id", "n_chars", "edited_sha", "print", "edited_print", "near_edited", "near_next"]
        return pd.DataFrame(out, columns=names)

    done = dealt.groupBy("part").applyInPandas(
        run, "doc_id long, n_chars long, edited_sha binary, print binary, edited_print binary, near_edited double, near_next double"
    )
    return done.withColumn("doc_id", F.nullif("doc_id", F.lit(2**63 - 1)))
