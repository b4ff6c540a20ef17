"""Removal of long repeated byte strings with a distributed merge sort of suffixes.

A byte goes when a string of ``length`` bytes that covers it also starts in a
document with a smaller id. Every such string holds a minimiser: the smallest
hash among its grams of ``GRAM`` bytes. Equal strings hold equal minimisers at
equal offsets, so only suffixes that begin at minimisers need sorting, and of
these only the ones whose gram occurs in two different texts.

1. ``_shared``: each task sends the minimiser hashes of its texts as flat
   blobs, dealt by hash; those seen in two texts come back per text. Of a hash
   that a task sees in many texts only the first and the last owner are sent:
   the others are known to share it at once.
2. ``_runs``: each task sorts the suffixes at these minimisers (with the bytes
   before them as a second key), and sends front-coded sorted runs by range.
   Of equal strings in a run only those of the smallest document are sent: the
   stretches of the others are settled at once and joined per document. So a
   passage that a third of all documents hold costs its range a row a run.
3. ``_merge``: each range merges its runs with a loser tree that carries common
   prefix lengths and only ever looks at bytes beyond a known prefix. Common
   prefixes of the merged order, and hashes of the bytes before, give for each
   of the strings around a minimiser the smallest document that has it.
4. The covered stretches go back per document and are cut out.

Texts that are equal as a whole are compared by digest first; only the smallest
id of each is sorted, whatever their number. A text is known by ``DIGITS`` of its
digest on the way; of texts that share these bits all suffixes are sorted.

Edge cases: null counts as empty; texts shorter than ``length`` lose nothing;
rows that repeat a whole row give equal results, and different texts under one
doc_id are cut each for itself; rows with a null doc_id keep all their bytes;
other columns are ignored.
"""

from __future__ import annotations

import hashlib
import zlib
from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame, GroupedData
from pyspark.sql import functions as F

from ._spark import join_hot, lean, map_frames, partitions, release, settle

GRAM = 24
DIGITS = 15  # hexadecimal digits of a digest that name a text on the way
PART_BYTES, MOST_PARTS = 64 << 20, 100_000  # bytes of text behind a part, beyond the session's partitions
_MIX1, _MIX2 = np.uint64(0xBF58476D1CE4E5B9), np.uint64(0x94D049BB133111EB)
_BASE = 0x100000001B3


def _window(x: np.ndarray, width: int, pick) -> np.ndarray:
    """Running minimum or maximum over ``width`` neighbours, by doubling."""
    have = 1
    while have * 2 <= width:
        x = pick(x[:-have], x[have:])
        have *= 2
    rest = width - have
    return pick(x[:-rest], x[rest:]) if rest else x


def minimisers(raw: np.ndarray, length: int) -> tuple[np.ndarray, np.ndarray]:
    """Positions and gram hashes that every window of ``length`` bytes shares with its equals."""
    if len(raw) < length:
        return np.empty(0, np.int64), np.empty(0, np.uint64)
    parts, have, h = {1: raw.astype(np.uint64) + np.uint64(1)}, 1, None
    while have * 2 <= GRAM:
        x = parts[have]
        parts[have * 2] = x[:-have] * np.uint64(pow(_BASE, have, 2**64)) + x[have:]
        have *= 2
    size = 0
    for width in sorted(parts, reverse=True):
        if GRAM & width:
            x = parts[width]
            h = x if h is None else h[: len(raw) - size - width + 1] * np.uint64(pow(_BASE, width, 2**64)) + x[size:]
            size += width
    h = (h ^ (h >> np.uint64(29))) * _MIX1
    h = (h ^ (h >> np.uint64(32))) * _MIX2
    grams = length - GRAM + 1
    low = _window(h, grams, np.minimum)  # of each window of bytes
    edge = np.zeros(grams - 1, np.uint64)
    at = np.flatnonzero(_window(np.concatenate([edge, low, edge]), grams, np.maximum) == h)
    return at, h[at]


def _key(text: bytes, digits: int) -> int:
    return int(hashlib.sha256(text).hexdigest()[:digits], 16)


def _owner(sha: Column, digits: int) -> Column:
    """``_key`` of a text by its hexadecimal digest."""
    return F.conv(F.substring(sha, 1, digits), 16, 10).cast("long")


def _dealt(owner: np.ndarray, values: list[np.ndarray], parts: np.ndarray, names: list[str]) -> pd.DataFrame:
    """One row of flat blobs for each part."""
    order = np.argsort(parts, kind="stable")
    cuts = np.flatnonzero(np.diff(parts[order])) + 1
    rows = []
    for at in np.split(order, cuts) if len(order) else []:
        rows.append((int(parts[at[0]]), owner[at].tobytes(), *(v[at].tobytes() for v in values)))
    return pd.DataFrame(rows, columns=["part", "owner", *names])


def _flat(blobs: pd.Series, kind: str) -> np.ndarray:
    return np.frombuffer(b"".join(blobs), kind)


def _met(dealt: DataFrame, parts: int) -> GroupedData:
    """Groups by part; more parts than the session's partitions are tasks of their own."""
    if parts > partitions(dealt.sparkSession):
        dealt = dealt.repartition(parts, "part")
    return dealt.groupBy("part")


def _per_owner(dealt: DataFrame, owners: list[str], name: str, width: int, parts: int) -> DataFrame:
    """Blobs dealt by owner to rows ``(*owners, name)``, one for each owner."""

    def collect(part: pd.DataFrame) -> pd.DataFrame:
        owner, value = _flat(part["owner"], "<i8").reshape(-1, len(owners)), _flat(part[name], f"V{width}")
        order = np.lexsort(owner.T)
        owner = owner[order]
        starts = np.flatnonzero(np.r_[True, (owner[1:] != owner[:-1]).any(axis=1)]) if len(owner) else np.empty(0, int)
        blobs = [x.tobytes() for x in np.split(value[order], starts[1:])] if len(owner) else []
        return pd.DataFrame({**{k: owner[starts, i] for i, k in enumerate(owners)}, name: blobs})

    kinds = ", ".join(f"{k} long" for k in owners)
    return _met(dealt, parts).applyInPandas(collect, f"{kinds}, {name} binary")


def _shared(texts: DataFrame, length: int, parts: int, digits: int) -> DataFrame:
    """Rows ``(owner, hashes)``: minimiser hashes of a text that another text has too."""

    @lean
    def send(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        owners, hashes, size = [], [], 0

        def flush() -> pd.DataFrame:
            owner, h = np.concatenate(owners), np.concatenate(hashes)
            order = np.lexsort((owner, h))
            owner, h = owner[order], h[order]
            new = np.r_[True, (h[1:] != h[:-1]) | (owner[1:] != owner[:-1])]
            owner, h = owner[new], h[new]
            starts = np.flatnonzero(np.r_[True, h[1:] != h[:-1]])
            ends = np.zeros(len(h), bool)
            ends[starts] = ends[np.r_[starts[1:], len(h)] - 1] = True
            open_ = _dealt(owner[ends], [h[ends]], (h[ends] % np.uint64(parts)).astype(np.int64), ["h"])
            known = _dealt(owner[~ends], [h[~ends]], -1 - owner[~ends] % parts, ["h"])
            return pd.concat([open_, known])

        for b in batches:
            for text in b["text"]:
                raw = text.encode("utf-8")
                h = np.unique(minimisers(np.frombuffer(raw, np.uint8), length)[1])
                if len(h):
                    owners.append(np.full(len(h), _key(raw, digits), "<i8"))
                    hashes.append(h)
                    size += len(h)
                if size > 4_000_000:
                    yield flush()
                    owners, hashes, size = [], [], 0
        if size:
            yield flush()

    def meet(part: pd.DataFrame) -> pd.DataFrame:
        owner, h = _flat(part["owner"], "<i8"), _flat(part["h"], "<u8")
        if part["part"].iloc[0] < 0:  # known to be shared
            return _dealt(owner, [h], owner % parts, ["h"])
        order = np.lexsort((owner, h))
        owner, h = owner[order], h[order]
        starts = np.flatnonzero(np.r_[True, h[1:] != h[:-1]])
        several = owner[starts] != owner[np.r_[starts[1:], len(h)] - 1]
        keep = np.repeat(several, np.diff(np.r_[starts, len(h)]))
        keep &= np.r_[True, (owner[1:] != owner[:-1]) | (h[1:] != h[:-1])]
        owner, h = owner[keep], h[keep]
        return _dealt(owner, [h], owner % parts, ["h"])

    kind = "part long, owner binary, h binary"
    met = _met(texts.select("text").mapInPandas(send, kind), parts).applyInPandas(meet, kind)
    return _per_owner(met, ["owner"], "h", 8, parts)


def _packed(texts: DataFrame, digits: int) -> DataFrame:
    """Rows ``(doc_id, owner, packed)``: each text's bytes compressed before they are shuffled by id; null stays null."""

    @lean
    def pack(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for b in batches:
            packed, owners = [], []
            for t in b["text"]:
                raw = None if t is None else t.encode("utf-8")
                packed.append(None if raw is None else zlib.compress(raw, 1))
                owners.append(None if raw is None else _key(raw, digits))
            yield pd.DataFrame({"doc_id": b["doc_id"], "owner": pd.Series(owners, b.index, "Int64"), "packed": pd.Series(packed, b.index, object)})

    return map_frames(texts.select("doc_id", "text"), pack, "doc_id long, owner long, packed binary")


def _grams(text: Column, sha: Column, count: int = 2) -> Column:
    """A few grams of a text at places that its digest tells."""
    raw = text.cast("binary")
    place = lambda k: F.pmod(F.xxhash64(sha, F.lit(k)), F.octet_length(text) - GRAM + 1).cast("int") + 1
    return F.array(*[F.substring(raw, place(k), F.lit(GRAM)) for k in range(count)])


def _splitters(digests: DataFrame, docs: int, parts: int, most: int = 100_000) -> np.ndarray:
    """Bounds of the suffix ranges, from the grams of about ``most`` documents at most; they shape tasks, not results."""
    rows = digests.sample(min(1.0, most / max(docs, 1)), seed=1).select(F.explode("grams").alias("gram")).collect()
    grams = sorted(bytes(r.gram) for r in rows)
    return np.array([grams[len(grams) * k // parts] for k in range(1, parts)] if grams else [], f"S{GRAM}")


def _stretches(grid: np.ndarray, length: int) -> tuple[np.ndarray, np.ndarray]:
    """First and last offset before a minimiser at which a window of ``length`` bytes lies within its text."""
    before = length - GRAM
    outside = grid == 255
    n_right = np.where(outside[:, :length].any(axis=1), outside[:, :length].argmax(axis=1), length)
    n_left = np.where(outside[:, length:].any(axis=1), outside[:, length:].argmax(axis=1), before)
    return length - n_right, n_left


def _joined(owner: np.ndarray, begin: np.ndarray, end: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Stretches of each owner without overlap, as owners and pairs of 32-bit offsets."""
    order = np.lexsort((begin, owner[:, 1], owner[:, 0]))
    owner, begin, end = owner[order], begin[order], end[order]
    group = np.cumsum(np.r_[0, (owner[1:] != owner[:-1]).any(axis=1)]) << 33
    reach = np.maximum.accumulate(end + group)
    new = np.flatnonzero(np.r_[True, (begin + group)[1:] > reach[:-1]])
    last = np.r_[new[1:], len(owner)] - 1
    pairs = np.stack([begin[new], reach[last] - group[last]], axis=1).astype("<u4")
    return owner[new], np.ascontiguousarray(pairs).view("V8").ravel()


def _runs(texts: DataFrame, length: int, bounds: np.ndarray, parts: int) -> DataFrame:
    """Front-coded sorted runs ``(part, lcp, rest, copies, doc, at)`` of suffixes at shared minimisers.

    Negative parts hold stretches that a run settles by itself: their owners in ``doc``, the offsets in ``at``.
    """
    before = length - GRAM
    width = length + before

    names = ["part", "lcp", "rest", "copies", "doc", "at"]

    def run_of(grid: np.ndarray, doc: np.ndarray, at: np.ndarray) -> pd.DataFrame:
        flat = np.ascontiguousarray(grid).view(f"S{width}").ravel()
        order = np.lexsort((doc[:, 0], flat))
        grid, doc, at = grid[order], doc[order], at[order]
        differ = grid[1:] != grid[:-1]
        lcp = np.r_[0, np.where(differ.any(axis=1), differ.argmax(axis=1), width)]
        new = np.flatnonzero(lcp < width)
        times = np.diff(np.r_[new, len(grid)])
        later = doc[:, 0] > np.repeat(doc[new, 0], times)
        rows = []
        if later.any():
            low, high = _stretches(grid[later], length)
            inside = low <= high
            owner, span = _joined(doc[later][inside], (at[later] - high)[inside], (at[later] - low)[inside] + length)
            found = _dealt(owner, [span], -1 - owner[:, 0] % parts, ["span"])
            rows += [(p, b"", b"", b"", zlib.compress(o, 1), zlib.compress(x, 1)) for p, o, x in found.itertuples(index=False)]
        times = np.add.reduceat(~later, new, dtype=np.int64)
        strings, known, doc, at = grid[new], lcp[new], doc[~later], at[~later]
        part = np.searchsorted(bounds, np.ascontiguousarray(strings[:, :GRAM]).view(f"S{GRAM}").ravel(), "right")
        ends = np.r_[0, np.cumsum(times)]
        for p in np.unique(part):
            lo, hi = np.searchsorted(part, [p, p + 1])
            mine = known[lo:hi].copy()
            mine[0] = 0
            rest = strings[lo:hi][np.arange(width)[None, :] >= mine[:, None]]
            docs = slice(ends[lo], ends[hi])
            blobs = mine.astype("u1"), rest, times[lo:hi].astype("<u4"), doc[docs], at[docs].astype("<u4")
            rows.append((int(p), *(zlib.compress(x.tobytes(), 1) for x in blobs)))
        return pd.DataFrame(rows, columns=names)

    @lean
    def send(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        grids, docs, ats, size = [], [], [], 0
        for b in batches:
            for doc, owner, packed, h in zip(b["doc_id"], b["owner"], b["packed"], b["h"], strict=True):
                raw = np.frombuffer(zlib.decompress(packed), np.uint8)
                at, own = minimisers(raw, length)
                if h is not None:
                    at = at[np.isin(own, np.frombuffer(h, "<u8"))]
                if not len(at):
                    continue
                # 255 is in no UTF-8 text: it stands for what lies outside of this one.
                wide = np.concatenate([np.full(before, 255, np.uint8), raw, np.full(length, 255, np.uint8)])
                right = wide[before + at[:, None] + np.arange(length)]
                left = wide[before + at[:, None] - 1 - np.arange(before)]
                grids.append(np.hstack([right, left]))
                docs.append(np.broadcast_to(np.array([doc, owner], "<i8"), (len(at), 2)))
                ats.append(at)
                size += len(at)
                if size > 300_000:
                    yield run_of(np.concatenate(grids), np.concatenate(docs), np.concatenate(ats))
                    grids, docs, ats, size = [], [], [], 0
        if size:
            yield run_of(np.concatenate(grids), np.concatenate(docs), np.concatenate(ats))

    return texts.select("doc_id", "owner", "packed", "h").mapInPandas(send, "part long, lcp binary, rest binary, copies binary, doc binary, at binary")


def unpack_run(lcp: bytes, rest: bytes, width: int) -> list[bytes]:
    """Strings of a front-coded run."""
    out, at, last = [], 0, b""
    for known in lcp:
        size = width - known
        last = last[:known] + rest[at : at + size]
        out.append(last)
        at += size
    return out


def merge_runs(runs: list[tuple[list[bytes], bytes]], width: int) -> tuple[list[int], list[int]]:
    """Merge sorted runs with a loser tree over common prefix lengths.

    Each run comes with the common prefix of every string and the one before it.
    Returns the run of each string in merged order, and its common prefix with
    its predecessor there. A player keeps the prefix it shares with the last
    winner on its path: unequal prefixes decide a match without a look at any
    byte, equal ones are only compared beyond it.
    """
    size = 1
    while size < max(1, len(runs)):
        size *= 2
    head: list[bytes | None] = [r[0][0] if r[0] else None for r in runs] + [None] * (size - len(runs))
    known = [0 if h is not None else -1 for h in head]
    place = [0] * len(runs)

    def match(a: int, b: int) -> tuple[int, int]:
        x, y = known[a], known[b]
        if x != y:
            return (a, b) if x > y else (b, a)
        if x < 0:
            return a, b
        s, t = head[a], head[b]
        while x < width:
            p, q = s[x : x + 8], t[x : x + 8]
            if p != q:
                k = 0
                while p[k] == q[k]:
                    k += 1
                if p[k] < q[k]:
                    known[b] = x + k
                    return a, b
                known[a] = x + k
                return b, a
            x += 8
        known[b] = width
        return a, b

    losers = [0] * size
    level = list(range(size))
    while len(level) > 1:
        half = len(level) // 2
        up = []
        for k in range(half):
            won, lost = match(level[2 * k], level[2 * k + 1])
            up.append(won)
            losers[half + k] = lost
        level = up
    best = level[0]
    order, shared = [], []
    while known[best] >= 0:
        order.append(best)
        shared.append(known[best])
        place[best] += 1
        strings, lcp = runs[best]
        if place[best] < len(strings):
            head[best], known[best] = strings[place[best]], lcp[place[best]]
        else:
            head[best], known[best] = None, -1
        node = (best + size) // 2
        while node:
            best, losers[node] = match(best, losers[node])
            node //= 2
    return order, shared


def _merge(runs: DataFrame, length: int, parts: int) -> DataFrame:
    """Rows ``(doc_id, owner, span)``: stretches of documents that a smaller document has too."""
    before = length - GRAM
    width = length + before

    def merge(part: pd.DataFrame) -> pd.DataFrame:
        if part["part"].iloc[0] < 0:  # settled in their runs
            row, span = (_flat(part[x].map(zlib.decompress), kind) for x, kind in (("doc", "<i8"), ("at", "V8")))
            row = row.reshape(-1, 2)
            return _dealt(row, [span], row[:, 0] % parts, ["span"])
        for name in ("lcp", "rest", "copies", "doc", "at"):
            part[name] = part[name].map(zlib.decompress)
        packed = [(unpack_run(lcp, rest, width), lcp) for lcp, rest in zip(part["lcp"], part["rest"], strict=True)]
        order, shared = (np.array(x, np.int64) for x in merge_runs(packed, width))
        # Where each merged string's documents lie in the concatenated runs.
        sizes = np.array([len(s) for s, _ in packed])
        rank = np.argsort(order, kind="stable")
        entry = np.empty(len(order), np.int64)
        entry[rank] = np.arange(len(order))
        grid = np.frombuffer(b"".join(b"".join(s) for s, _ in packed), np.uint8).reshape(-1, width)[entry]
        assert sizes.sum() == len(order)
        copies = _flat(part["copies"], "<u4").astype(np.int64)
        begins = np.cumsum(copies) - copies
        row_of, at = _flat(part["doc"], "<i8").reshape(-1, 2), _flat(part["at"], "<u4").astype(np.int64)
        doc = row_of[:, 0]
        first = np.minimum.reduceat(doc, begins)[entry]
        owner = np.empty(len(doc), np.int64)  # the merged string of each occurrence
        owner[:] = np.repeat(np.argsort(entry, kind="stable"), copies)
        low, high = _stretches(grid, length)
        covered = np.zeros((len(doc), before + 3), bool)
        left = np.zeros(len(grid), np.uint64)
        for o in range(before + 1):
            if o:
                left = (left + grid[:, length + o - 1].astype(np.uint64) + np.uint64(1)) * _MIX1
                left ^= left >> np.uint64(31)
            right = np.cumsum(shared < length - o).astype(np.uint64)
            key = (right * _MIX2) ^ left
            by = np.argsort(key, kind="stable")
            starts = np.flatnonzero(np.r_[True, key[by][1:] != key[by][:-1]])
            least = np.empty(len(key), np.int64)
            least[by] = np.repeat(np.minimum.reduceat(first[by], starts), np.diff(np.r_[starts, len(by)]))
            ok = (low <= o) & (o <= high)
            covered[:, o + 1] = ok[owner] & (least[owner] < doc)
        step = np.diff(covered.astype(np.int8), axis=1)
        row, lo = np.nonzero(step == 1)
        hi = np.nonzero(step == -1)[1]
        if not len(row):
            return pd.DataFrame([], columns=["part", "owner", "span"])
        owner, span = _joined(row_of[row], at[row] - (hi - 1), at[row] - lo + length)
        return _dealt(owner, [span], owner[:, 0] % parts, ["span"])

    met = _met(runs, parts).applyInPandas(merge, "part long, owner binary, span binary")
    return _per_owner(met, ["doc_id", "owner"], "span", 8, parts)


def _cut(packed: bytes | None, spans: bytes | None, whole: bool, length: int) -> tuple[int, int, int, bytes]:
    """``(bytes, removed, stretches, what is left)`` of a packed text."""
    raw = zlib.decompress(packed) if packed is not None else b""
    if whole and len(raw) >= length:
        return len(raw), len(raw), 1, b""
    if not spans or whole:
        return len(raw), 0, 0, raw
    pairs = np.frombuffer(spans, "<u4").reshape(-1, 2).astype(np.int64)
    pairs = pairs[np.argsort(pairs[:, 0], kind="stable")]
    reach = np.maximum.accumulate(pairs[:, 1])
    new = np.flatnonzero(np.r_[True, pairs[1:, 0] > reach[:-1]])
    begin, end = pairs[new, 0], reach[np.r_[new[1:], len(pairs)] - 1]
    keep = b"".join(raw[a:b] for a, b in zip([0, *end], [*begin, len(raw)], strict=True))
    return len(raw), int((end - begin).sum()), len(new), keep


def repeated_spans(docs: DataFrame, length: int = 50, digits: int = DIGITS) -> DataFrame:
    """Rows ``(doc_id, owner, spans, whole)`` of texts with something to remove.

    ``spans`` holds pairs of 32-bit byte offsets; ``whole`` marks a text that a
    smaller document equals altogether; ``owner`` tells the texts of a doc_id apart.
    """
    spark = docs.sparkSession
    slim = docs.select(F.col("doc_id").cast("long"), F.col("text").cast("string")).where("doc_id is not null and text is not null")
    long = slim.where(F.octet_length("text") >= length)
    hashed = long.withColumn("sha", F.sha2("text", 256))
    digests = settle(hashed.select("doc_id", F.unhex("sha").alias("sha"), F.octet_length("text").alias("size"), _grams(F.col("text"), F.col("sha")).alias("grams")))
    count, total = digests.agg(F.count("*"), F.coalesce(F.sum("size"), F.lit(0))).first()
    parts = max(partitions(spark), min(MOST_PARTS, total // PART_BYTES))
    firsts = digests.groupBy("sha").agg(F.min("doc_id").alias("first"), F.count("*").alias("n"))
    copied = join_hot(digests.select("sha", "doc_id"), firsts.where("n > 1"), "sha", count)
    whole = settle(copied.where("doc_id <> first").select("doc_id", _owner(F.hex("sha"), digits).alias("owner")).distinct())
    shared = _shared(slim, length, parts, digits)
    keyed = firsts.select(F.col("first").alias("doc_id"), _owner(F.hex("sha"), digits).alias("owner"))
    # Texts with one owner number are one but for chance: of others every suffix is sought.
    keyed = keyed.groupBy("owner").agg(F.collect_list("doc_id").alias("ids"))
    found = keyed.join(shared, "owner", "left").where("h is not null or size(ids) > 1")
    sought = settle(found.select(F.explode("ids").alias("doc_id"), "owner", F.when(F.size("ids") == 1, F.col("h")).alias("h")))
    bounds = _splitters(digests, count, parts)
    del digests, firsts, copied, shared, keyed, found  # what nobody refers to any more frees its shuffle files
    release(spark)
    texts = _packed(long, digits).join(sought, ["doc_id", "owner"])
    spans = settle(_merge(_runs(texts, length, bounds, parts), length, parts))
    del sought, texts
    release(spark)
    return (
        spans.withColumnRenamed("span", "spans")
        .join(whole.withColumn("whole", F.lit(True)), ["doc_id", "owner"], "full")
        .select("doc_id", "owner", "spans", F.coalesce("whole", F.lit(False)).alias("whole"))
    )


def deduplicate(docs: DataFrame, length: int = 50, *, texts: bool = True, digits: int = DIGITS) -> DataFrame:
    """Rows ``(doc_id, n_bytes, n_removed, n_spans, kept_sha256, kept)``; ``kept`` is the bytes left, null with ``texts=False``."""
    spans = repeated_spans(docs, length, digits)
    slim = docs.select(F.col("doc_id").cast("long"), F.col("text").cast("string"))

    @lean
    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for b in batches:
            rows = []
            for packed, span, whole in zip(b["packed"], b["spans"], b["whole"], strict=True):
                *counts, kept = _cut(packed, span, whole is True or whole == True, length)  # noqa: E712
                rows.append((*counts, hashlib.sha256(kept).hexdigest(), kept if texts else None))
            got = pd.DataFrame(rows, columns=["n_bytes", "n_removed", "n_spans", "kept_sha256", "kept"], index=b.index)
            yield pd.concat([b[["doc_id"]], got], axis=1)

    return map_frames(
        _packed(slim, digits).join(spans, ["doc_id", "owner"], "left"), run, "doc_id long, n_bytes long, n_removed long, n_spans long, kept_sha256 string, kept binary"
    )
