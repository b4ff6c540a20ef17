"""BPE encoding and decoding with batched numpy merge rounds.

All distinct words of a batch of texts sit in one flat array of symbols. A
round looks every neighbouring pair up by binary search over the sorted pair
keys of the merge table, takes the lowest rank of each word, and merges all
its occurrences from the left. Words without a mergeable pair leave the array.

The tokenizer file is a parameter: its vocabulary, merges, word-end suffix,
byte alphabet, splitting pattern and special tokens are read from it.

Edge cases: null counts as empty and gives no ids; special tokens inside a text
are recognised before normalisation; very long words only make more rounds;
repeated rows are encoded each; other columns are ignored.
"""

from __future__ import annotations

import itertools
import json
import unicodedata
from collections.abc import Iterator

import numpy as np
import pandas as pd
import regex
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ._spark import lean, map_frames

_NONE = np.iinfo(np.int64).max
MOST_WORDS = 150_000  # of the index in one Python worker; beyond it the index starts anew


def byte_alphabet() -> list[str]:
    """The public byte-level alphabet: printable bytes stand for themselves, others move up from 256."""
    plain = {*range(33, 127), *range(161, 173), *range(174, 256)}
    moved = (chr(256 + k) for k in range(256))
    return [chr(b) if b in plain else next(moved) for b in range(256)]


class _Index(dict):
    """Numbers words in the order they come."""

    def __missing__(self, word: str) -> int:
        self[word] = n = len(self)
        return n


class WordBpe:
    """Tokenizer of a word-level BPE file with a word-end suffix."""

    def __init__(self, path: str):
        with open(path, encoding="utf-8") as f:
            spec = json.load(f)
        model, vocab = spec["model"], spec["model"]["vocab"]
        end = model["end_of_word_suffix"] or ""
        alphabet = byte_alphabet()
        self.inner = np.array([vocab[c] for c in alphabet], np.int64)
        self.final = np.array([vocab[c + end] for c in alphabet], np.int64)
        self.specials = {t["content"]: t["id"] for t in spec["added_tokens"]}
        self.size = max([*vocab.values(), *self.specials.values()]) + 1
        pairs = [(vocab[a] * self.size + vocab[b], vocab[a + b]) for a, b in model["merges"]]
        keys = np.array([k for k, _ in pairs], np.int64)
        self.order = np.argsort(keys, kind="stable")
        self.keys = keys[self.order]
        self.merged = np.array([m for _, m in pairs], np.int64)
        self.tokens = np.full(self.size, "", object)
        for token, k in [*vocab.items(), *self.specials.items()]:
            self.tokens[k] = token
        split = next(p["pattern"]["Regex"] for p in spec["pre_tokenizer"]["pretokenizers"] if p["type"] == "Split")
        self.words = regex.compile(split)
        self.forget()
        self.special = regex.compile("(" + "|".join(map(regex.escape, self.specials)) + ")")

    def split(self, text: str) -> list[str]:
        """Words and special tokens of a whole text, in order."""
        out: list[str] = []
        for k, part in enumerate(self.special.split(text) if "<|" in text else [text]):
            if k % 2:
                out.append(part)
            elif part:
                # White space parts words and is no part of any, so it is not folded first.
                plain = part if part.isascii() else unicodedata.normalize("NFC", part).replace("Σ", "σ")
                out += self.words.findall(plain.lower())
        return out

    def encode_words(self, words: list[str]) -> tuple[np.ndarray, np.ndarray]:
        """Ids of many distinct words: one flat array and where each word starts in it."""
        raw = [w.encode("utf-8") for w in words]
        lengths = np.fromiter(map(len, raw), np.int64, len(raw))
        flat = np.frombuffer(b"".join(raw), np.uint8)
        ends = np.cumsum(lengths) - 1
        ids = self.inner[flat]
        ids[ends] = self.final[flat[ends]]
        owner = np.repeat(np.arange(len(raw)), lengths)
        done: list[tuple[np.ndarray, np.ndarray]] = []
        while len(ids):
            key = np.full(len(ids), -1, np.int64)
            inside = owner[:-1] == owner[1:]
            key[:-1][inside] = ids[:-1][inside] * self.size + ids[1:][inside]
            at = np.minimum(np.searchsorted(self.keys, key), len(self.keys) - 1)
            rank = np.where(self.keys[at] == key, self.order[at], _NONE)
            starts = np.flatnonzero(np.r_[True, owner[1:] != owner[:-1]])
            lowest = np.repeat(np.minimum.reduceat(rank, starts), np.diff(np.r_[starts, len(ids)]))
            over = lowest == _NONE
            if over.any():
                done.append((ids[over], owner[over]))
                live = ~over
                ids, owner, rank, lowest = ids[live], owner[live], rank[live], lowest[live]
                if not len(ids):
                    break
            hits = np.flatnonzero(rank == lowest)
            runs = np.r_[True, np.diff(hits) != 1]  # in "aaa" the pair at 0 wins over that at 1
            first = hits[runs][np.cumsum(runs) - 1]
            hits = hits[(hits - first) % 2 == 0]
            ids[hits] = self.merged[rank[hits]]
            keep = np.ones(len(ids), bool)
            keep[hits + 1] = False
            ids, owner = ids[keep], owner[keep]
        if done:
            ids, owner = np.concatenate([d[0] for d in done]), np.concatenate([d[1] for d in done])
            order = np.argsort(owner, kind="stable")
            ids, owner = ids[order], owner[order]
        return ids, np.searchsorted(owner, np.arange(len(raw) + 1))

    def encode_batch(self, texts: list[str]) -> list[np.ndarray]:
        """Ids of each text; a distinct word is encoded once while the index of words holds it."""
        if len(self.index) > MOST_WORDS:
            self.forget()
        known = len(self.index)
        codes = []
        for text in texts:
            words = self.split(text)
            codes.append(np.fromiter(map(self.index.__getitem__, words), np.int64, len(words)))
        if len(self.index) > known:
            words = list(itertools.islice(self.index, known, None))
            ids, starts = self.encode_words(["\u0000" if w in self.specials else w for w in words])
            begins, sizes = starts[:-1] + len(self.ids), np.diff(starts)
            for w in self.specials:
                if self.index.get(w, -1) >= known:
                    begins[self.index[w] - known], sizes[self.index[w] - known] = len(self.ids) + len(ids), 1
                    ids = np.r_[ids, self.specials[w]]
            self.ids, self.begins, self.sizes = (np.concatenate(x) for x in ((self.ids, ids), (self.begins, begins), (self.sizes, sizes)))
        out = []
        for c in codes:
            n = self.sizes[c]
            shift = np.repeat(self.begins[c] - (np.cumsum(n) - n), n)
            out.append(self.ids[shift + np.arange(len(shift))].astype("<u4"))
        return out

    def forget(self) -> None:
        """Empty the index of words."""
        self.index = _Index()
        self.ids = self.begins = self.sizes = np.empty(0, np.int64)

    def decode(self, ids: np.ndarray) -> str:
        """The file names no decoder: tokens are joined by spaces."""
        return " ".join(self.tokens[ids].tolist())


_LOADED: dict[str, WordBpe] = {}


def tokenizer(path: str) -> WordBpe:
    """One tokenizer per Python worker."""
    if path not in _LOADED:
        _LOADED[path] = WordBpe(path)
    return _LOADED[path]


def groups(texts: list[str], most: int = 2_000_000) -> Iterator[slice]:
    """Slices of consecutive texts with about ``most`` characters, one text at least."""
    begin = size = 0
    for k, text in enumerate(texts):
        size += len(text)
        if size >= most:
            yield slice(begin, k + 1)
            begin, size = k + 1, 0
    if begin < len(texts):
        yield slice(begin, len(texts))


def encode_documents(docs: DataFrame, path: str, *, decode: bool = True) -> DataFrame:
    """Rows ``(doc_id, n_tokens, ids, decoded)``: ids as little-endian 32-bit integers.

    ``decoded`` is null with ``decode=False``. The file at ``path`` must exist on every executor.
    """

    @lean
    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        bpe = tokenizer(path)
        for b in batches:
            texts = [t or "" for t in b["text"]]
            for part in groups(texts):
                ids = bpe.encode_batch(texts[part])
                yield pd.DataFrame(
                    {
                        "doc_id": b["doc_id"].iloc[part],
                        "n_tokens": [len(x) for x in ids],
                        "ids": [x.tobytes() for x in ids],
                        "decoded": [bpe.decode(x) if decode else None for x in ids],
                    }
                )
        bpe.forget()

    return map_frames(
        docs.select(F.col("doc_id").cast("long"), F.col("text").cast("string")), run, "doc_id long, n_tokens long, ids binary, decoded string"
    )


def decode_documents(encoded: DataFrame, path: str) -> DataFrame:
    """Rows ``(doc_id, text)`` from ``(doc_id, ids)``; null ids give null."""

    @lean
    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        bpe = tokenizer(path)
        for b in batches:
            yield pd.DataFrame({"doc_id": b["doc_id"], "text": [None if x is None else bpe.decode(np.frombuffer(x, "<u4")) for x in b["ids"]]})

    return map_frames(encoded.select("doc_id", "ids"), run, "doc_id long, text string")


