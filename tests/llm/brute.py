"""Plain versions of the operators' results, for small inputs."""

import hashlib
import re
from collections import Counter, defaultdict

import numpy as np

WORD = re.compile(r"[^\x20\x09-\x0D]+")


def words(text):
    return WORD.findall(text or "")


def near_duplicates(rows, size=2, percent=80):
    """{doc_id: (n_shingles, component)} by comparing all pairs that share a shingle."""
    low = str.maketrans("ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz")
    sets = {}
    for k, text in rows:
        w = words((text or "").translate(low))
        n = min(size, len(w))
        sets[k] = {tuple(w[i : i + n]) for i in range(len(w) - n + 1)} if w else set()
    root = {k: k for k in sets}

    def find(x):
        while root[x] != x:
            x = root[x]
        return x

    ids = sorted(k for k in sets if sets[k])
    for i, a in enumerate(ids):
        for b in ids[i + 1 :]:
            s, t = sets[a], sets[b]
            if 5 * min(len(s), len(t)) < 4 * max(len(s), len(t)):
                continue
            both = len(s & t)
            if 100 * both >= percent * (len(s) + len(t) - both):
                x, y = sorted((find(a), find(b)))
                root[y] = x
    return {k: (len(s), find(k)) for k, s in sets.items()}


def base_metrics(text):
    w = words(text)
    lines = [x for x in (text or "").split("\n") if words(x)]
    triples = [tuple(w[i : i + 3]) for i in range(len(w) - 2)]
    seen = Counter(triples)
    hit = {i + j for i, t in enumerate(triples) if seen[t] > 1 for j in range(3)}
    return len(w), sum(map(len, w)), sum(c in "#*$%&|<>" for c in text or ""), len(lines) - len(set(lines)), len(hit)


def cut_repeats(rows, length=50):
    """{doc_id: (n_bytes, n_removed, n_spans, sha)} with a dictionary of all strings."""
    first = {}
    raw = {k: (t or "").encode() for k, t in rows}
    for k, b in raw.items():
        for i in range(len(b) - length + 1):
            s = b[i : i + length]
            first[s] = min(first.get(s, k), k)
    out = {}
    for k, b in raw.items():
        gone = bytearray(len(b))
        for i in range(len(b) - length + 1):
            if first[b[i : i + length]] < k:
                gone[i : i + length] = b"\1" * length
        kept = bytes(c for c, g in zip(b, gone, strict=True) if not g)
        spans = len(re.findall(b"\1+", bytes(gone)))
        out[k] = (len(b), sum(gone), spans, hashlib.sha256(kept).hexdigest())
    return out


def base_secrets(text):
    """Counts per kind and the digest of base spans."""
    assign = r"""(password|passwd|secret|token|api_?key)["']?\x20*[:=]\x20*["']?([A-Za-z0-9+/_.=-]+)"""
    found = [(m.start(), 0, m.end()) for m in re.finditer(assign, text or "", re.I | re.A) if len(m[2]) >= 6]
    found += [(m.start(), 1, m.end()) for m in re.finditer("AKIA[A-Z0-9]+", text or "") if len(m[0]) >= 20]
    found += [(m.start(), 2, m.end()) for m in re.finditer("[0-9a-f]+", text or "") if len(m[0]) >= 24]
    found.sort()
    joined = ",".join(f"{('assign', 'access', 'hex')[k]}:{s}:{e}" for s, k, e in found)
    n = Counter(k for _, k, _ in found)
    return n[0], n[1], n[2], hashlib.sha256(joined.encode()).hexdigest()


def share_targets(sizes, weights=(3, 1, 2), share=1.5, most=2):
    names = sorted(sizes, key=lambda s: (s is None, s or ""))
    w = {s: weights[i % 3] for i, s in enumerate(names)}
    capped = defaultdict(bool)
    while True:
        left = share * sum(sizes.values()) - sum(most * sizes[s] for s in names if capped[s])
        whole = sum(w[s] for s in names if not capped[s])
        goal = {s: most * sizes[s] if capped[s] else left * w[s] / whole for s in names}
        over = [s for s in names if goal[s] > most * sizes[s]]
        if not over:
            return goal
        for s in over:
            capped[s] = True


def adaptive_kept(rows, prior=50):
    """{doc_id: kept} of ``(doc_id, lang, source, text)``: fences from sorted lists of weighted values."""
    def floor(v):
        size = 1
        while v // size >= 128:
            size *= 2
        return v // size * size

    found = {}
    for k, lang, source, text in rows:
        n, chars, symbols, dups, repeats = base_metrics(text)
        lines = max(1, sum(bool(words(x)) for x in (text or "").split("\n")))
        found[k] = (lang, source, n < 50 or 2 * repeats > n, [(symbols, max(n, 1), 1000), (repeats, max(n, 1), 1000), (dups, lines, 1000), (chars, max(n, 1), 100)])
    pick = lambda test: [x for x in found.values() if not x[2] and test(x)]
    share = lambda docs, m, weight: [(floor(x[3][m][2] * x[3][m][0] // x[3][m][1]), weight) for x in docs]

    def quantiles(lang, source, m, levels):
        every, of_lang, own = pick(lambda x: True), pick(lambda x: x[0] == lang), pick(lambda x: x[:2] == (lang, source))
        up = share(of_lang, m, 1) + share(every, m, prior / len(every))
        up = [(v, w * prior / (len(of_lang) + prior)) for v, w in up]
        total, out = len(own) + prior, []
        for q in levels:
            seen = 0
            for v, w in sorted(share(own, m, 1) + up):
                seen += w
                if seen >= total * (q - 1e-9):
                    break
            out.append(v)
        return out

    cache, kept = {}, {}
    for k, (lang, source, failed, values) in found.items():
        for m, levels in enumerate([(0.5, 0.8), (0.5, 0.99), (0.5, 0.99), (0.5, 0.9, 0.1)]):
            if (lang, source, m) not in cache and not failed:
                cache[lang, source, m] = quantiles(lang, source, m, levels)
        kept[k] = not failed
        for m, reach in enumerate((3, 1, 1, 2)):
            if kept[k]:
                count, out_of, scale = values[m]
                mid, high, *low = cache[lang, source, m]
                if low:
                    v = scale * count // out_of
                    kept[k] = low[0] - reach * (mid - low[0]) <= v <= high + reach * (high - mid)
                else:
                    kept[k] = count - 3 * count**0.5 <= out_of * (high + reach * (high - mid)) / scale
    return kept


def linked_secrets(text, scope=400):
    """Weak secrets and endpoints beside an access identifier, each part tried with each anchor."""
    base = [(m.start(), m.end(), "assign") for m in re.finditer(r"""(password|passwd|secret|token|api_?key)["']?\x20*[:=]\x20*["']?([A-Za-z0-9+/_.=-]+)""", text, re.I | re.A) if len(m[2]) >= 6]
    base += [(m.start(), m.end(), "access") for m in re.finditer("AKIA[A-Z0-9]+", text) if len(m[0]) >= 20]
    base += [(m.start(), m.end(), "hex") for m in re.finditer("[0-9a-f]+", text) if len(m[0]) >= 24]
    weak = []
    for m in re.finditer("[A-Za-z0-9+/_=-]{30,}", text):
        mixed = re.search("[0-9]", m[0]) and re.search("[A-Z]", m[0]) and re.search("[a-z]", m[0])
        if mixed and all(e <= m.start() or m.end() <= s for s, e, _ in base):
            weak.append((m.start(), m.end()))
    ends = [(m.start(), m.end()) for m in re.finditer(r"https?://[A-Za-z0-9.-]+\.[A-Za-z]{2,}[A-Za-z0-9./_-]*", text)]
    out = set()
    for s, e, kind in base:
        if kind == "access":
            near = lambda parts: {p for p in parts if s - scope <= p[0] < e + scope and p[1] <= e + scope}  # noqa: B023, E731
            out |= {(a, "secret", b) for a, b in near(weak)}
            if near(weak) or near([x[:2] for x in base if x[2] != "access"]):
                out |= {(a, "endpoint", b) for a, b in near(ends)}
    return out


class PlainWalk:
    """The edit embedding one step at a time, from the same shared random numbers."""

    def __init__(self, seed=11):
        rng = np.random.default_rng(seed)
        self.moves = rng.integers(0, 2, (256, 4096), dtype=np.uint8)
        self.moves[:, 4095] = 1
        self.minima = [[1] for _ in range(256)]
        while min(x[-1] for x in self.minima) < 2**45:
            for x, u in zip(self.minima, rng.random(256), strict=True):
                x.append(float(np.floor(x[-1] / u) + 1))
        self.salt = [int(x) for x in rng.integers(0, 2**63, 256, dtype=np.uint64)]

    def fingerprint(self, text):
        under, pointer = [], 0  # the pointer at each step
        while pointer < len(text):
            move = self.moves[ord(text[pointer]) % 256, len(under) % 4096]
            under.append(pointer)
            pointer += int(move)
        digits = []
        for salt, minima in zip(self.salt, self.minima, strict=True):
            value = salt
            if text:
                at = under[int(max(x for x in minima if x <= len(under))) - 1]
                value ^= sum(ord(c) << (21 * k) for k, c in enumerate(text[at : at + 3])) % 2**64
            value = (value ^ (value >> 31)) * 0x9E3779B97F4A7C15 % 2**64
            digits.append("%x" % (value >> 60))
        return "".join(digits)
