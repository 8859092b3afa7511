"""Plain versions of the operators, one document after another."""

import hashlib
import re
from collections import Counter, defaultdict

import numpy as np
import xxhash

LOWER = str.maketrans("ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz")
ALNUM = re.compile("[^\x00-\x2f\x3a-\x60\x7b-\x7f]+")
SPACED = re.compile("[^\x20\x09-\x0d]+")


def decontaminate(rows, items):
    windows = defaultdict(set)
    for i, t in items:
        w = ALNUM.findall((t or "").translate(LOWER))
        n = min(10, len(w))
        for k in range(len(w) - n + 1) if n else ():
            windows[tuple(w[k : k + n])].add("null" if i is None else str(i))
    sizes = {len(w) for w in windows}
    out = []
    for i, t in rows:
        w, hit, found = ALNUM.findall((t or "").translate(LOWER)), set(), set()
        for n in sizes:
            for k in range(len(w) - n + 1):
                if got := windows.get(tuple(w[k : k + n])):
                    hit |= set(range(k, k + n))
                    found |= got
        out.append((i, len(w), len(hit), len(found), hashlib.sha256(",".join(sorted(found)).encode()).hexdigest(), bool(hit)))
    return out


def base_counts(rows):
    out = []
    for i, t in rows:
        t = t or ""
        w = SPACED.findall(t)
        seen, dup = set(), 0
        for line in t.split("\n"):
            if SPACED.search(line):
                dup += line in seen
                seen.add(line)
        n = Counter(tuple(w[k : k + 5]) for k in range(len(w) - 4))
        rep = {p for k in range(len(w) - 4) if n[tuple(w[k : k + 5])] > 1 for p in range(k, k + 5)}
        out.append((i, len(w), sum(map(len, w)), len(re.findall(r"[#*$%&|<>]", t)), dup, len(rep), len(w) < 10 or 100 * len(rep) > 20 * len(w)))
    return out


def fingerprint(t):
    w = SPACED.findall((t or "").translate(LOWER))
    s = [" ".join(w[k : k + 3]) for k in range(len(w) - 2)] if len(w) >= 3 else [" ".join(w)] if w else []
    h = [xxhash.xxh64_intdigest(x.encode(), 42) for x in s]
    return sum(1 << b for b in range(64) if 2 * sum(x >> b & 1 for x in h) > len(h))


def components(n, linked):
    parent = list(range(n))

    def find(x):
        while parent[x] != x:
            x = parent[x]
        return x

    for a in range(n):
        for b in range(a):
            if linked(a, b):
                parent[find(a)] = find(b)
    return [find(x) for x in range(n)]


def simhash(rows):
    fps = [fingerprint(t) for _, t in rows]
    comp = components(len(rows), lambda a, b: (fps[a] ^ fps[b]).bit_count() <= 2)
    least = {}
    for c, (i, _) in zip(comp, rows):
        if i is not None:
            least[c] = min(i, least.get(c, i))
    return [(i, f"{f:016x}", least.get(c)) for c, (i, _), f in zip(comp, rows, fps)]


def repeats(rows, window=400):
    texts = [(t or "").encode() for _, t in rows]
    seen = Counter(t[k : k + window] for t in texts for k in range(len(t) - window + 1))
    out = []
    for (i, _), t in zip(rows, texts):
        d = np.zeros(len(t) + 1, int)
        for k in range(len(t) - window + 1):
            if seen[t[k : k + window]] > 1:
                d[k] += 1
                d[k + window] -= 1
        gone = np.cumsum(d)[: len(t)] > 0
        kept = bytes(b for b, g in zip(t, gone) if not g)
        spans = int(gone[:1].sum() + (gone[1:] & ~gone[:-1]).sum())
        out.append((i, len(t), int(gone.sum()), spans, hashlib.sha256(kept).hexdigest()))
    return out


def line_dedup(rows, min_chars=40, min_docs=5):
    key = lambda x: x.strip(" \t\n\x0b\x0c\r").translate(LOWER)
    low = lambda i: -(1 << 63) if i is None else i
    where = defaultdict(set)
    for i, t in rows:
        for x in (t or "").split("\n"):
            where[key(x)].add(low(i))
    out = []
    for i, t in rows:
        lines = (t or "").split("\n")
        kept = [x for x in lines if len(key(x)) < min_chars or len(where[key(x)]) < min_docs or max(where[key(x)]) == low(i)]
        out.append((i, len(lines), len(lines) - len(kept), "\n".join(kept)))
    return out


def near_survivors(rows, shingle=5, similarity=0.8):
    """One row of each component of texts by Jaccard similarity of their sets of windows: the smallest id, nulls last."""
    texts = sorted({t or "" for _, t in rows})
    sets = []
    for t in texts:
        w = SPACED.findall(t.translate(LOWER))
        sets.append({tuple(w[k : k + shingle]) for k in range(max(1, len(w) - shingle + 1))})
    comp = components(len(texts), lambda a, b: len(sets[a] & sets[b]) >= similarity * len(sets[a] | sets[b]))
    of, best = dict(zip(texts, comp)), {}
    for i, t in rows:
        c = of[t or ""]
        if c not in best or (i is None, i) < (best[c][0] is None, best[c][0]):
            best[c] = (i, t)
    return list(best.values())
