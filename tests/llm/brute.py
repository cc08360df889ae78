"""Plain versions of the operators, for small inputs."""

import re
from collections import Counter

WORD = re.compile(r"[^\x20\x09-\x0D]+")
LOWER = str.maketrans({chr(c): chr(c + 32) for c in range(65, 91)})


def shingles(text, k):
    w = WORD.findall((text or "").translate(LOWER))
    if not w:
        return frozenset()
    return frozenset(tuple(w[i : i + k]) for i in range(max(1, len(w) - k + 1)))


def components(docs, k=4, percent=80):
    """{doc_id: (set size, component)} by comparing all pairs."""
    sets = {d: shingles(t, k) for d, t in docs}
    up = {d: d for d in sets}

    def top(x):
        while up[x] != x:
            x = up[x]
        return x

    ids = sorted(sets)
    for i, a in enumerate(ids):
        for b in ids[i + 1 :]:
            x, y = sets[a], sets[b]
            if x and y and 10 * min(len(x), len(y)) >= 7 * max(len(x), len(y)):
                n = len(x & y)
                if 100 * n >= percent * (len(x) + len(y) - n):
                    p, q = top(a), top(b)
                    up[max(p, q)] = min(p, q)
    return {d: (len(s), top(d)) for d, s in sets.items()}


def stats(text):
    text = text or ""
    w = WORD.findall(text)
    seen = Counter(tuple(w[i : i + 5]) for i in range(len(w) - 4))
    covered = {j for i in range(len(w) - 4) if seen[tuple(w[i : i + 5])] > 1 for j in range(i, i + 5)}
    lines = [x for x in text.split("\n") if WORD.search(x)]
    return len(w), sum(map(len, w)), len(re.findall(r"[#*$%&|<>]", text)), len(lines) - len(set(lines)), len(covered)


def removed(docs, n=50):
    """{doc_id: set of removed byte positions} for the suffix-array operator."""
    first, out = {}, {}
    for d, t in sorted(docs):
        b = (t or "").encode()
        for i in range(len(b) - n + 1):
            first.setdefault(b[i : i + n], d)
    for d, t in docs:
        b = (t or "").encode()
        out[d] = {j for i in range(len(b) - n + 1) if first[b[i : i + n]] < d for j in range(i, i + n)}
    return out


def near_pairs(docs, words=50, k=5, similarity=0.8):
    """{(later, earlier)} of documents with two passages of so many words whose shingle sets are that similar."""
    import numpy as np

    ids: dict = {}
    rows = []
    for d, t in sorted(docs):
        w = WORD.findall((t or "").translate(LOWER))
        rows.append((d, np.array([ids.setdefault(tuple(w[i : i + k]), len(ids)) for i in range(len(w) - k + 1)], np.int64)))
    n, out = words - k + 1, set()
    for i, (a, x) in enumerate(rows):
        for b, y in rows[i + 1 :]:
            if min(len(x), len(y)) < n or not len(np.intersect1d(x, y)):
                continue
            both = np.zeros((len(x) + 1, len(y) + 1), np.int32)
            both[1:, 1:] = (x[:, None] == y[None, :]).cumsum(0).cumsum(1)  # shingles don't repeat in these documents
            shared = both[n:, n:] - both[:-n, n:] - both[n:, :-n] + both[:-n, :-n]
            if (shared >= similarity * (2 * n - shared)).any():
                out.add((b, a))
    return out
