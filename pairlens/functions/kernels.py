"""Single-row kernels that built-in expressions can't express: LCS, ROUGE, stemming, centrality, loops. Plain Python and numpy."""

from __future__ import annotations

import re
from collections import Counter
from collections.abc import Callable
from decimal import ROUND_FLOOR, ROUND_HALF_UP, Decimal
from functools import lru_cache

import numpy as np

TOKEN, ASCII = re.compile(r"[^\W_]+"), re.compile(r"[a-z0-9]+")
MICRO = Decimal("0.000001")


@lru_cache(100_000)
def stem_de(word: str, keep_case: bool = False) -> str:
    """Suffix stripping for German. keep_case tells a capitalised word, whose t stays, from others."""
    capital = keep_case and word[:1].isupper()
    w = word.lower().translate(str.maketrans({"ü": "u", "ö": "o", "ä": "a"})).replace("ß", "ss")
    w = re.sub(r"^ge(.{4,})", r"\1", w)
    w = w.replace("sch", "$").replace("ei", "%").replace("ie", "&")
    w = re.sub(r"(.)\1", r"\1*", w)
    while len(w) > 3:
        if len(w) > 5 and re.search(r"(em|er|nd)$", w):
            w = w[:-2]
        elif (not capital and w.endswith("t")) or w.endswith(("e", "s", "n")):
            w = w[:-1]
        else:
            break
    w = re.sub(r"(.)\*", r"\1\1", w)
    return w.replace("$", "sch").replace("%", "ei").replace("&", "ie")


def tokenize(text: str | None, stem: str | None = None, ascii_only: bool = False) -> list[str]:
    toks = (ASCII if ascii_only else TOKEN).findall((text or "").lower())
    return [stem_de(t) for t in toks] if stem == "de" else toks


def lcs_length(a: list, b: list) -> int:
    """Bit-parallel: one integer of len(b) bits, a step per item of a."""
    if not a or not b:
        return 0
    at: dict = {}
    for j, x in enumerate(b):
        at[x] = at.get(x, 0) | 1 << j
    full = (1 << len(b)) - 1
    v = full
    for x in a:
        u = v & at.get(x, 0)
        v = ((v + u) | (v - u)) & full
    return len(b) - v.bit_count()


def substring_length(a: str, b: str) -> int:
    """Length of the longest common run of characters: a suffix automaton of the shorter text, a walk over the other."""
    if len(a) > len(b):
        a, b = b, a
    step: list[dict[str, int]] = [{}]
    link, size, last = [-1], [0], 0
    for c in a:
        new = len(step)
        step.append({})
        size.append(size[last] + 1)
        link.append(0)
        p = last
        while p >= 0 and c not in step[p]:
            step[p][c] = new
            p = link[p]
        if p >= 0:
            q = step[p][c]
            if size[p] + 1 != size[q]:
                twin = len(step)
                step.append(dict(step[q]))
                size.append(size[p] + 1)
                link.append(link[q])
                while p >= 0 and step[p].get(c) == q:
                    step[p][c] = twin
                    p = link[p]
                link[q] = twin
                q = twin
            link[new] = q
        last = new
    best = run = at = 0
    for c in b:
        while at and c not in step[at]:
            at = link[at]
            run = size[at]
        if c in step[at]:
            at, run = step[at][c], run + 1
        best = max(best, run)
    return best


def lcs_places(a: list, b: list) -> set[int]:
    """Places of b on one longest common subsequence."""
    n, m = len(a), len(b)
    t = np.zeros((n + 1, m + 1), np.int32)
    codes = {x: i for i, x in enumerate(dict.fromkeys([*a, *b]))}
    bb = np.array([codes[x] for x in b])
    for i, x in enumerate(a):
        t[i + 1, 1:] = np.maximum.accumulate(np.where(bb == codes[x], t[i, :-1] + 1, t[i, 1:]))
    out, i, j = set(), n, m
    while i and j:
        if a[i - 1] == b[j - 1]:
            out.add(j - 1)
            i, j = i - 1, j - 1
        elif t[i - 1, j] >= t[i, j - 1]:
            i -= 1
        else:
            j -= 1
    return out


def prf(hit: float, pred: int, target: int) -> tuple[float, float, float]:
    p, r = (hit / pred if pred else 0.0), (hit / target if target else 0.0)
    return p, r, 2 * p * r / (p + r) if p + r else 0.0


def rouge_n(pred: list[str], target: list[str], n: int) -> tuple[float, float, float]:
    a, b = (Counter(zip(*(x[i:] for i in range(n)), strict=False)) for x in (pred, target))
    return prf(sum((a & b).values()), sum(a.values()), sum(b.values()))


def rouge_l(pred: list[str], target: list[str]) -> tuple[float, float, float]:
    return prf(lcs_length(pred, target), len(pred), len(target))


def rouge_lsum(pred: list[list[str]], target: list[list[str]]) -> tuple[float, float, float]:
    """Per target sentence the union of places matched by any output sentence; hits are clipped by counts on both sides."""
    left, right = Counter(t for s in pred for t in s), Counter(t for s in target for t in s)
    hits = 0
    for sent in target:
        for j in sorted(set().union(*(lcs_places(p, sent) for p in pred)) if pred else ()):
            t = sent[j]
            if left[t] > 0 and right[t] > 0:
                hits, left[t], right[t] = hits + 1, left[t] - 1, right[t] - 1
    return prf(hits, sum(map(len, pred)), sum(map(len, target)))


def hashed_vectors(sentences: list[str], dim: int = 256, sizes: tuple[int, ...] = (3, 4, 5)) -> np.ndarray:
    """Signed hashed character n-grams, log-scaled and normalised: a stand-in for a trained sentence encoder. All
    sentences are counted at once; a gram of up to five bytes is its own number."""
    m = len(sentences)
    raws = [s.lower().encode() for s in sentences]
    lens = np.fromiter(map(len, raws), np.int64, m)
    buf = np.frombuffer(b"".join(raws), np.uint8).astype(np.uint64)
    owner, ends = np.repeat(np.arange(m), lens), np.repeat(np.cumsum(lens), lens)
    out = np.zeros(m * dim)
    for n in sizes:
        starts = np.flatnonzero(np.arange(len(buf)) + n <= ends)
        grams = np.zeros(len(starts), np.uint64)
        for j in range(n):
            grams = grams << np.uint64(8) | buf[starts + j]
        order = np.lexsort((grams, owner[starts]))
        g, o = grams[order], owner[starts][order]
        first = np.flatnonzero(np.r_[True, (g[1:] != g[:-1]) | (o[1:] != o[:-1])]) if len(g) else np.zeros(0, np.int64)
        count = np.diff(np.r_[first, len(g)])
        h = (g[first] + np.uint64(n)) * np.uint64(0x9E3779B97F4A7C15)
        h ^= h >> np.uint64(31)
        value = np.where(h >> np.uint64(63), 1.0, -1.0) * np.log1p(count)
        out += np.bincount(o[first] * dim + (h % np.uint64(dim)).astype(np.int64), value, m * dim)
    out = out.reshape(m, dim)
    norm = np.linalg.norm(out, axis=1, keepdims=True)
    return out / np.where(norm > 0, norm, 1)


def similarity(sentences: list[str], weights: str = "hashed", idf: dict[str, float] | None = None, encoder: Callable[[list[str]], np.ndarray] = hashed_vectors) -> np.ndarray:
    """Sentence graph: cosine of the encoder's vectors (weights hashed), of tf-idf counts, or word overlap by log lengths."""
    if weights == "hashed":
        v = encoder(sentences)
        s = v @ v.T
    else:
        toks = [tokenize(x) for x in sentences]
        if weights == "overlap":
            s = np.zeros((len(toks),) * 2)
            sets = [set(t) for t in toks]
            for i, a in enumerate(sets):
                for j, b in enumerate(sets[:i]):
                    base = np.log(len(a)) + np.log(len(b)) if a and b else 0
                    s[i, j] = s[j, i] = len(a & b) / base if base > 0 else 0.0
        else:
            vocab = {w: i for i, w in enumerate(dict.fromkeys(w for t in toks for w in t))}
            v = np.zeros((len(toks), max(1, len(vocab))))
            for i, t in enumerate(toks):
                for w in t:
                    v[i, vocab[w]] += (idf or {}).get(w, 1.0)
            norm = np.linalg.norm(v, axis=1, keepdims=True)
            v /= np.where(norm > 0, norm, 1)
            s = v @ v.T
    s = np.maximum(s, 0.0)
    np.fill_diagonal(s, 0.0)
    return s


def centrality(s: np.ndarray, graph: str = "continuous", threshold: float = 0.1, damping: float = 0.85, rounds: int = 50, enough: float = 1e-6) -> np.ndarray:
    m = len(s)
    if graph == "degree":
        return (s >= threshold).sum(1).astype(float)
    if graph == "threshold":
        s = (s >= threshold).astype(float)
    total = s.sum(1, keepdims=True)
    walk = np.where(total > 0, s / np.where(total > 0, total, 1), 1.0 / m)
    p = np.full(m, 1.0 / m)
    for _ in range(rounds):
        q = (1 - damping) / m + damping * walk.T @ p
        done = np.abs(q - p).sum() < enough
        p = q
        if done:
            break
    return p


def central_places(sentences: list[str], k: int, weights: str = "hashed", graph: str = "continuous", idf: dict | None = None, order: str = "document", encoder: Callable[[list[str]], np.ndarray] = hashed_vectors, **walk) -> list[int]:
    """Places of the k most central sentences, in document order or by rank; ties go to the earlier one. walk: threshold,
    damping, rounds and enough of the centrality."""
    if len(sentences) <= k and order == "document":
        return list(range(len(sentences)))
    p = np.round(centrality(similarity(sentences, weights, idf, encoder), graph, **walk), 9)
    top = np.lexsort((np.arange(len(p)), -p))[:k].tolist()
    return top if order == "rank" else sorted(top)


def reaches(s: np.ndarray, threshold: float, bound: float) -> np.ndarray:
    """Whether values rounded to six digits, halves away from zero, are at least threshold (NaN is); bound is the least
    value that is, up to its own rounding."""
    out = (s >= bound) | np.isnan(s)
    close = np.flatnonzero(np.abs(s - bound) <= 1e-9 * max(1.0, abs(bound)))
    values, at = np.unique(s[close], return_inverse=True)
    out[close] = np.array([float(Decimal(repr(x)).quantize(MICRO, ROUND_HALF_UP)) >= threshold for x in values.tolist()], bool)[at]
    return out


def open_places(flags: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Rows and columns of the few flags that are set; rows are whole words of eight flags."""
    words = flags.view(np.uint64)
    busy = np.flatnonzero(np.bitwise_or.reduce(words, axis=1))
    p, k = np.nonzero(words[busy] != 0)
    z, q = np.nonzero(words[busy[p], k].view(bool).reshape(-1, 8))
    return busy[p[z]], k[z] * 8 + q


def near_counts(a: np.ndarray, na: np.ndarray, b: np.ndarray, nb: np.ndarray, threshold: float, rows: int = 240, columns: int = 2040) -> tuple[np.ndarray, np.ndarray]:
    """Per row of a the copies of b's rows (nb of each) whose products with it, rounded to six digits, are at least
    threshold, and per row of b those of a's. Products are taken in the type of the vectors; those that its errors leave
    open are added up anew in doubles, from the first number to the last. rows: below 256 and columns: at most 2040, as
    eight counts go in a word."""
    least = Decimal(threshold).quantize(MICRO, ROUND_FLOOR)
    bound = float((least if float(least) >= threshold else least + MICRO) - MICRO / 2)
    error = 2 * (a.shape[1] + 4) * float(np.finfo(a.dtype).eps)
    with np.errstate(all="ignore"):
        sizes = [np.linalg.norm(x.astype(float), axis=1) for x in (a, b)]
    got = np.zeros(len(a), np.int64), np.zeros(len(b), np.int64)
    order = np.argsort(sizes[0], kind="stable")
    a, sizes[0], na = a[order], sizes[0][order], na[order]
    mine = np.zeros(len(a), np.int64)
    kind = np.float32 if max(na.sum(), nb.sum()) < 1 << 24 else np.float64  # whole numbers that it holds
    todo: list[tuple[np.ndarray, np.ndarray]] = []
    waiting = 0
    step = max(1, (1 << 17) // max(1, a.shape[1]))

    def settle() -> None:
        """Adds up the open products, some at a time."""
        p, q = (np.concatenate(x) for x in zip(*todo, strict=True))
        todo.clear()
        for i in range(0, len(p), step):
            x, y = p[i : i + step], q[i : i + step]
            t = np.zeros(len(x))
            with np.errstate(all="ignore"):
                products = a[x].astype(float) * b[y].astype(float)
                for k in range(a.shape[1]):
                    t += products[:, k]
                yes = reaches(t, threshold, bound)
            np.add.at(mine, x[yes], nb[y[yes]])
            np.add.at(got[1], y[yes], na[x[yes]])

    for lo in range(0, len(b), columns):
        y, ny = b[lo : lo + columns], nb[lo : lo + columns]
        m = len(y)
        more_y = np.flatnonzero(ny > 1)
        flags = [np.full((rows, -(-m // 8) * 8), x) for x in (False, True, False)]  # what fills the last word is not near and not open
        for at in range(0, len(a), rows):
            x, nx = a[at : at + rows], na[at : at + rows]
            near, less, undecided = (f[: len(x)] for f in flags)
            more_x = np.flatnonzero(nx > 1)
            with np.errstate(all="ignore"):
                s = x @ y.T
                slack = error * (sizes[0][at : at + rows].max() * sizes[1][lo : lo + columns] + abs(bound)) + 1e-30
                slack[~(slack < 1e30)] = np.nan
                if slack.max() <= 2 * slack.min():
                    slack = slack.max()
                np.greater_equal(s, (bound + slack).astype(s.dtype), out=near[:, :m])
                np.less(s, (bound - slack).astype(s.dtype), out=less[:, :m])
            np.equal(near, less, out=undecided)
            p, q = open_places(undecided)
            if len(p):
                todo.append((p + at, q + lo))
                waiting += len(p)
            mine[at : at + rows] += np.add.reduce(near.view(np.uint64), axis=1).view(np.uint8).reshape(-1, 8).sum(axis=1, dtype=np.int64)
            if len(more_y):
                mine[at : at + rows] += (near[:, more_y].astype(kind) @ (ny[more_y] - 1).astype(kind)).astype(np.int64)
            got[1][lo : lo + columns] += np.add.reduce(near.view(np.uint64), axis=0).view(np.uint8)[:m]
            if len(more_x):
                got[1][lo : lo + columns] += ((nx[more_x] - 1).astype(kind) @ near[more_x, :m].astype(kind)).astype(np.int64)
            if waiting > 1 << 16:
                settle()
                waiting = 0
    if todo:
        settle()
    got[0][order] = mine
    return got


def near_counts_within(a: np.ndarray, n: np.ndarray, threshold: float, small: int = 2040) -> np.ndarray:
    """near_counts of a with itself, each two of its halves, quarters and so on once."""
    if len(a) <= small:
        return near_counts(a, n, a, n, threshold)[0]
    m = len(a) // 2
    across = near_counts(a[:m], n[:m], a[m:], n[m:], threshold)
    return np.concatenate(across) + np.concatenate([near_counts_within(a[:m], n[:m], threshold, small), near_counts_within(a[m:], n[m:], threshold, small)])


def oracle_places(sentences: list[str], target: str, most: int) -> list[int]:
    """Greedy: adds the sentence that raises the extract's R-2 F1 most, until none does."""
    toks, goal = [tokenize(s) for s in sentences], tokenize(target)
    chosen: list[int] = []
    best = 0.0
    while len(chosen) < most:
        top = max(((rouge_n([t for i in sorted([*chosen, j]) for t in toks[i]], goal, 2)[2], -j) for j in range(len(toks)) if j not in chosen), default=(0.0, 0))
        if top[0] <= best + 1e-12:
            break
        best = top[0]
        chosen.append(-top[1])
    return sorted(chosen)


def loop_length(toks: list[str], max_period: int = 5) -> float:
    """Longest stretch that repeats a phrase of up to max_period tokens at once, in periods (1 where nothing repeats)."""
    best = 1.0 if toks else 0.0
    for p in range(1, max_period + 1):
        run = 0
        for i in range(p, len(toks)):
            run = run + 1 if toks[i] == toks[i - p] else 0
            best = max(best, (run + p) / p if run else best)
    return best


def block_repeats(toks: list[str], n: int = 3) -> list[str]:
    """Drops each token that would complete an n-gram already there."""
    out: list[str] = []
    seen: set[tuple] = set()
    for t in toks:
        gram = tuple([*out[1 - n :], t]) if n > 1 else (t,)
        if len(gram) == n and gram in seen:
            continue
        out.append(t)
        if len(gram) == n:
            seen.add(gram)
    return out


def fragments(ref: list[str], summ: list[str]) -> tuple[float, float]:
    """(coverage, density): greedy longest copied fragments; their share and the mean square of their lengths."""
    at: dict[str, list[int]] = {}
    for j, t in enumerate(ref):
        at.setdefault(t, []).append(j)
    i, lengths = 0, []
    while i < len(summ):
        best = 0
        for j in at.get(summ[i], ()):
            n = 0
            while i + n < len(summ) and j + n < len(ref) and summ[i + n] == ref[j + n]:
                n += 1
            best = max(best, n)
        if best:
            lengths.append(best)
        i += max(best, 1)
    n = len(summ) or 1
    return sum(lengths) / n, sum(x * x for x in lengths) / n
