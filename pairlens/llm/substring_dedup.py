"""Near-duplicate passages by compact windows.

A text is its sequence of word shingles. Under one hash function the least hash of a subsequence is at one shingle c,
and all subsequences within (l, c, r), the node of c in the Cartesian tree over the hashes, share it. Nodes of at
least a passage's width are few, about 2 n / width, and stand for all passages of that length or more.

1. Every text gives its nodes under some hash functions.
2. Nodes with one signature (function and hash) meet. The least document stands for the signature; every other one is
   joined with it, if the two windows, laid over each other at c, have a passage's width in common.
3. Joined windows on one diagonal of a pair of documents become one region, which is verified on the shingles: passages
   stand where a window of the set width shares enough of them, up to a few places off the diagonal.
4. Windows that aren't near the least document's, or reach past what is, may be near another's: passages that no
   verified span has are compared with the other windows of the signature, from the least document on, until they are
   covered or have met all of them. Windows
   whose shingles the rest of the signature doesn't have are set aside first.
"""

from __future__ import annotations

import math
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from pairlens.llm.cells import blocks, cells
from pairlens.llm.shared import Scratch
from pairlens.llm.textkernel import Words, chunks_of_bytes, mix, running, span_hash

_rng = np.random.Generator(np.random.PCG64(11))
SALTS = _rng.integers(1, 2**63, 64, dtype=np.uint64) * np.uint64(2) + np.uint64(1)
#: Tables of minima go up to so many places; wider windows are found by repeated steps.
TOP_LEVEL = 10
#: Windows of a signature that ask, and windows of it in all, in one cell.
QUERIES, MEMBERS = 4_096, 16_384


@dataclass(frozen=True)
class Settings:
    #: Least words of a passage.
    words: int = 50
    shingle: int = 5
    #: Jaccard similarity of the shingles of two passages, from which they are near duplicates.
    similarity: float = 0.8
    #: Hash functions: at the least similarity a passage has no signature in common with a chance of 0.2**4.
    functions: int = 4
    #: Places that words may be shifted inside a passage, by inserted or dropped words.
    shift: int = 5

    @property
    def width(self) -> int:
        return self.words - self.shingle + 1

    @property
    def shared(self) -> int:
        """Shingles that two passages of the least width share at the least similarity."""
        return math.ceil(2 * self.width * self.similarity / (1 + self.similarity) - 1e-9)


def _sliding(v: np.ndarray, width: int, best=np.minimum) -> np.ndarray:
    m, k = v.copy(), 1
    while 2 * k <= width:
        m[:-k] = best(m[:-k], m[k:])
        k *= 2
    if width > k:
        m[: k - width] = best(m[: k - width], m[width - k :])
    return m[: len(v) - width + 1]


def nodes(values: np.ndarray, width: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(l, c, r), both ends included, of the nodes of the Cartesian tree that are width wide or more: the subsequences
    within l to r that have c stand for c's value, and c is the first place that has it. So each subsequence has one
    node, however often its least value is repeated. Zeros part texts."""
    none = np.zeros(0, np.int64)
    if len(values) < width:
        return none, none, none
    least = _sliding(values, width)
    edge = np.zeros(width - 1, np.uint64)
    top = _sliding(np.concatenate([edge, least, edge]), width, np.maximum)
    c = np.flatnonzero((values > 0) & (top == values))
    own = values[c]
    levels = [values]
    while len(levels) <= TOP_LEVEL and 2 << len(levels) - 1 <= len(values):
        m, k = levels[-1], 1 << len(levels) - 1
        levels.append(np.minimum(m[:-k], m[k:]))
    l, r = c.copy(), c + 1  # noqa: E741
    for j in (*reversed(range(len(levels))),):
        m, k = levels[j], 1 << j
        again = True
        while again:
            to = l - k
            ok = (to >= 0) & (m[np.clip(to, 0, len(m) - 1)] > own)
            l[ok] -= k
            go = (r < len(m)) & (m[np.minimum(r, len(m) - 1)] >= own)
            r[go] += k
            again = j == len(levels) - 1 and bool(ok.any() or go.any())
    wide = r - l >= width
    return l[wide], c[wide], r[wide] - 1


def _spread(values: np.ndarray, c: np.ndarray, s: Settings) -> np.ndarray:
    """Which nodes stay. A phrase said over and over gives a text many nodes of one value: of those within the places
    that words may be shifted the first stays, and of those with the same surroundings one in each width. The passages
    of the others lie in the spans of those that stay."""
    stay, text = np.ones(len(c), bool), np.cumsum(values == 0)[c]
    by = np.lexsort((c, values[c], text))
    again = np.zeros(len(c), bool)
    again[1:] = (text[by[1:]] == text[by[:-1]]) & (values[c[by[1:]]] == values[c[by[:-1]]])
    if not again.any():
        return stay
    again[:-1] |= again[1:]
    twins = by[again]  # in order of text, value, place
    at = c[twins]
    around = span_hash(running(values), np.maximum(at - s.width, 0), np.minimum(at + s.width, len(values)))
    same = (values[at[1:]] == values[at[:-1]]) & (text[twins[1:]] == text[twins[:-1]])
    same &= (at[1:] // s.shift == at[:-1] // s.shift) | (around[1:] == around[:-1]) & (at[1:] // (s.width - s.shift) == at[:-1] // (s.width - s.shift))
    stay[twins[1:][same]] = False
    return stay


def _shingled(part: list[bytes], s: Settings) -> tuple[np.ndarray, np.ndarray]:
    """(hashes, bounds by text); texts without a whole shingle have none."""
    w = Words(part)
    hashes, _, bounds = w.shingles(s.shingle)
    n = np.diff(w.first)
    short = (n > 0) & (n < s.shingle)
    if short.any():
        keep = np.ones(len(hashes), bool)
        keep[bounds[:-1][short]] = False
        hashes, bounds = hashes[keep], np.concatenate([[0], np.cumsum(np.diff(bounds) - short)])
    return hashes, bounds


def compact_windows(docs: DataFrame, s: Settings, text: str, key: str) -> DataFrame:
    """sig, key, c, l, r: places of shingles from 0."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            keys, done = batch.column(0).to_numpy(), 0
            for part in chunks_of_bytes(batch.column(1)):
                hashes, bounds = _shingled(part, s)
                n = np.diff(bounds)
                text_of = np.repeat(np.arange(len(part)), n)
                place = np.arange(len(hashes)) + text_of + 1
                bases = bounds[:-1] + np.arange(len(part)) + 1
                cols: list[list] = [[], [], [], [], []]
                for f in range(s.functions):
                    v = np.zeros(len(hashes) + len(part) + 1, np.uint64)
                    v[place] = mix(hashes ^ SALTS[f]) | np.uint64(1)
                    stay = _spread(v, (found := nodes(v, s.width))[1], s)
                    l, c, r = (x[stay] for x in found)  # noqa: E741
                    at = np.searchsorted(bases, c, side="right") - 1
                    base = bases[at]
                    for x, y in zip(cols, (mix(v[c] ^ np.uint64(f)).view(np.int64), keys[done + at], c - base, l - base, r - base), strict=True):
                        x.append(y)
                done += len(part)
                sig, k, c, l, r = (np.concatenate(x) for x in cols)  # noqa: E741
                yield pa.RecordBatch.from_arrays([pa.array(sig), pa.array(k, batch.column(0).type), *(pa.array(x.astype(np.int32)) for x in (c, l, r))], names=["sig", "key", "c", "l", "r"])

    kind = docs.schema[key].dataType.simpleString()
    plain = docs.where(F.col(key).isNotNull() & F.col(text).isNotNull()).select(F.col(key).alias("key"), F.col(text).cast("binary").alias("text"))
    return plain.mapInArrow(run, f"sig bigint, key {kind}, c int, l int, r int")


def _met(windows: DataFrame, s: Settings, kind: str) -> DataFrame:
    """a, key, diag, c, lo, hi, sig, l, r: windows (key) joined with that of the least document (a) of their signature
    where the two have a passage's width in common. A window that is alone with the least one has no sig; one that isn't
    and has less in common with it, or is a further one of the least document, comes with lo past hi, for the others of
    its signature. The windows are shuffled once and come sorted, so a signature of any number of documents passes by its first one without being
    held."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        last: tuple | None = None
        for b in batches:
            sig, key, c, l, r = (b.column(i).to_numpy() for i in range(5))  # noqa: E741
            if not len(sig):
                continue
            new = np.ones(len(sig), bool)
            new[1:] = sig[1:] != sig[:-1]
            new[0] = last is None or sig[0] != last[0]
            head = np.maximum.accumulate(np.where(new, np.arange(len(sig)), -1))
            a, ca, la, ra = (np.where(head >= 0, x[np.maximum(head, 0)], last[i + 1] if last else 0) for i, x in enumerate((key, c, l, r)))
            diag = c - ca
            lo, hi = np.maximum(l, la + diag), np.minimum(r, ra + diag)
            wide = hi - lo + 1 >= s.width
            lone = np.zeros(len(sig), bool)
            lone[1:-1] = new[:-2] & ~new[1:-1] & new[2:]
            wide &= key > a
            ok = wide | ~lone & ~new
            hi = np.where(wide, hi, lo - 1)
            own = [pa.array(a[ok].astype(key.dtype), b.column(1).type), pa.array(key[ok], b.column(1).type), *(pa.array(x[ok].astype(np.int32)) for x in (diag, c, lo, hi))]
            yield pa.RecordBatch.from_arrays([*own, pa.array(sig[ok], mask=lone[ok]), *(pa.array(x[ok].astype(np.int32)) for x in (l, r))], names=["a", "key", "diag", "c", "lo", "hi", "sig", "l", "r"])
            last = (sig[-1], a[-1], ca[-1], la[-1], ra[-1])

    rows = windows.repartition("sig").sortWithinPartitions("sig", "key", "c")
    return rows.mapInArrow(run, f"a {kind}, key {kind}, diag int, c int, lo int, hi int, sig bigint, l int, r int")


def _sequences(docs: DataFrame, s: Settings, text: str, key: str) -> DataFrame:
    """key and 4 bytes of each shingle's hash, in order."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            done = 0
            for part in chunks_of_bytes(batch.column(1)):
                hashes, bounds = _shingled(part, s)
                seqs = [hashes[a:b].astype("<u4").tobytes() for a, b in zip(bounds[:-1].tolist(), bounds[1:].tolist(), strict=True)]
                yield pa.RecordBatch.from_arrays([batch.column(0).slice(done, len(part)), pa.array(seqs, pa.binary())], names=["key", "seq"])
                done += len(part)

    kind = docs.schema[key].dataType.simpleString()
    return docs.select(F.col(key).alias("key"), F.col(text).cast("binary").alias("text")).mapInArrow(run, f"key {kind}, seq binary")


def _verified(x: bytes, lo: int, y: bytes, diag: int, s: Settings) -> list[tuple[int, int, float]]:
    """verify() of shingles as bytes; equal parts are seen at once."""
    n, at = len(x) // 4, 4 * (lo - diag)
    if n >= s.width and at >= 0 and y[at : at + len(x)] == x:
        return [(lo, lo + n - 1, 1.0)]
    return verify(np.frombuffer(x, "<u4"), lo, np.frombuffer(y, "<u4"), diag, s)


def verify(part: np.ndarray, lo: int, y: np.ndarray, diag: int, s: Settings) -> list[tuple[int, int, float]]:
    """(first, last shingle, similarity) of the passages in a part of a text, from place lo on, that y has near the diagonal."""
    if len(part) < s.width:
        return []
    found = np.zeros(len(part), bool)
    for d in range(-s.shift, s.shift + 1):
        a = lo - diag + d
        p, q = max(a, 0), min(a + len(part), len(y))
        if q > p:
            found[p - a : q - a] |= part[p - a : q - a] == y[p:q]
    sums = np.concatenate([[0], np.cumsum(found)])
    per = sums[s.width :] - sums[: -s.width]
    good = np.flatnonzero(per >= s.shared)
    if not len(good):
        return []
    new = np.flatnonzero(np.concatenate([[True], np.diff(good) > s.width]))
    out = []
    for a, b in zip(new.tolist(), [*new[1:].tolist(), len(good)], strict=True):
        most = int(per[good[a:b]].max())
        inside = np.flatnonzero(found[good[a] : good[b - 1] + s.width]) + int(good[a])
        out.append((lo + int(inside[0]), lo + int(inside[-1]), most / (2 * s.width - most)))
    return out


def _starts(lo: int, hi: int, spans: list[tuple[int, int]], s: Settings) -> list[int]:
    """Starts of passages within lo to hi that no span has, up to the places that may differ: first, last, first, last and so on."""
    at, end, out = lo, hi - s.width + 1, []
    for p, q in sorted((p - s.width + s.shared, q - s.shared + 1) for p, q in spans):
        if p > q or q < at:
            continue
        if p > end:
            break
        if p > at:
            out += [at, p - 1]
        at = q + 1
    return out + [at, end] if at <= end else out


def _flat(lists: pa.ListArray) -> tuple[np.ndarray, list[pa.Array]]:
    """(row of each element, the fields of the elements) of a column of lists of structs."""
    n = pc.list_value_length(lists).to_numpy(zero_copy_only=False)
    return np.repeat(np.arange(len(n)), n), lists.flatten().flatten()


def _lists(row: np.ndarray, rows: int, fields: dict[str, pa.Array]) -> pa.ListArray:
    """The reverse of _flat: elements are sorted by row."""
    at = np.concatenate([[0], np.cumsum(np.bincount(row, minlength=rows))]).astype(np.int32)
    return pa.ListArray.from_arrays(pa.array(at), pa.StructArray.from_arrays(list(fields.values()), names=list(fields)))


def _regions(pair: np.ndarray, diag: np.ndarray, lo: np.ndarray, hi: np.ndarray) -> tuple[np.ndarray, ...]:
    """(pair, diag, lo, hi) of the unions of windows of one pair and diagonal that touch, sorted."""
    order = np.lexsort((lo, diag, pair))
    pair, diag, lo, hi = (x[order].astype(np.int64) for x in (pair, diag, lo, hi))
    new = np.ones(len(pair), bool)
    new[1:] = (pair[1:] != pair[:-1]) | (diag[1:] != diag[:-1])
    group = np.cumsum(new) << 32
    reach = np.maximum.accumulate(hi + group) - group
    new[1:] |= lo[1:] > reach[:-1] + 1
    head = np.flatnonzero(new)
    return pair[head], diag[head], lo[head], reach[np.concatenate([head[1:], [len(pair)]]) - 1] if len(head) else reach


def _far_first(regions: list[tuple[int, int, bytes]], width: int) -> list[tuple[int, int, bytes]]:
    """Regions (lo, diag, shingles) a passage apart, then those between them: a text that repeats a phrase has one
    region for each repeat, and those in between add nothing once their neighbours are known."""
    first, rest, end = [], [], -1
    for z in sorted(regions):
        if z[0] > end:
            first.append(z)
            end = z[0] + max(width, len(z[2]) // 4 - width)
        else:
            rest.append(z)
    return first + rest


def _with(spans: list[tuple[int, int]], lo: int, hi: int, width: int) -> list[tuple[int, int]]:
    """Sorted spans with one more; spans that have a passage's width less one place in common grow together, as every
    passage of the two then lies in one of them."""
    out = []
    for p, q in spans:
        if q - lo + 1 >= width - 1 and hi - p + 1 >= width - 1:
            lo, hi = min(lo, p), max(hi, q)
        else:
            out.append((p, q))
    return sorted([*out, (lo, hi)])


def _solve(cell: np.ndarray, key: np.ndarray, ints: list[np.ndarray], loose: list[list[int] | None], xs: list[np.ndarray], s: Settings) -> list[tuple]:
    """(a, key, start, stop, shift, similarity) among the windows of whole cells, sorted by cell."""
    c, at, lo, hi = ints
    size = np.array([len(x) for x in xs])
    rows = np.flatnonzero(size >= s.width)
    asks = np.array([bool(x) for x in loose])
    while len(rows):
        # shingles that another window of the cell has; a passage needs so many of them
        bits = max(1, int(len(rows) - 1).bit_length())
        row = np.repeat(np.arange(len(rows), dtype=np.uint64), size[rows])
        group = np.cumsum(np.concatenate([[0], np.diff(cell[rows]) != 0])).astype(np.uint64)
        flat = np.concatenate([xs[i] for i in rows.tolist()])
        marks = mix(np.repeat(group, size[rows]) << np.uint64(32) | flat) >> np.uint64(bits) << np.uint64(bits)
        order = np.sort(marks | row)
        v = order >> np.uint64(bits)
        cut = np.flatnonzero(np.concatenate([[True], v[1:] != v[:-1]]))
        last = np.concatenate([cut[1:], [len(v)]]) - 1
        row_of = (order & np.uint64((1 << bits) - 1)).astype(np.int64)
        common = np.repeat(row_of[cut] != row_of[last], last - cut + 1)
        stay = np.bincount(row_of[common], minlength=len(rows)) >= s.shared
        # a cell needs one that asks and another
        n, n_asks = (np.bincount(group.astype(np.int64), x) for x in (stay, stay & asks[rows]))
        stay &= ((n > 1) & (n_asks > 0))[group.astype(np.int64)]
        if stay.all():
            break
        rows = rows[stay]
    out: list[tuple] = []
    if not len(rows):
        return out
    shared = v[cut[row_of[cut] != row_of[last]]]
    todo: dict[int, np.ndarray] = {}
    ends = np.cumsum(size[rows]).tolist()
    for i, end in zip(rows.tolist(), ends, strict=True):
        if asks[i]:
            own = marks[end - size[i] : end][lo[i] - at[i] : hi[i] - at[i] + 1] >> np.uint64(bits)
            found = shared[np.minimum(np.searchsorted(shared, own), len(shared) - 1)] == own
            sums = np.concatenate([[0], np.cumsum(found)])
            ask = np.zeros(len(sums) - s.width, bool)
            for p, q in zip(loose[i][::2], loose[i][1::2], strict=True):
                ask[p - lo[i] : q - lo[i] + 1] = True
            ask &= sums[s.width :] - sums[: -s.width] >= s.shared
            if ask.any():
                todo[i] = ask
    bounds = np.flatnonzero(np.concatenate([[True], np.diff(cell[rows]) != 0, [True]]))
    for p, q in zip(bounds[:-1].tolist(), bounds[1:].tolist(), strict=True):
        mine = rows[p:q]
        open_ = [i for i in mine.tolist() if i in todo]
        if not open_:
            continue
        many = _Aligned(mine, key, c, at, xs, s) if len(mine) * len(open_) > 24 else None
        for j in open_:
            ask, part = todo[j], xs[j][lo[j] - at[j] : hi[j] - at[j] + 1]
            others = mine[key[mine] < key[j]].tolist() if many is None else many.near(j, part, int(lo[j]), ask)
            for i in others:
                diag = int(c[j] - c[i])
                for x, y, sim in _verified(part.tobytes(), int(lo[j]), xs[i].tobytes(), diag + int(at[i]), s):
                    first = max(0, x - s.width + s.shared - int(lo[j]))
                    has = ask[first : max(first, y - s.shared + 2 - int(lo[j]))]
                    if has.any():
                        out.append((key[i].item(), key[j].item(), x, y, diag, sim))
                        has[:] = False
                if not ask.any():
                    break
    return out


class _Aligned:
    """The windows of a cell as rows of one matrix, laid over each other at c, their shingles numbered. Windows that
    have the most in common with all come first, as they are the likeliest partners."""

    def __init__(self, mine: np.ndarray, key: np.ndarray, c: np.ndarray, at: np.ndarray, xs: list[np.ndarray], s: Settings):
        self.s, self.key, self.c = s, key, c
        self.off = s.width + 2 * s.shift - 1
        size = np.array([len(xs[i]) for i in mine.tolist()])
        kinds, ids, count = np.unique(np.concatenate([xs[i] for i in mine.tolist()]), return_inverse=True, return_counts=True)
        self.none, self.count, row = len(kinds), count, np.repeat(np.arange(len(mine)), size)
        order = np.argsort(-np.bincount(row, count[ids].astype(np.float64)), kind="stable")
        to = np.empty(len(mine), np.int64)
        to[order] = np.arange(len(mine))
        self.mine, self.place = mine[order], dict(zip(mine.tolist(), to.tolist(), strict=True))
        place = np.arange(len(ids)) - np.repeat(np.cumsum(size) - size, size) + np.repeat(at[mine] - c[mine] + self.off, size)
        self.ids = np.full((len(mine), 2 * self.off + 1), self.none, np.int32)
        self.ids[to[row], place] = ids
        self.rows_of, self.first = to[row[np.argsort(ids, kind="stable")]], np.concatenate([[0], np.cumsum(count)])
        self.known: dict[tuple, tuple] = {}

    def near(self, j: int, part: np.ndarray, lo: int, ask: np.ndarray) -> Iterator[int]:
        """Windows of smaller keys that have passages which window j still asks for; ask shrinks between two of them.
        A window that equals an earlier one has that one, or in the same text that one's partners."""
        left = lo - int(self.c[j]) + self.off
        own = self.ids[self.place[j], left : left + len(part)]
        twin = self.known.get((left, part.tobytes()))
        if twin and self.key[twin[0]] < self.key[j]:
            yield twin[0]
        elif twin and not (ask & ~twin[1]).any():
            yield from twin[2]
            return
        partners: list[int] = []
        self.known.setdefault((left, part.tobytes()), (j, ask.copy(), partners))
        for i in self.search(j, own, left, ask) if ask.any() else ():
            partners.append(i)
            yield i

    def candidates(self, own: np.ndarray, ask: np.ndarray) -> np.ndarray:
        """Rows that have one of the rarest shingles of a passage asked for: as at most width - shared of a passage's
        shingles may be missing, one of any width - shared + 1 of them is in a partner."""
        s = self.s
        starts, rare = np.flatnonzero(ask), s.width - s.shared
        view = np.lib.stride_tricks.sliding_window_view(self.count[own], s.width)[starts]
        pick = view <= np.partition(view, rare, axis=1)[:, rare, None]
        some = np.unique(own[(starts[:, None] + np.arange(s.width))[pick]])
        n = self.count[some]
        if n.sum() > 4 * len(self.mine):
            return np.arange(len(self.mine))
        return np.unique(self.rows_of[np.arange(n.sum()) + np.repeat(self.first[some] - np.cumsum(n) + n, n)])

    def search(self, j: int, own: np.ndarray, left: int, ask: np.ndarray) -> Iterator[int]:
        s, rows = self.s, self.candidates(own, ask)
        rows = rows[self.key[self.mine[rows]] < self.key[j]]
        done, step = 0, 32
        while done < len(rows) and ask.any():
            some = rows[done : done + step]
            done, step = done + step, min(4 * step, 2048)
            found = np.zeros((len(some), len(own) + 1), bool)
            for d in range(-s.shift, s.shift + 1):
                p, q = max(left + d, 0), min(left + d + len(own), self.ids.shape[1])
                found[:, 1 + p - left - d : 1 + q - left - d] |= self.ids[some, p:q] == own[p - left - d : q - left - d]
            sums = np.cumsum(found, axis=1, dtype=np.int16)
            good = sums[:, s.width :] - sums[:, : -s.width] >= s.shared
            for i in np.flatnonzero((good & ask).any(1)).tolist():
                if (good[i] & ask).any():
                    yield int(self.mine[some[i]])
                if not ask.any():
                    break


def _rounds(nodes_: DataFrame, seqs: DataFrame, s: Settings, kind: str) -> DataFrame:
    """a, key, start, stop, shift, similarity: windows with passages that no span has (they start in loose), compared with the others of their
    signature, in cells. Only signatures where a loose window isn't the least one's are looked at."""
    far = s.width + s.shift - 1
    asks = F.size("loose") > 0
    asked = nodes_.groupBy("sig").agg(F.min("key").alias("least"), F.max(F.when(asks, F.col("key"))).alias("most"), F.count_if(asks).alias("mine"), F.count(F.lit(1)).alias("total")).where("least < most").drop("least", "most")
    # how many blocks a signature has goes along, so the cut windows are shuffled once
    counted = nodes_.join(asked, "sig").select("sig", "key", "c", "l", "r", "loose", blocks("mine", QUERIES).alias("mine"), blocks("total", MEMBERS).alias("total"))
    mine = counted.groupBy("key").agg(F.collect_list(F.struct("sig", "c", "l", "r", "loose", "mine", "total")).alias("w"))

    def cut(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            row, (sig, c, l, r, loose, mine, total) = _flat(batch.column(1))  # noqa: E741
            raws, c = batch.column(2).to_pylist(), c.to_numpy().astype(np.int64)
            at, end, lazy = np.maximum(c - far, 0), c + far + 1, (pc.list_value_length(loose).to_numpy() == 0).tolist()
            seen: set = set()
            xs, stay = [], np.ones(len(c), bool)
            for i, (k, p, q, z) in enumerate(zip(row.tolist(), at.tolist(), end.tolist(), lazy, strict=True)):
                x = raws[k][4 * p : 4 * q]
                if z:  # a text that repeats a phrase offers each surrounding once
                    mark = (k, sig[i], x)
                    if mark in seen:
                        stay[i] = False
                        continue
                    seen.add(mark)
                xs.append(x)
            lo, hi = np.maximum(l.to_numpy(), c - s.width + 1), np.minimum(r.to_numpy(), c + s.width - 1)
            where = pa.array(np.flatnonzero(stay))
            ints = [pa.array(x[stay].astype(np.int32)) for x in (c, at, lo, hi)]
            out = pa.RecordBatch.from_arrays([sig.take(where), batch.column(0).take(pa.array(row[stay])), *ints, loose.take(where), mine.take(where), total.take(where), pa.array(xs, pa.binary())], names=["bucket", "id", "c", "at", "lo", "hi", "loose", "mine", "total", "x"])
            for i in range(0, out.num_rows, 20_000):
                yield out.slice(i, 20_000)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: list[pa.RecordBatch] = []

        def solved(rows: list[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            whole = pa.Table.from_batches(rows).combine_chunks()
            cols = [whole.column(i).to_numpy() for i in range(8)]
            new = np.ones(whole.num_rows, bool)
            new[1:] = np.any([x[1:] != x[:-1] for x in cols[:3]], axis=0)
            xs = [np.frombuffer(x.as_buffer(), "<u4") for x in whole.column(9)]
            out = _solve(np.cumsum(new), cols[3], cols[4:8], whole.column(8).to_pylist(), xs, s)
            k = rows[0].column(3).type
            for i in range(0, len(out), 100_000):
                z = list(zip(*out[i : i + 100_000], strict=True))
                yield pa.RecordBatch.from_arrays([pa.array(z[0], k), pa.array(z[1], k), *(pa.array(z[j], pa.int32()) for j in (2, 3, 4)), pa.array(z[5], pa.float64())], names=["a", "key", "start", "stop", "shift", "similarity"])

        for b in batches:
            if not b.num_rows:
                continue
            cells_ = [b.column(i).to_numpy() for i in range(3)]
            last = int(np.flatnonzero(np.concatenate([[True], np.any([x[1:] != x[:-1] for x in cells_], axis=0)]))[-1])
            if held and last == 0 and all(x[0] == held[-1].column(i)[-1].as_py() for i, x in enumerate(cells_)):
                held.append(b)
                continue
            if held or last:
                yield from solved([*held, b.slice(0, last)])
            held = [b.slice(last)]
        if held:
            yield from solved(held)

    cuts = mine.join(seqs, "key").select("key", "w", "seq").mapInArrow(cut, f"bucket bigint, id {kind}, c int, at int, lo int, hi int, loose array<int>, mine int, total int, x binary")
    dealt = cells(cuts, asks, F.col("mine"), F.col("total"), F.col("id"), F.col("c"))
    return dealt.select("bucket", "q", "j", "id", "c", "at", "lo", "hi", F.when(F.col("asks"), F.col("loose")).alias("loose"), "x").mapInArrow(run, f"a {kind}, key {kind}, start int, stop int, shift int, similarity double")


def repeated_passages(docs: DataFrame, settings: Settings | None = None, text: str = "text", key: str = "doc_id", scratch: Scratch | None = None) -> DataFrame:
    """key, start, end, first_key, first_start, first_end, similarity: a passage (places of words, the end not included)
    that is a near duplicate of one in a document with a smaller key.

    Words are runs without ASCII white space, A-Z lower-cased. Each passage is linked to the least document of a
    signature that both share or, if it isn't near that one, to others of the signature; of a class of equal passages
    each but the first is so linked, pairs among the rest are not spelled out. Texts under the least number of words, null texts and null keys give nothing; rows with equal keys
    count as one document, of which one text is taken.
    """
    s = settings or Settings()
    spark = docs.sparkSession
    sc = scratch or Scratch(spark, "passages")
    kind = docs.schema[key].dataType.simpleString()
    windows = compact_windows(docs, s, text, key)
    met = _met(windows, s, kind)
    pairs = sc.keep(met.groupBy("a", "key").agg(F.collect_list(F.struct("diag", "lo", "hi", "c", "sig", "l", "r")).alias("windows")), "pairs")
    asked = pairs.select(F.explode(F.array("a", "key")).alias("key")).distinct()
    own = docs.select(F.col(key).alias("key"), F.col(text).alias("text")).where(F.col("text").isNotNull()).join(asked, "key", "left_semi").dropDuplicates(["key"])
    seqs = sc.keep(_sequences(own, s, "text", "key"), "sequences")

    parts = "array<struct<diag:int,lo:int,x:binary>>"
    nodes_ = "array<struct<sig:bigint,c:int,l:int,r:int>>"

    def cut(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        """Of each text only what lies within a passage's width of a joined node: longer passages have more nodes."""
        for batch in batches:
            row, (diag, lo, hi, c, sig, l, r) = _flat(batch.column(2))  # noqa: E741
            d, p, q, at = (x.to_numpy() for x in (diag, lo, hi, c))
            ok = p <= q
            pair, d, p, q = _regions(row[ok], d[ok], np.maximum(p, at - s.width + 1)[ok], np.minimum(q, at + s.width - 1)[ok])
            raws = batch.column(3).to_pylist()
            xs = [raws[i][4 * a : 4 * (b + 1)] for i, a, b in zip(pair.tolist(), p.tolist(), q.tolist(), strict=True)]
            regions = _lists(pair, batch.num_rows, {"diag": pa.array(d.astype(np.int32)), "lo": pa.array(p.astype(np.int32)), "x": pa.array(xs, pa.binary())})
            open_ = sig.is_valid().to_numpy(zero_copy_only=False)
            where = pa.array(np.flatnonzero(open_))
            more = _lists(row[open_], batch.num_rows, {f: x.take(where) for f, x in zip(("sig", "c", "l", "r"), (sig, c, l, r), strict=True)})
            yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), regions, more], names=["a", "key", "parts", "nodes"])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        names = ["a", "key", "start", "stop", "shift", "similarity", "sig", "loose"]
        for batch in batches:
            pair, (diag, lo, x) = _flat(batch.column(2))
            regions: list[list[tuple[int, int, bytes]]] = [[] for _ in range(batch.num_rows)]
            for i, z in zip(pair.tolist(), zip(lo.to_pylist(), diag.to_pylist(), x.to_pylist(), strict=True), strict=True):
                regions[i].append(z)
            spans_of: list[list[tuple[int, int]]] = []
            out: list[tuple] = []
            for i, (own, y) in enumerate(zip(regions, batch.column(4).to_pylist(), strict=True)):
                spans: list[tuple[int, int]] = []
                for lo_, diag_, z in _far_first(own, s.width):
                    if spans and not _starts(lo_, lo_ + len(z) // 4 - 1, spans, s):
                        continue
                    for p, q, sim in _verified(z, lo_, y, diag_, s):
                        out.append((i, p, q, diag_, sim))
                        spans = _with(spans, p, q, s.width)
                spans_of.append(spans)
            a, key = batch.column(0), batch.column(1)
            if out:
                i, p, q, d, sim = zip(*out, strict=True)
                who = pa.array(i)
                ints = [pa.array(z, pa.int32()) for z in (p, q, d)]
                yield pa.RecordBatch.from_arrays([a.take(who), key.take(who), *ints, pa.array(sim, pa.float64()), pa.nulls(len(out), pa.int64()), pa.nulls(len(out), pa.list_(pa.int32()))], names=names)
            row, (sig, c, l, r) = _flat(batch.column(3))  # noqa: E741
            first, last = np.maximum(l.to_numpy(), c.to_numpy() - s.width + 1).tolist(), np.minimum(r.to_numpy(), c.to_numpy() + s.width - 1).tolist()
            loose, ends = [], [0]
            for i, p, q in zip(row.tolist(), first, last, strict=True):
                loose += _starts(p, q, spans_of[i], s)
                ends.append(len(loose))
            who = pa.array(row)
            yield pa.RecordBatch.from_arrays([a.take(who), key.take(who), l, r, c, pa.nulls(len(row), pa.float64()), sig, pa.ListArray.from_arrays(pa.array(ends, pa.int32()), pa.array(loose, pa.int32()))], names=names)

    cuts = sc.keep(pairs.join(seqs.withColumnRenamed("seq", "x"), "key").select("a", "key", "windows", "x").mapInArrow(cut, f"a {kind}, key {kind}, parts {parts}, nodes {nodes_}"), "cuts")
    sc.drop("pairs")
    both = cuts.join(seqs.select(F.col("key").alias("a"), F.col("seq").alias("y")), "a")
    checked = sc.keep(both.select("a", "key", "parts", "nodes", "y").mapInArrow(run, f"a {kind}, key {kind}, start int, stop int, shift int, similarity double, sig bigint, loose array<int>"), "checked")
    sc.drop("cuts")
    near = checked.where("sig is null").select("key", "start", "stop", "a", "shift", "similarity")
    left = checked.where("sig is not null").select("sig", "key", F.col("shift").alias("c"), F.col("start").alias("l"), F.col("stop").alias("r"), "loose")
    later = sc.keep(_rounds(left, seqs, s, kind), "later")
    sc.drop("sequences")
    w = F.array_sort(F.collect_set(F.struct("start", "stop", "similarity")))
    # spans of one diagonal that neighbouring windows gave, as one
    grown = later.groupBy("key", "a", "shift").agg(w.alias("w")).select("key", "a", "shift", F.explode(F.aggregate("w", F.array().cast("array<struct<start:int,stop:int,similarity:double>>"), _joined)).alias("z"))
    equal = grown.select("key", F.col("z.start").alias("start"), F.col("z.stop").alias("stop"), "a", "shift", F.col("z.similarity").alias("similarity"))
    out = near.unionByName(equal)
    end = F.col("stop") + s.shingle
    return out.select(F.col("key").alias(key), "start", end.alias("end"), F.col("a").alias(f"first_{key}"), (F.col("start") - F.col("shift")).alias("first_start"), (end - F.col("shift")).alias("first_end"), F.round("similarity", 6).alias("similarity"))


def _joined(done, x):
    """Sorted spans with one more: it grows the last if the two touch."""
    last = F.try_element_at(done, F.lit(-1))
    grown = F.struct(last["start"].alias("start"), F.greatest(last["stop"], x["stop"]).alias("stop"), F.greatest(last["similarity"], x["similarity"]).alias("similarity"))
    rest = F.slice(done, 1, F.greatest(F.size(done) - 1, F.lit(0)))
    return F.when(F.size(done) == 0, F.array(x)).when(x["start"] <= F.try_element_at(done, F.lit(-1))["stop"] + 1, F.concat(rest, F.array(grown))).otherwise(F.concat(done, F.array(x)))


def _union(spans: list[tuple[int, int]], gap: int) -> list[tuple[int, int]]:
    out: list[list[int]] = []
    for lo, hi in spans:
        if out and lo <= out[-1][1] + 1:
            out[-1][1] = max(out[-1][1], hi)
        else:
            out.append([lo, hi])
    return [(a, b) for a, b in out]


def drop_passages(docs: DataFrame, passages: DataFrame, text: str = "text", key: str = "doc_id") -> DataFrame:
    """docs without the words of their passages: what is left of a text is joined as it stands. Other rows and columns
    stay as they are; a null key or text has no passages. A text may become empty."""
    spans = passages.groupBy(F.col(key).alias("__key")).agg(F.collect_set(F.struct("start", "end")).alias("__spans"))
    both = docs.join(spans, docs[key] == F.col("__key"), "left").drop("__key")
    fields = both.schema.names
    i_text, i_spans = fields.index(text), fields.index("__spans")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            new = []
            for t, spans in zip(batch.column(i_text), batch.column(i_spans), strict=True):
                if not spans.is_valid or not t.is_valid:
                    new.append(t.as_py())
                    continue
                raw, cut = t.as_py().encode(), []
                w = Words([raw])
                for lo, hi in _union(sorted((x["start"], x["end"] - 1) for x in spans.as_py()), 0):
                    cut.append((int(w.starts[lo]), int(w.starts[hi + 1]) if hi + 1 < len(w.starts) else len(raw)))
                kept = b"".join(raw[p:q] for p, q in zip([0, *(b for _, b in cut)], [*(a for a, _ in cut), len(raw)], strict=True))
                new.append(kept.decode())
            arrays = [pa.array(new, pa.string()) if i == i_text else batch.column(i) for i in range(len(fields)) if i != i_spans]
            yield pa.RecordBatch.from_arrays(arrays, names=[f for i, f in enumerate(fields) if i != i_spans])

    return both.mapInArrow(run, docs.schema)
