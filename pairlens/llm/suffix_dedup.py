"""Exact repeats of n bytes across documents, by suffix arrays.

1. Each text's n-byte strings are cut into runs by their minimizer (the least hash of the k-byte grams inside): equal
   strings have equal minimizers, wherever they stand. Sorted gram hashes go out packed; a gram that only one text has
   can't lie in a repeat, and its runs are left out. Exact copies count as one text here and as removed later.
2. The runs that are left go to the shard of their gram. A shard builds a suffix array over its distinct runs
   (Larsson-Sadakane: groups of equal prefixes are refined by the ranks of what follows, only while they are unsorted)
   and the common prefixes of neighbours (Kasai, in the form that fills in text order from the irreducible ones).
   Neighbours with n bytes in common are equal strings; each group's least document keeps them.
3. A gram with more runs than a shard holds comes in pieces, in the order of documents: the sorted distinct strings of
   earlier pieces are searched by bisection and merged.
4. Spans go back to their documents.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from pairlens.llm.shared import Scratch
from pairlens.llm.textkernel import chunks_of_bytes, mix, running, span_hash

#: Bytes of runs that a task holds at once.
SHARD_BYTES = 3 << 20
#: Text bytes whose gram hashes one task holds: there are as many ranges of hashes as the corpus has of these.
RANGE_BYTES = 32 << 20
FAR = np.iinfo(np.int64).max


def sliding_min(v: np.ndarray, width: int) -> np.ndarray:
    """v's minima over width values from each place on (shorter by width - 1)."""
    m, k = v.copy(), 1
    while 2 * k <= width:
        np.minimum(m[:-k], m[k:], out=m[:-k])
        k *= 2
    if width > k:
        np.minimum(m[: k - width], m[width - k :], out=m[: k - width])
    return m[: len(v) - width + 1]


def runs(texts: list[bytes], n: int, k: int) -> tuple[np.ndarray, ...]:
    """(sums, text, first string, number of strings, minimizer) of every run of n-byte strings with one minimizer."""
    at = np.concatenate([[0], np.cumsum([len(t) + 1 for t in texts])])
    data = np.frombuffer(b"\0".join(texts) + b"\0", np.uint8)
    sums = running(data)
    if len(data) < n:
        none = np.zeros(0, np.int64)
        return sums, at, none, none, none, none.view(np.uint64)
    a = np.arange(len(data) - k + 1)
    least = sliding_min(mix(span_hash(sums, a, a + k)), n - k + 1)
    per = np.maximum(np.diff(at) - n, 0)
    text = np.repeat(np.arange(len(texts)), per)
    place = np.arange(len(text)) - np.repeat(np.cumsum(per) - per, per) + at[text]
    least = least[place]
    new = np.ones(len(text), bool)
    new[1:] = (least[1:] != least[:-1]) | (text[1:] != text[:-1])
    head = np.flatnonzero(new)
    return sums, at, text[head], place[head], np.diff(np.concatenate([head, [len(text)]])), least[head]


def suffix_array(t: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(order of the suffixes, 8-byte words at each place)."""
    size = len(t)
    padded = np.concatenate([t, np.zeros(8, np.uint8)])
    word = np.zeros(size, np.uint64)
    for j in range(8):
        word = (word << np.uint64(8)) | padded[j : j + size]
    sa = np.argsort(word).astype(np.int32)
    rank = np.empty(size, np.int64)

    def renew(slots: np.ndarray, keys: np.ndarray) -> np.ndarray:
        """Ranks of the suffixes in these slots; the slots whose groups still hold several."""
        head = np.ones(len(slots), bool)
        head[1:] = keys[1:] != keys[:-1]
        rank[sa[slots]] = slots[np.maximum.accumulate(np.where(head, np.arange(len(slots)), 0))]
        alone = head & np.concatenate([head[1:], [True]])
        return slots[~alone]

    open_ = renew(np.arange(size), word[sa]) if size else np.zeros(0, np.int64)
    h = 8
    while len(open_):
        s = sa[open_]
        after = s.astype(np.int64) + h
        inside = after < size
        key = rank[s] << 32
        # what ends within h bytes comes first, the shorter before the longer
        key += np.where(inside, rank[np.minimum(after, size - 1)] + h + 1, size - s)
        order = np.argsort(key)
        sa[open_] = s[order]
        open_ = renew(open_, key[order])
        h *= 2
    return sa, word


def common_prefixes(t: np.ndarray, sa: np.ndarray, word: np.ndarray) -> np.ndarray:
    """Bytes that each suffix shares with the one before it in the array (0 for the first)."""
    size = len(t)
    before = np.full(size, -1, np.int64)
    before[sa[1:]] = sa[:-1]
    i = np.arange(size)
    # a common prefix can only be longer than its left neighbour's less one where the bytes to the left differ
    own = (before >= 0) & ((i == 0) | (before == 0) | (t[i - 1] != t[before - 1]))
    x, y = i[own], before[own]
    shared, live = np.zeros(len(x), np.int64), np.arange(len(x))
    while len(live):
        p, q = x[live] + shared[live], y[live] + shared[live]
        room = np.maximum(p, q) + 8 <= size
        same = room.copy()
        same[room] = word[p[room]] == word[q[room]]
        rest = live[~same]
        for _ in range(8):  # bytes of the last word
            if not len(rest):
                break
            p, q = x[rest] + shared[rest], y[rest] + shared[rest]
            ok = np.maximum(p, q) < size
            ok[ok] = t[p[ok]] == t[q[ok]]
            rest = rest[ok]
            shared[rest] += 1
        live = live[same]
        shared[live] += 8
    ends = np.zeros(size, np.int64)
    ends[x] = x + shared
    # elsewhere the match of the left neighbour goes on: it ends where that one ends
    plcp = np.maximum.accumulate(ends) - i
    plcp[before < 0] = 0
    return np.maximum(plcp, 0)[sa]


class Shard:
    """Runs of whole grams, in the order of (gram, document)."""

    def __init__(self, n: int):
        self.n, self.gram = n, None
        self.strings, self.docs = np.zeros(0, f"S{n + 1}"), np.zeros(0, np.int64)

    def solve(self, rows: list[tuple]) -> Iterator[tuple]:
        """(document, tag, spans) of rows (gram, document, tag, start, bytes)."""
        n = self.n
        place: dict[bytes, int] = {}
        kind = np.array([place.setdefault(r[4], len(place)) for r in rows])
        doc = np.array([r[1] for r in rows], np.int64)
        gram = np.array([r[0] for r in rows], np.int64)
        first = np.full(len(place), FAR)
        np.minimum.at(first, kind, doc)
        of = np.zeros(len(place), np.int64)
        of[kind] = gram
        size = np.array([len(b) for b in place])
        base = np.cumsum(size + 1) - size - 1
        t = np.frombuffer(b"\0".join(place) + b"\0", np.uint8)
        sa, word = suffix_array(t)
        lcp = common_prefixes(t, sa, word)
        per = size - n + 1
        who = np.repeat(np.arange(len(place)), per)
        at = np.arange(len(who)) - np.repeat(np.cumsum(per) - per, per) + base[who]
        owner = np.full(len(t), -1, np.int64)
        owner[at] = who
        own = owner[sa]
        head = np.flatnonzero(lcp < n)
        group = np.cumsum(lcp < n) - 1
        least = np.minimum.reduceat(np.where(own >= 0, first[own], FAR), head)
        best = np.empty(len(t), np.int64)
        best[sa] = least[group]
        # the last gram may go on in the next piece, and the first may have begun in the one before
        if self.gram is not None and rows[0][0] == self.gram:
            best = self.searched(t, at[of[who] == self.gram], best)
        else:
            self.strings, self.docs = self.strings[:0], self.docs[:0]
        self.gram = rows[-1][0]
        mine = np.zeros(len(t), bool)
        mine[at[of[who] == self.gram]] = True
        order = sa[mine[sa]]
        ids = group[mine[sa]]
        keep = order[np.concatenate([[True], ids[1:] != ids[:-1]])] if len(ids) else order
        self.merge(t, keep, best)
        covered = best[at] < first[who]
        edge = np.diff(np.concatenate([[0], covered.astype(np.int8), [0]]))
        # runs of covered strings, cut where one run of bytes ends
        cut = np.zeros(len(who) + 1, bool)
        cut[np.cumsum(per)] = cut[0] = True
        both = cut[:-1] & covered & np.concatenate([[False], covered[:-1]])
        a = np.flatnonzero((edge[:-1] == 1) | both)
        b = np.flatnonzero((edge[1:] == -1) | np.concatenate([both[1:], [False]])) + 1
        lo, hi = np.searchsorted(who[a], [np.arange(len(place)), np.arange(1, len(place) + 1)])
        a, b = a - (np.cumsum(per) - per)[who[a]], b - (np.cumsum(per) - per)[who[b - 1]]
        out: dict[tuple, list[int]] = {}
        for r, k, later in zip(rows, kind.tolist(), (doc > first[kind]).tolist(), strict=True):
            spans = out.setdefault((r[1], r[2]), [])
            if later:
                spans += (r[3], r[3] + len(r[4]))
            else:
                for j in range(lo[k], hi[k]):
                    spans += (r[3] + int(a[j]), r[3] + int(b[j]) - 1 + n)
        return ((d, tag, s) for (d, tag), s in out.items() if s)

    def cut(self, t: np.ndarray, at: np.ndarray) -> np.ndarray:
        """The strings at these places, each with an end mark so that zero bytes at its end count."""
        if not len(at):
            return np.zeros(0, f"S{self.n + 1}")
        rows = np.lib.stride_tricks.sliding_window_view(t, self.n)[at]
        return np.concatenate([rows, np.ones((len(at), 1), np.uint8)], 1).view(f"S{self.n + 1}").ravel()

    def searched(self, t: np.ndarray, at: np.ndarray, best: np.ndarray) -> np.ndarray:
        s = self.cut(t, at)
        i = np.searchsorted(self.strings, s)
        hit = i < len(self.strings)
        hit[hit] = self.strings[i[hit]] == s[hit]
        best[at[hit]] = np.minimum(best[at[hit]], self.docs[i[hit]])
        return best

    def merge(self, t: np.ndarray, at: np.ndarray, best: np.ndarray) -> None:
        s = self.cut(t, at)
        i = np.searchsorted(self.strings, s)
        new = i == len(self.strings)
        new[~new] = self.strings[i[~new]] != s[~new]
        self.strings, self.docs = np.insert(self.strings, i[new], s[new]), np.insert(self.docs, i[new], best[at[new]])


def _gram_lists(texts: DataFrame, n: int, k: int, ranges: int) -> DataFrame:
    """fp, hashes: of each distinct text the minimizers that another text has too, in packed pieces."""

    def out_(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            prints, seen, own, bodies = batch.column(0).to_pylist(), {}, [], []
            for p, b in zip(prints, batch.column(1), strict=True):
                if p not in seen:
                    seen[p] = len(seen)
                    bodies.append(b)
            hs, cs, i = [], [], 0
            for part in chunks_of_bytes(bodies):
                _, _, text, _, _, least = runs(part, n, k)
                hs.append(least)
                cs.append((text + i).astype(np.uint32))
                i += len(part)
            if not hs:
                continue
            h, c = np.concatenate(hs), np.concatenate(cs)
            # minimizers are least hashes, so they crowd at the low end: a second hash deals them evenly
            r = ((mix(h) >> np.uint64(32)) * np.uint64(ranges)) >> np.uint64(32)
            order = np.lexsort((c, h, r))
            h, c, r = h[order], c[order], r[order]
            one = np.ones(len(h), bool)
            one[1:] = (h[1:] != h[:-1]) | (c[1:] != c[:-1])
            h, c, r = h[one], c[one], r[one]
            bounds = np.searchsorted(r, np.arange(ranges + 1).astype(np.uint64))
            own = np.frombuffer(b"".join(seen), np.uint8).reshape(-1, 16)
            rows = []
            for j, (a, b) in enumerate(zip(bounds[:-1].tolist(), bounds[1:].tolist(), strict=True)):
                if b > a:
                    used, who = np.unique(c[a:b], return_inverse=True)
                    rows.append((j, h[a:b].tobytes(), who.astype("<u2" if len(used) < 65536 else "<u4").tobytes(), own[used].tobytes()))
            yield pa.RecordBatch.from_arrays([pa.array([x[0] for x in rows], pa.int32()), *(pa.array([x[i] for x in rows], pa.binary()) for i in (1, 2, 3))], names=["r", "h", "who", "fps"])

    def by_range(batches: Iterator[pa.RecordBatch], solve) -> Iterator[pa.RecordBatch]:
        """Rows come sorted by range: one range is held at a time."""
        r, held = None, []
        for batch in batches:
            for row in zip(*(batch.column(i).to_pylist() for i in range(4)), strict=True):
                if row[0] != r and held:
                    yield from solve(held)
                    held = []
                r = row[0]
                held.append(row[1:])
        if held:
            yield from solve(held)

    def back(rows: list[tuple]) -> Iterator[pa.RecordBatch]:
        hs, cs, prints, at = [], [], [], 0
        for h, who, fps in rows:
            h = np.frombuffer(h, np.uint64)
            hs.append(h)
            cs.append(np.frombuffer(who, "<u2" if len(who) == 2 * len(h) else "<u4").astype(np.int64) + at)
            prints.append(np.frombuffer(fps, np.uint64).reshape(-1, 2))
            at += len(prints[-1])
        h, c, fp = np.concatenate(hs), np.concatenate(cs), np.concatenate(prints)
        del hs, cs, prints
        _, back_to, c64 = np.unique(fp[:, 0], return_index=True, return_inverse=True)
        c = c64[c]
        order = np.argsort(h)
        h, c = h[order], c[order]
        head = np.flatnonzero(np.concatenate([[True], h[1:] != h[:-1]]))
        many = np.minimum.reduceat(c, head) != np.maximum.reduceat(c, head)
        want = np.repeat(many, np.diff(np.concatenate([head, [len(h)]])))
        h, c = h[want], c[want]
        # one row for each range of fingerprints: the texts' answers travel packed
        order = np.argsort(c, kind="stable")
        h, c = h[order], c[order]
        head = np.flatnonzero(np.concatenate([[True], c[1:] != c[:-1]])) if len(c) else np.zeros(0, np.int64)
        count, own = np.diff(np.concatenate([head, [len(c)]])), fp[back_to[c[head]]]
        to = (own[:, 0] >> np.uint64(32)) * np.uint64(ranges) >> np.uint64(32)
        cut, place = np.searchsorted(to, np.arange(ranges + 1).astype(np.uint64)), np.concatenate([head, [len(c)]])
        rows = [(j, own[p:q].tobytes(), count[p:q].astype("<u4").tobytes(), h[place[p] : place[q]].tobytes()) for j, (p, q) in enumerate(zip(cut[:-1].tolist(), cut[1:].tolist(), strict=True)) if q > p]
        yield pa.RecordBatch.from_arrays([pa.array([x[0] for x in rows], pa.int32()), *(pa.array([x[i] for x in rows], pa.binary()) for i in (1, 2, 3))], names=["r", "fps", "counts", "h"])

    def unpack(rows: list[tuple]) -> Iterator[pa.RecordBatch]:
        """All answers of a text in one row."""
        fps = [np.frombuffer(f, np.uint64).reshape(-1, 2) for f, _, _ in rows]
        counts, hs = [np.frombuffer(n, "<u4").astype(np.int64) for _, n, _ in rows], [np.frombuffer(h, np.uint64) for _, _, h in rows]
        fp, count, h = np.concatenate(fps), np.concatenate(counts), np.concatenate(hs)
        order = np.lexsort((fp[:, 1], fp[:, 0]))
        start = (np.cumsum(count) - count)[order]
        fp, count = fp[order], count[order]
        at = np.concatenate([[0], np.cumsum(count)])
        h = h[np.arange(at[-1]) + np.repeat(start - at[:-1], count)]
        head = np.flatnonzero(np.concatenate([[True], (fp[1:] != fp[:-1]).any(1)]))
        ends = [*at[head[1:]].tolist(), len(h)]
        for lo in range(0, len(head), 5_000):
            part = list(zip(head[lo : lo + 5_000].tolist(), ends[lo : lo + 5_000], strict=True))
            yield pa.RecordBatch.from_arrays([pa.array([fp[i].tobytes() for i, _ in part], pa.binary()), pa.array([h[at[i] : j].tobytes() for i, j in part], pa.binary())], names=["fp", "hashes"])

    packed = texts.select("fp", "body").mapInArrow(out_, "r int, h binary, who binary, fps binary")
    answers = packed.repartition(ranges, "r").sortWithinPartitions("r").mapInArrow(lambda b: by_range(b, back), "r int, fps binary, counts binary, h binary")
    return answers.repartition(ranges, "r").sortWithinPartitions("r").mapInArrow(lambda b: by_range(b, unpack), "fp binary, hashes binary")


def repeated_spans(docs: DataFrame, n: int = 50, gram: int = 24, text: str = "text", key: str = "doc_id", scratch: Scratch | None = None) -> DataFrame:
    """key, tag (of the text), spans (pairs of int32, start and end): places covered by an n-byte string that a smaller key has too."""
    spark = docs.sparkSession
    s = scratch or Scratch(spark, "suffix")
    size = docs.agg(F.sum(F.octet_length(F.col(text)))).first()[0] or 0
    ranges = max(int(spark.conf.get("spark.sql.shuffle.partitions")), -(-size // RANGE_BYTES))
    texts = _texts(docs, text, key).where(F.col("key").isNotNull() & (F.octet_length("body") >= n))
    lists = s.keep(_gram_lists(texts, n, gram, ranges), "grams")
    classes = texts.groupBy("fp").agg(F.min("key").alias("first"))
    kind = docs.schema[key].dataType.simpleString()

    def cut(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        """Runs to route; those equal to a run of a smaller key in the batch, and whole copies, come without bytes."""
        names = ["gram", "key", "tag", "start", "size", "run"]
        types = [pa.int64(), pa.int64(), pa.int64(), pa.int32(), pa.int32(), pa.binary()]
        for batch in batches:
            keys, tags = batch.column(0).to_numpy().astype(np.int64), batch.column(1).to_numpy()
            own, size = batch.column(2).to_pylist(), pc.binary_length(batch.column(3)).to_numpy()
            copies = np.flatnonzero(~np.array(own, bool))
            if len(copies):
                yield pa.RecordBatch.from_arrays([pa.array(mix(keys[copies].view(np.uint64)).view(np.int64)), pa.array(keys[copies]), pa.array(tags[copies]), pa.array(np.zeros(len(copies), np.int32)), pa.array(size[copies].astype(np.int32)), pa.nulls(len(copies), pa.binary())], names=names)
            rows = np.array([i for i, (o, x) in enumerate(zip(own, batch.column(4), strict=True)) if o and x.is_valid], np.int64)
            if not len(rows):
                continue
            lists_, bodies, done = batch.column(4), batch.column(3), 0
            for part in chunks_of_bytes([bodies[int(i)] for i in rows], 2 << 20):
                here = rows[done : done + len(part)]
                done += len(part)
                asked = np.unique(np.frombuffer(b"".join(lists_[i].as_py() for i in here.tolist()), np.uint64))
                sums, at, t, place, count, least = runs(part, n, gram)
                want = np.isin(least, asked)
                t, place, count, least = t[want], place[want], count[want], least[want]
                end = place + count - 1 + n
                same, doc = mix(span_hash(sums, place, end)), keys[here[t]]
                order = np.lexsort((doc, count, same))
                twin = np.concatenate([[False], (same[order][1:] == same[order][:-1]) & (count[order][1:] == count[order][:-1])])
                lead = np.maximum.accumulate(np.where(~twin, np.arange(len(order)), 0))
                known = np.zeros(len(order), bool)
                known[order] = doc[order] > doc[order][lead] if len(order) else False
                raw = b"\0".join(part)
                bytes_ = [None if z else raw[a:b] for z, a, b in zip(known.tolist(), place.tolist(), end.tolist(), strict=True)]
                yield pa.RecordBatch.from_arrays([pa.array(least.view(np.int64)), pa.array(doc), pa.array(tags[here[t]]), pa.array((place - at[t]).astype(np.int32)), pa.array((end - place).astype(np.int32)), pa.array(bytes_, pa.binary())], names=names) if len(t) else pa.RecordBatch.from_arrays([pa.array([], x) for x in types], names=names)

    def solve(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        shard, held, size = Shard(n), [], 0

        def packed(found) -> pa.RecordBatch:
            found = list(found)
            return pa.RecordBatch.from_arrays([pa.array([x[0] for x in found], pa.int64()), pa.array([x[1] for x in found], pa.int64()), pa.array([np.array(x[2], "<i4").tobytes() for x in found], pa.binary())], names=["key", "tag", "spans"])

        for batch in batches:
            cols = [batch.column(i).to_pylist() for i in range(6)]
            known: dict[tuple, list[int]] = {}
            for g, d, tag, start, length, run in zip(*cols, strict=True):
                if run is None:
                    known.setdefault((d, tag), []).extend((start, start + length))
                    continue
                held.append((g, d, tag, start, run))
                size += len(run)
                if size >= SHARD_BYTES:
                    yield packed(shard.solve(held))
                    held, size = [], 0
            if known:
                yield packed((d, t, x) for (d, t), x in known.items())
        if held:
            yield packed(shard.solve(held))

    both = texts.join(classes, "fp").join(lists, "fp", "left")
    routed = both.select(F.col("key"), "tag", (F.col("key") == F.col("first")).alias("own"), "body", "hashes").mapInArrow(cut, "gram bigint, key bigint, tag bigint, start int, size int, run binary")
    found = routed.repartition(ranges, "gram").sortWithinPartitions("gram", "key").mapInArrow(solve, "key bigint, tag bigint, spans binary")
    out = s.keep(found, "spans")
    s.drop("grams")
    return out.select(F.col("key").cast(kind).alias(key), "tag", "spans")


def _texts(docs: DataFrame, text: str, key: str) -> DataFrame:
    body = F.coalesce(F.col(text).cast("binary"), F.lit(b""))
    base = docs.select(F.col(key).alias("key"), body.alias("body")).withColumn("fp", F.unhex(F.left(F.sha2("body", 256), F.lit(32))))
    return base.withColumn("tag", F.xxhash64("fp"))


def remove_repeats(docs: DataFrame, n: int = 50, gram: int = 24, text: str = "text", key: str = "doc_id", scratch: Scratch | None = None, keep_text: bool = False) -> DataFrame:
    """key, n_bytes, n_removed, n_spans, kept_sha256 of each row (with keep_text also kept, the remaining bytes).

    A byte goes if an n-byte string that covers it starts in a row with a smaller key too; matches stay within a row's
    text (UTF-8; null: empty). Of rows with equal keys none removes from the other; a row with a null key is left as
    it is and removes from none. Keys are whole numbers.
    """
    spans = repeated_spans(docs, n, gram, text, key, scratch).groupBy(F.col(key).alias("key"), "tag").agg(F.collect_list("spans").alias("spans"))
    all_ = _texts(docs, text, key).join(spans, ["key", "tag"], "left").select("key", "body", "spans")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            out = []
            for body, lists in zip(batch.column(1), batch.column(2), strict=True):
                b = body.as_py()
                if not lists.is_valid:
                    out.append((len(b), 0, 0, hashlib.sha256(b).hexdigest(), b))
                    continue
                x = np.frombuffer(b"".join(lists.as_py()), "<i4").reshape(-1, 2).astype(np.int64)
                x = x[np.argsort(x[:, 0], kind="stable")]
                end = np.maximum.accumulate(x[:, 1])
                new = np.concatenate([[True], x[1:, 0] > end[:-1]])
                lo, hi = x[new, 0], end[np.concatenate([new[1:], [True]])]
                kept = b"".join(b[p:q] for p, q in zip([0, *hi.tolist()], [*lo.tolist(), len(b)], strict=True))
                out.append((len(b), len(b) - len(kept), len(lo), hashlib.sha256(kept).hexdigest(), kept))
            cols = list(zip(*out, strict=True)) if out else [[]] * 5
            arrays = [batch.column(0), *(pa.array(c, pa.int64()) for c in cols[:3]), pa.array(cols[3], pa.string()), *([pa.array(cols[4], pa.binary())] if keep_text else [])]
            yield pa.RecordBatch.from_arrays(arrays, names=["key", "n_bytes", "n_removed", "n_spans", "kept_sha256", *(["kept"] if keep_text else [])])

    kind = docs.schema[key].dataType.simpleString()
    return all_.mapInArrow(run, f"key {kind}, n_bytes bigint, n_removed bigint, n_spans bigint, kept_sha256 string" + ", kept binary" * keep_text).withColumnRenamed("key", key)
