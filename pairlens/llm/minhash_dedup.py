"""Near duplicates: universal hash minima with banding, signatures, full sets, connected components.

Steps, each on columns as narrow as they can be:
1. One pass over the texts gives each document its set size, a 128-bit fingerprint of its set, its band keys and one
   byte of each minimum (its signature).
2. Documents with equal sets form a class; only a class's least document goes on.
3. In each bucket of a band every document is paired with the bucket's least one: as many pairs as members, not their
   square. Sizes, then signatures rule out most false pairs; the rest are confirmed on full sets.
4. A star can miss a link between two members that both differ from the least one. So after the components are known,
   in buckets that still hold several, members outside the largest meet a few of its members; and what is apart even
   then is compared with all members of other components, inside the bucket and on full sets, and only links that join
   two components come out. Then every pair that shares a bucket is either in one component or compared.
5. Confirmed links become components.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from pairlens.llm.cells import Cell, blocks, cells, column, through
from pairlens.llm.components import components
from pairlens.llm.shared import Scratch
from pairlens.llm.textkernel import Words, chunks_of_bytes, mix

#: Bands and minima in each. A pair at similarity 0.8 shares no band with a chance of (1 - 0.8**4)**32, about 5e-8.
BANDS, ROWS = 32, 4
#: Signatures may fall short of the threshold by so many standard deviations before a pair is ruled out unseen.
SLACK = 6.0
#: Members of a bucket's main component that those outside it meet before they are compared with all.
LEADERS = 4
#: Parts in which the rows of one class of equal sets are given their component.
SALTS = 64
#: Rows of a block of queries and of members when signatures are compared, and shingles of either when full sets are.
QUERY_ROWS, MEMBER_ROWS = 4_096, 65_536
QUERY_SHINGLES, MEMBER_SHINGLES = 1 << 19, 1 << 23
_rng = np.random.Generator(np.random.PCG64(97))
MULTIPLY = _rng.integers(1, 2**63, BANDS * ROWS, dtype=np.uint64) * np.uint64(2) + np.uint64(1)
ADD = _rng.integers(0, 2**63, BANDS * ROWS, dtype=np.uint64)


def minima(hashes: np.ndarray, starts: np.ndarray) -> np.ndarray:
    """uint32 minima of each set under each universal hash: rows are sets, columns hash functions."""
    out = np.empty((len(starts), len(MULTIPLY)), np.uint32)
    for j, (m, a) in enumerate(zip(MULTIPLY, ADD, strict=True)):
        out[:, j] = np.minimum.reduceat(((hashes * m + a) >> np.uint64(32)).astype(np.uint32), starts)
    return out


def bands(mins: np.ndarray) -> np.ndarray:
    wide = mins.astype(np.uint64).reshape(len(mins), BANDS, ROWS)
    key = np.arange(1, BANDS + 1, dtype=np.uint64)[None, :].repeat(len(mins), 0)
    for j in range(ROWS):
        key = mix(key * np.uint64(0x9E3779B97F4A7C15) + wide[:, :, j])
    return key.view(np.int64)


def sketch(docs: DataFrame, shingle: int, text: str, key: str) -> DataFrame:
    """id, n, fp (two longs), bands, sig of each document; without words n is 0 and the rest null."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            n_all, f1, f2, band, sig = [], [], [], [], []
            for part in chunks_of_bytes(batch.column(1)):
                hashes, _, bounds = Words(part).shingles(shingle)
                lists = [np.unique(hashes[a:b]) for a, b in zip(bounds[:-1].tolist(), bounds[1:].tolist(), strict=True)]
                n = np.array([len(x) for x in lists])
                full = np.flatnonzero(n)
                cols = [np.zeros(len(n), np.int64), np.zeros(len(n), np.int64), np.zeros((len(n), BANDS), np.int64), np.zeros((len(n), BANDS * ROWS), np.uint8)]
                if len(full):
                    flat = np.concatenate([lists[i] for i in full])
                    starts = np.concatenate([[0], np.cumsum(n[full])[:-1]])
                    mins = minima(flat, starts)
                    cols[0][full] = np.add.reduceat(mix(flat), starts).view(np.int64)
                    cols[1][full] = np.add.reduceat(mix(flat ^ np.uint64(0xA0761D6478BD642F)), starts).view(np.int64)
                    cols[2][full], cols[3][full] = bands(mins), mins.astype(np.uint8)
                n_all.append(n)
                for a, x in zip((f1, f2, band, sig), cols, strict=True):
                    a.append(x)
            if not n_all:
                continue
            n = np.concatenate(n_all).astype(np.int64)
            none = n == 0
            band_at = pa.array(np.concatenate([[0], np.cumsum(np.where(none, 0, BANDS))]).astype(np.int32))
            yield pa.RecordBatch.from_arrays(
                [batch.column(0), pa.array(n), pa.array(np.concatenate(f1), mask=none), pa.array(np.concatenate(f2), mask=none), pa.ListArray.from_arrays(band_at, pa.array(np.concatenate(band)[~none].ravel())), pa.array([None if z else s.tobytes() for z, s in zip(none, np.concatenate(sig), strict=True)], pa.binary())],
                names=["id", "n", "f1", "f2", "bands", "sig"],
            )

    kind = docs.schema[key].dataType.simpleString()
    return docs.select(F.col(key).alias("id"), F.col(text).cast("binary").alias("text")).mapInArrow(run, f"id {kind}, n bigint, f1 bigint, f2 bigint, bands array<bigint>, sig binary")


def full_sets(docs: DataFrame, shingle: int, text: str, key: str) -> DataFrame:
    """id and its whole set, sorted, as bytes."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            at = 0
            for part in chunks_of_bytes(batch.column(1)):
                hashes, _, bounds = Words(part).shingles(shingle)
                sets = [np.unique(hashes[a:b]).tobytes() for a, b in zip(bounds[:-1].tolist(), bounds[1:].tolist(), strict=True)]
                yield pa.RecordBatch.from_arrays([batch.column(0).slice(at, len(part)), pa.array(sets, pa.binary())], names=["id", "members"])
                at += len(part)

    kind = docs.schema[key].dataType.simpleString()
    return docs.select(F.col(key).alias("id"), F.col(text).cast("binary").alias("text")).mapInArrow(run, f"id {kind}, members binary")


def alike(pairs: DataFrame, percent: int) -> DataFrame:
    """Pairs (a, b, sig_a, sig_b) whose signatures agree often enough."""
    size, t = BANDS * ROWS, percent / 100
    least = size * t - SLACK * (size * t * (1 - t)) ** 0.5

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            if b.num_rows:
                x, y = (np.frombuffer(b"".join(b.column(i).to_pylist()), np.uint8).reshape(-1, size) for i in (2, 3))
                yield b.select([0, 1]).filter(pa.array((x == y).sum(1) >= least))

    kind = pairs.schema["a"].dataType.simpleString()
    return pairs.select("a", "b", "sig_a", "sig_b").mapInArrow(run, f"a {kind}, b {kind}")


def confirmed(pairs: DataFrame, sets: DataFrame, percent: int) -> DataFrame:
    """Pairs (a, b) with 100 * intersection >= percent * union of the full sets."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            ok = []
            for x, y in zip(b.column(2), b.column(3), strict=True):
                x, y = (np.frombuffer(z.as_buffer(), np.uint64) for z in (x, y))
                both = np.concatenate([x, y])
                both.sort(kind="stable")
                same = int((both[1:] == both[:-1]).sum())
                ok.append(100 * same >= percent * (len(both) - same))
            yield b.select([0, 1]).filter(pa.array(ok, pa.bool_()))

    kind = pairs.schema["a"].dataType.simpleString()
    with_b = pairs.join(sets.select(F.col("id").alias("b"), F.col("members").alias("set_b")), "b")
    with_a = with_b.join(sets.select(F.col("id").alias("a"), F.col("members").alias("set_a")), "a")
    return with_a.select("a", "b", "set_a", "set_b").mapInArrow(run, f"a {kind}, b {kind}")


def near_duplicates(docs: DataFrame, shingle: int = 5, percent: int = 80, text: str = "text", key: str = "doc_id", scratch: Scratch | None = None) -> DataFrame:
    """key, n_shingles, component_id, kept for each row.

    Words are runs without ASCII white space, A-Z lower-cased; a text with fewer words than a shingle has its whole
    sequence as one, a text without words (or a null) has an empty set and is linked with nothing. Documents are linked
    if 100 * intersection >= percent * union; component_id is the least key reachable and kept tells if it is the row's
    own. Keys should be unique and not null; repeated rows with one key share a component.
    """
    spark = docs.sparkSession
    s = scratch or Scratch(spark, "minhash")
    sk = s.keep(sketch(docs, shingle, text, key), "sketch")
    salted = sk.select("id", "n", "f1", "f2", F.pmod(F.xxhash64("id"), F.lit(SALTS)).alias("salt"))  # a class may hold very many copies
    classes = salted.where("n > 0").groupBy("f1", "f2", "n").agg(F.min("id").alias("rep"), F.collect_set("salt").alias("salts"))
    reps = s.keep(sk.join(classes.select(F.col("rep").alias("id")).distinct(), "id", "left_semi").where("n > 0").dropDuplicates(["id"]).select("id", "n", "bands", "sig"), "reps")
    members = reps.select("id", F.explode("bands").alias("bucket"))
    least = members.groupBy("bucket").agg(F.min("id").alias("a"), F.count(F.lit(1)).alias("m")).where("m > 1").select("bucket", "a")
    shared = s.keep(members.join(least, "bucket").select("bucket", "a", "id"), "shared")  # the buckets with several members
    asked = shared.select("id").distinct()
    own = docs.select(key, text).join(asked.withColumnRenamed("id", key), key, "left_semi").dropDuplicates([key])
    sets = s.keep(full_sets(own, shingle, text, key), "sets")
    small = reps.select("id", "n", "sig")

    def screen(pairs: DataFrame) -> DataFrame:
        """By size, then by signature."""
        one = pairs.join(small.select(F.col("id").alias("b"), F.col("n").alias("n_b"), F.col("sig").alias("sig_b")), "b")
        two = one.join(small.select(F.col("id").alias("a"), F.col("n").alias("n_a"), F.col("sig").alias("sig_a")), "a")
        return alike(two.where(100 * F.least("n_a", "n_b") >= percent * F.greatest("n_a", "n_b")), percent)

    def confirm(pairs: DataFrame, tag: str) -> DataFrame:
        return s.keep(confirmed(s.keep(pairs, f"{tag}-pairs"), sets, percent), f"{tag}-links")

    def torn(links: DataFrame, tag: str) -> DataFrame:
        """bucket, id, component, main of the buckets that still hold several components; main is the largest's."""
        parts = s.keep(components(links, s, f"{tag}-cc"), f"{tag}-parts")
        held = shared.select("bucket", "id").join(parts.withColumnRenamed("node", "id"), "id", "left").select("bucket", "id", F.coalesce("component", "id").alias("component"))
        counts = held.groupBy("bucket", "component").agg(F.count(F.lit(1)).alias("m"))
        main = counts.groupBy("bucket").agg(F.max(F.struct("m", "component")).alias("top"), F.sum("m").alias("total"), F.count(F.lit(1)).alias("k")).where("k > 1")
        return s.keep(held.join(main.select("bucket", F.col("top.component").alias("main"), (F.col("total") - F.col("top.m")).alias("mine"), "total"), "bucket"), f"{tag}-torn")

    links = confirm(screen(shared.where("a < id").select("a", F.col("id").alias("b")).distinct()), "star")
    # members that the least one doesn't reach meet some others of the main component, as many for each
    open_ = torn(links, "first")
    others = open_.where("component = main").groupBy("bucket").agg(*(F.min_by("id", F.xxhash64("id", F.lit(i))).alias(f"o{i}") for i in range(LEADERS)))
    more = open_.where("component <> main").join(others, "bucket").select("id", F.explode(F.array(*(f"o{i}" for i in range(LEADERS)))).alias("o"))
    links = s.keep(links.unionByName(confirm(screen(more.select(F.least("id", "o").alias("a"), F.greatest("id", "o").alias("b")).distinct()), "more")), "links")
    # what is still apart is compared with all members of other components, in blocks
    open_ = torn(links, "second").select("bucket", "id", "component", (F.col("component") == F.col("main")).alias("main"), "mine", "total").join(small, "id")
    final = components(links.unionByName(_apart(open_, sets, percent, s)), s, "all")
    for tag in ("reps", "shared", "sets", "links", "maybe", "rest-links", *(f"{x}-{y}" for x in ("star", "more") for y in ("pairs", "links")), *(f"{x}-{y}" for x in ("first", "second") for y in ("parts", "torn"))):
        s.drop(tag)
    named = classes.join(final.select(F.col("node").alias("rep"), "component"), "rep", "left").select("f1", "f2", "n", F.explode("salts").alias("salt"), "rep", "component")
    out = salted.join(named, ["f1", "f2", "n", "salt"], "left")
    group = F.coalesce("component", "rep", "id")
    return out.select(F.col("id").alias(key), F.col("n").alias("n_shingles"), group.alias("component_id"), group.eqNullSafe(F.col("id")).alias("kept"))


class _Screen(Cell):
    """Members and queries of a cell that have a partner in another component, by size and signature. A row that has
    been found isn't compared with others that have been, so a cell of many alike takes little more than one pass."""

    def __init__(self, percent: int):
        size, t = BANDS * ROWS, percent / 100
        self.percent, self.least = percent, size * t - SLACK * (size * t * (1 - t)) ** 0.5

    def read(self, rows: pa.RecordBatch) -> tuple:
        sig = np.frombuffer(b"".join(column(rows, "sig").to_pylist()), np.uint8).reshape(-1, BANDS * ROWS)
        return column(rows, "component").to_numpy(), column(rows, "n").to_numpy(), sig

    def open(self, queries: pa.RecordBatch) -> None:
        self.rows, (self.comp, self.n, self.sig) = queries, self.read(queries)
        self.hit = np.zeros(queries.num_rows, bool)

    def meet(self, members: pa.RecordBatch) -> Iterator[pa.RecordBatch]:
        comp, n, sig = self.read(members)
        hit = np.zeros(len(comp), bool)
        for i in range(len(self.comp)):
            ok = (comp != self.comp[i]) & (100 * np.minimum(n, self.n[i]) >= self.percent * np.maximum(n, self.n[i]))
            if self.hit[i]:
                ok &= ~hit
            at = np.flatnonzero(ok)
            at = at[np.count_nonzero(sig[at] == self.sig[i], axis=1) >= self.least]
            if len(at):
                self.hit[i] = hit[at] = True
        if hit.any():
            yield self.out(members.filter(pa.array(hit)))

    def close(self) -> Iterator[pa.RecordBatch]:
        if self.hit.any():
            yield self.out(self.rows.filter(pa.array(self.hit)))

    @staticmethod
    def out(rows: pa.RecordBatch) -> pa.RecordBatch:
        return rows.select(["bucket", "id", "component", "main", "n"])


class _Join(Cell):
    """Links between a cell's members and queries of different components, by their full sets: an inverted index over
    the queries' shingles counts what each member shares with each query. Only links that join two components that the
    task hasn't joined yet come out, so a cell gives fewer links than it has components."""

    #: Counters and postings that are worked on at once.
    WORK = 1 << 22

    def __init__(self, percent: int):
        self.percent, self.label, self.up = percent, {}, []

    def top(self, component) -> int:
        """The joined component's number in this task."""
        x = self.label.setdefault(component, len(self.up))
        if x == len(self.up):
            self.up.append(x)
        while self.up[x] != x:
            self.up[x] = self.up[self.up[x]]
            x = self.up[x]
        return x

    @staticmethod
    def sets(rows: pa.RecordBatch) -> list[np.ndarray]:
        return [np.frombuffer(x.as_buffer(), np.uint64) for x in column(rows, "members")]

    def open(self, queries: pa.RecordBatch) -> None:
        xs = self.sets(queries)
        self.ids, self.comp, self.n = column(queries, "id"), column(queries, "component").to_pylist(), np.array([len(x) for x in xs])
        flat, owner = np.concatenate(xs), np.repeat(np.arange(len(xs)), self.n)
        order = np.argsort(flat, kind="stable")
        self.flat, self.owner = flat[order], owner[order]

    def meet(self, members: pa.RecordBatch) -> Iterator[pa.RecordBatch]:
        roots = np.array([self.top(c) for c in self.comp])
        ids, comp, xs = column(members, "id"), column(members, "component").to_pylist(), self.sets(members)
        out: list[tuple[int, int]] = []
        lo = 0
        while lo < len(xs):
            if (roots == roots[0]).all():  # then only members elsewhere matter
                while lo < len(xs) and self.top(comp[lo]) == roots[0]:
                    lo += 1
                if lo == len(xs):
                    break
            hi = lo + max(1, min(len(xs) - lo, self.WORK // len(self.n), 64))
            flat = np.concatenate(xs[lo:hi])
            size = np.array([len(x) for x in xs[lo:hi]])
            first, last = np.searchsorted(self.flat, flat, "left"), np.searchsorted(self.flat, flat, "right")
            per, row = last - first, np.repeat(np.arange(hi - lo), size)
            shared = np.zeros((hi - lo) * len(self.n), np.int64)
            ends = np.cumsum(per)
            p = 0
            while p < len(per):  # so many postings at once
                q = max(p + 1, int(np.searchsorted(ends, (ends[p - 1] if p else 0) + self.WORK, "right")))
                k = per[p:q]
                at = np.arange(k.sum()) - np.repeat(np.cumsum(k) - k, k) + np.repeat(first[p:q], k)
                shared += np.bincount(np.repeat(row[p:q] * len(self.n), k) + self.owner[at], minlength=len(shared))
                p = q
            shared = shared.reshape(hi - lo, -1)
            near = 100 * shared >= self.percent * (size[:, None] + self.n[None, :] - shared)
            for i in np.flatnonzero(near.any(1)).tolist():
                own = self.top(comp[lo + i])
                for j in np.flatnonzero(near[i] & (roots != own)).tolist():
                    if roots[j] != own:
                        out.append((lo + i, j))
                        old = roots[j]
                        self.up[old] = own
                        roots[roots == old] = own
            lo = hi
        if out:
            x, y = ids.take(pa.array([i for i, _ in out])), self.ids.take(pa.array([j for _, j in out]))
            less = pc.less(x, y)
            yield pa.RecordBatch.from_arrays([pc.if_else(less, x, y), pc.if_else(less, y, x)], names=["a", "b"])

    def close(self) -> Iterator[pa.RecordBatch]:
        yield from ()


def _apart(open_: DataFrame, sets: DataFrame, percent: int, s: Scratch) -> DataFrame:
    """Links (a, b) that join components which meet in a bucket. open_: bucket, id, component, main, mine, total, n, sig.

    Signatures first tell which members have a possible partner in another component; only these, not pairs of them,
    come out. Their full sets then meet inside the bucket. So rows grow with the members, however alike they are.
    """
    kind = open_.schema["id"].dataType.simpleString()
    outside, first = ~F.col("main"), F.col("asks").desc()
    dealt = cells(open_, outside, blocks("mine", QUERY_ROWS), blocks("total", MEMBER_ROWS), first)
    maybe = dealt.select("bucket", "q", "j", "asks", "is_asked", "id", "component", "main", "n", "sig").mapInArrow(lambda b: through(b, _Screen(percent)), f"bucket bigint, id {kind}, component {kind}, main boolean, n bigint")
    maybe = s.keep(maybe.distinct(), "maybe")
    size = maybe.groupBy("bucket").agg(F.sum(F.when(~F.col("main"), F.col("n"))).alias("mine"), F.sum("n").alias("total"))
    dealt = cells(maybe.join(size, "bucket").join(sets, "id"), outside, blocks("mine", QUERY_SHINGLES), blocks("total", MEMBER_SHINGLES), first)
    found = dealt.select("bucket", "q", "j", "asks", "is_asked", "id", "component", "members").mapInArrow(lambda b: through(b, _Join(percent)), f"a {kind}, b {kind}")
    return s.keep(found.distinct(), "rest-links")
