"""Best-fit packing in bounded space: a fixed number of open bins, found by a bitset keyed by free space."""

from __future__ import annotations

import zlib
from collections import deque
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from pairlens.llm.textkernel import chunks_of_bytes
from pairlens.llm.token_counts import memo

WORK_BYTES = 1 << 20
#: Bins that may stand open in a task; beyond it the fullest closes.
OPEN_BINS = 1024
SCHEMA = "key {kind}, piece int, start bigint, length bigint, ids_crc32 bigint, sequence_id bigint, offset bigint"


class OpenBins:
    """Online best fit: an item goes to the fullest open bin that has room; ties go to the bin opened first."""

    def __init__(self, capacity: int, most: int):
        self.capacity, self.most, self.n, self.opened = capacity, most, 0, 0
        self.has = 0  # bit f is set if a bin with f free places is open
        self.by_free: dict[int, deque] = {}

    def put(self, size: int) -> tuple[int, int]:
        """(bin, offset) for an item of 1 to capacity places."""
        fits = self.has >> size
        if fits:
            free = size + (fits & -fits).bit_length() - 1
            b = self.take(free)
        else:
            if self.n >= self.most:
                self.take((self.has & -self.has).bit_length() - 1)  # the fullest closes
            b, free = self.opened, self.capacity
            self.opened += 1
        left = free - size
        if left:
            self.by_free.setdefault(left, deque()).append(b)
            self.has |= 1 << left
            self.n += 1
        return b, self.capacity - free

    def take(self, free: int) -> int:
        same = self.by_free[free]
        b = same.popleft()
        self.n -= 1
        if not same:
            self.has &= ~(1 << free)
        return b


def cut(n: int, capacity: int) -> list[tuple[int, int]]:
    """(start, length) of a document's pieces: only one that is too long is cut, and then all but the first are full."""
    head = n % capacity or capacity
    return [(0, head), *((s, capacity) for s in range(head, n, capacity))]


def pack(docs: DataFrame, tokenizer: str, capacity: int = 2048, end_id: int = 0, open_bins: int = OPEN_BINS, text: str = "text", key: str = "doc_id") -> DataFrame:
    """One row per piece: key, piece, start, length, ids_crc32, sequence_id, offset.

    A document is its tokens and then end_id; a null or empty text is end_id alone. Each task packs what it reads, in
    the order read, and numbers its sequences from its own range; so nothing is shuffled, a lost task is simply run
    again, and a task leaves at most open_bins sequences that more rows could have filled. Repeated rows are packed
    as often as they come; columns other than key and text are not read.
    """

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        from pyspark import TaskContext

        ids_of, bins = memo(tokenizer), OpenBins(capacity, open_bins)
        base, tail = TaskContext.get().partitionId() << 40, np.array([end_id], "<u4").tobytes()
        for batch in batches:
            row, out = 0, []
            for part in chunks_of_bytes(batch.column(1), WORK_BYTES):
                ids, bounds = ids_of(part)
                raw, bounds = ids.astype("<u4").tobytes(), bounds.tolist()
                for a, b in zip(bounds[:-1], bounds[1:], strict=True):
                    whole = raw[4 * a : 4 * b] + tail
                    for p, (s, n) in enumerate(cut(b - a + 1, capacity)):
                        seq, off = bins.put(n)
                        out.append((row, p, s, n, zlib.crc32(whole[4 * s : 4 * (s + n)]), base + seq, off))
                    row += 1
            cols = np.array(out, np.int64).reshape(-1, 7).T
            yield pa.RecordBatch.from_arrays([batch.column(0).take(pa.array(cols[0])), pa.array(cols[1].astype(np.int32)), *map(pa.array, cols[2:])], names=NAMES)

    kind = docs.schema[key].dataType.simpleString()
    plain = docs.select(F.col(key).alias("key"), F.col(text).cast("binary").alias("text"))
    out = plain.mapInArrow(run, SCHEMA.format(kind=kind))
    return out.withColumnRenamed("key", key)


NAMES = ["key", "piece", "start", "length", "ids_crc32", "sequence_id", "offset"]
