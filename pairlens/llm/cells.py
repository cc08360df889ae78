"""Buckets dealt in cells: blocks of queries and of members that meet in one task each."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F


def cells(rows: DataFrame, asks: Column, mine: Column, all_: Column, *order: Column) -> DataFrame:
    """rows (with bucket, id) once for each cell they are in, dealt and sorted by cell and then as set.

    Those of a bucket's members that ask are its queries, cut in blocks; all its members are cut in blocks as well. A
    cell is a block of queries and a block of members, so one task never holds more than a block of queries, and a
    large bucket is spread over as many tasks as it has cells. mine and all_: how many blocks of either kind. Columns
    q, j, asks, is_asked tell the cell and what the row is there.
    """
    rows = rows.withColumn("nq", mine).withColumn("nm", all_)
    rows = rows.withColumn("bq", F.pmod(F.xxhash64("id", F.lit(1)), F.col("nq")).cast("int")).withColumn("bm", F.pmod(F.xxhash64("id", F.lit(2)), F.col("nm")).cast("int"))
    as_member = F.transform(F.sequence(F.lit(0), F.col("nq") - 1), lambda q: F.struct(q.alias("q"), F.col("bm").alias("j"), (asks & (q == F.col("bq"))).alias("asks"), F.lit(True).alias("is_asked")))
    as_query = F.transform(F.filter(F.sequence(F.lit(0), F.col("nm") - 1), lambda j: j != F.col("bm")), lambda j: F.struct(F.col("bq").alias("q"), j.alias("j"), F.lit(True).alias("asks"), F.lit(False).alias("is_asked")))
    places = F.when(asks, F.concat(as_member, as_query)).otherwise(as_member)
    out = rows.withColumn("cell", F.explode(places)).select("*", "cell.*").drop("cell", "nq", "nm", "bq", "bm")
    return out.repartition("bucket", "q", "j").sortWithinPartitions("bucket", "q", "j", *order)


class Cell:
    """What a cell does with its rows: open() takes the queries as one batch, meet() members, close() the end; all
    yield batches. Members may be among the queries."""

    def open(self, queries: pa.RecordBatch) -> None: ...

    def meet(self, members: pa.RecordBatch) -> Iterator[pa.RecordBatch]: ...

    def close(self) -> Iterator[pa.RecordBatch]: ...


def through(batches: Iterator[pa.RecordBatch], met: Cell) -> Iterator[pa.RecordBatch]:
    """Runs the cells of a task: columns bucket, q, j, asks, is_asked and others, sorted with the queries first."""
    cell, waiting, opened = None, [], False

    def begin() -> Iterator[pa.RecordBatch]:
        queries = pa.Table.from_batches(waiting).combine_chunks().to_batches()[0]
        met.open(queries)
        yield from met.meet(queries.filter(queries.column(queries.schema.get_field_index("is_asked"))))

    for batch in batches:
        if not batch.num_rows:
            continue
        cols = [batch.column(batch.schema.get_field_index(c)).to_numpy(zero_copy_only=False) for c in ("bucket", "q", "j", "asks")]
        new = np.zeros(batch.num_rows, bool)
        for c in cols:
            new[1:] |= c[1:] != c[:-1]
        edges = [0, *np.flatnonzero(new).tolist(), batch.num_rows]
        for lo, hi in zip(edges[:-1], edges[1:], strict=True):
            now, part = tuple(c[lo].item() for c in cols[:3]), batch.slice(lo, hi - lo)
            if now != cell:
                if waiting and not opened:
                    yield from begin()
                if cell is not None and waiting:
                    yield from met.close()
                cell, waiting, opened = now, [], False
            if cols[3][lo]:
                waiting.append(part)
            elif waiting:
                if not opened:
                    yield from begin()
                    opened = True
                yield from met.meet(part)
    if waiting:
        if not opened:
            yield from begin()
        yield from met.close()


def blocks(size: str, per: int) -> Column:
    return F.ceil(F.greatest(F.col(size), F.lit(1)) / per).cast("int")


def column(batch: pa.RecordBatch, name: str) -> pa.Array:
    return batch.column(batch.schema.get_field_index(name))
