"""Connected components by alternating large-star and small-star, each round a table in the shared folder."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from pairlens.llm.shared import Scratch


def _starred(edges: DataFrame, large: bool) -> DataFrame:
    """large: each node's larger neighbours point to its least neighbour (itself included); small: its smaller ones and itself do.
    The least is found by an aggregate and joined back, so a node with very many neighbours is spread over tasks."""
    both = edges.unionByName(edges.select(F.col("b").alias("a"), F.col("a").alias("b"))) if large else edges.select(F.greatest("a", "b").alias("a"), F.least("a", "b").alias("b"))
    least = both.groupBy("a").agg(F.min("b").alias("m")).select("a", F.least("a", "m").alias("m"))
    joined = both.join(least, "a")
    if large:
        out = joined.where(F.col("b") > F.col("a")).select(F.col("b").alias("a"), F.col("m").alias("b"))
    else:
        out = joined.select(F.col("b").alias("a"), F.col("m").alias("b")).unionByName(least.select("a", F.col("m").alias("b")))
    return out.where("a <> b").distinct()


def components(edges: DataFrame, scratch: Scratch, tag: str = "cc") -> DataFrame:
    """(node, component) of all nodes that have an edge; component is the least node reachable. edges: a, b of one type.

    Null ends, loops and repeated edges are dropped. Only counts reach the driver, once a round.
    """
    now = scratch.keep(edges.select("a", "b").where("a <> b").distinct(), f"{tag}-0")
    seen, i = None, 0
    while True:
        i += 1
        now = scratch.keep(_starred(_starred(now, True), False), f"{tag}-{i}")
        mark = tuple(now.agg(F.count(F.lit(1)), F.sum(F.xxhash64("a", "b").cast("decimal(20,0)"))).first())
        scratch.drop(f"{tag}-{i - 1}")
        if mark == seen:
            break
        seen = mark
    return now.select(F.col("a").alias("node"), F.col("b").alias("component")).unionByName(now.select(F.col("b").alias("node"), F.col("b").alias("component")).distinct())
