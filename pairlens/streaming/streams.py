"""The sieve on streams: row checks as they are, duplicates with bounded or kept state, windows and joins."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming.query import StreamingQuery

from pairlens.operators import dedup
from pairlens.operators.sieve import Sieve


def stream_table(spark: SparkSession, path: str, like: DataFrame, files_per_batch: int = 1) -> DataFrame:
    """Files of a folder as a stream; times without a zone become instants, as watermarks ask for."""
    out = spark.readStream.schema(like.schema).option("maxFilesPerTrigger", files_per_batch).parquet(path)
    return out.withColumns({f.name: F.col(f.name).cast("timestamp") for f in like.schema.fields if f.dataType.simpleString() == "timestamp_ntz"})


def label_stream(pairs: DataFrame, sieve: Sieve | None = None) -> DataFrame:
    """Row checks hold no state, so the stream has the very columns of the batch."""
    return (sieve or Sieve(dedup=None)).label_rows(pairs)


def first_of_each(pairs: DataFrame, time: str, delay: str = "1 hour", side: str = "summary") -> DataFrame:
    """The first pair of each text within the delay; older state is dropped."""
    return pairs.withWatermark(time, delay).withColumn("fs", F.md5(side)).dropDuplicatesWithinWatermark(["fs"])


def additive_stream(pairs: DataFrame, path: str, checkpoint: str) -> StreamingQuery:
    """Order-respecting removal over batches: each batch is held against the texts kept so far, then against itself."""

    def batch(df: DataFrame, n: int) -> None:
        spark = df.sparkSession
        seen = f"{path}/kept"
        fresh = df.withColumn("fr", F.md5("reference")).withColumn("fs", F.md5("summary"))
        if n:
            kept = spark.read.parquet(seen)
            kept = kept.where(F.col("batch") < n)
            fresh = fresh.join(kept.select("fr"), "fr", "left_anti").join(kept.select("fs"), "fs", "left_anti")
        own = fresh.join(dedup.keep(fresh), "pair_id", "left_semi")
        # a batch that runs again after a failure overwrites its own folder only
        own.write.mode("overwrite").parquet(f"{seen}/batch={n}")

    return pairs.writeStream.foreachBatch(batch).option("checkpointLocation", checkpoint).trigger(availableNow=True).start()


def windowed_counts(events: DataFrame, width: str = "1 hour", slide: str | None = None, delay: str = "10 minutes") -> DataFrame:
    w = F.window("ts", width, slide) if slide else F.window("ts", width)
    return events.withWatermark("ts", delay).groupBy(w.alias("w"), "event_type").agg(F.count(F.lit(1)).alias("n")).select("w.start", "w.end", "event_type", "n")


def sessions(events: DataFrame, gap: str = "30 minutes", delay: str = "10 minutes") -> DataFrame:
    return events.withWatermark("ts", delay).groupBy(F.session_window("ts", gap).alias("w"), "user_id").agg(F.count(F.lit(1)).alias("n")).select("w.start", "w.end", "user_id", "n")


def bought_after_view(events: DataFrame, within: str = "1 hour", delay: str = "10 minutes") -> DataFrame:
    """Interval join of two streams; both sides' state is bounded by the watermark."""
    v = events.where("event_type = 'view'").select(F.col("user_id").alias("vu"), F.col("ts").alias("vt"), F.col("event_id").alias("view_id")).withWatermark("vt", delay)
    p = events.where("event_type = 'purchase'").select("user_id", "ts", F.col("event_id").alias("purchase_id")).withWatermark("ts", delay)
    return v.join(p, F.expr(f"vu = user_id AND ts >= vt AND ts <= vt + INTERVAL {within}")).select("view_id", "purchase_id", "user_id")


def repeat_counts(events: DataFrame) -> DataFrame:
    """A running count per user, held as arbitrary state."""
    import pandas as pd
    from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

    def step(key, batches, state: GroupState):
        n = (state.get[0] if state.exists else 0) + sum(len(b) for b in batches)
        state.update((n,))
        yield pd.DataFrame({"user_id": [key[0]], "n": [n]})

    return events.groupBy("user_id").applyInPandasWithState(step, "user_id bigint, n bigint", "n bigint", "update", GroupStateTimeout.NoTimeout)


def run_to_end(df: DataFrame, name: str, checkpoint: str, mode: str = "append") -> DataFrame:
    df.writeStream.format("memory").queryName(name).outputMode(mode).option("checkpointLocation", checkpoint).trigger(availableNow=True).start().awaitTermination()
    return df.sparkSession.table(name)


def with_limits(pairs: DataFrame, limits: DataFrame) -> DataFrame:
    """A stream of pairs against a static table (origin, min_ref, min_summ), a row per origin and so small: the verdict
    of the lengths. Origins without limits keep their pairs."""
    j = pairs.join(F.broadcast(limits), "origin", "left")
    short = lambda c, n: F.length(c) < F.coalesce(n, F.lit(0))
    return j.withColumn("verdict", F.when(short("reference", F.col("min_ref")), "ref_short").when(short("summary", F.col("min_summ")), "summ_short").otherwise("valid")).drop("min_ref", "min_summ")


def run_to_files(df: DataFrame, path: str, checkpoint: str) -> StreamingQuery:
    """All that has come so far, appended to files; run again on the same checkpoint it goes on where it ended."""
    query = df.writeStream.format("parquet").outputMode("append").option("path", path).option("checkpointLocation", checkpoint).trigger(availableNow=True).start()
    query.awaitTermination()
    return query


def dropped_late(query: StreamingQuery) -> int:
    """Rows that came behind the watermark, as the query's progress tells. Rows are held against the watermark of the
    batch before the last, so a row is late only if it was late then."""
    return sum(op["numRowsDroppedByWatermark"] for p in query.recentProgress for op in p["stateOperators"])
