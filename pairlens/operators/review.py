"""Samples to look at: in order, at random, outliers, representatives; and length statistics."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F


def in_order(df: DataFrame, axes: list[Column], n: int, offset: int = 0) -> DataFrame:
    """A page of rows along any axis: the top of the order only, never a full sort."""
    return df.orderBy(*axes).offset(offset).limit(n)


def _hash(key: str, seed: int) -> Column:
    return F.md5(F.concat(F.col(key).cast("string"), F.lit(str(seed))))


def random_sample(df: DataFrame, n: int, key: str, seed: int = 0, by: str | None = None) -> DataFrame:
    """n rows (of each group) with the least hashes: the same rows at any partitioning."""
    if by is None:
        return df.orderBy(_hash(key, seed)).limit(n)
    w = W.partitionBy(by).orderBy(_hash(key, seed))
    return df.withColumn("rn", F.row_number().over(w)).where(F.col("rn") <= n).drop("rn")


def extremes(df: DataFrame, metric: Column, n: int, key: str) -> DataFrame:
    m = df.select(key, metric.alias("value"))
    low = m.orderBy("value", key).limit(n).withColumn("side", F.lit("low"))
    return low.unionByName(m.orderBy(F.desc("value"), key).limit(n).withColumn("side", F.lit("high")))


def outliers(df: DataFrame, metric: Column, key: str, rule: str = "iqr", k: float = 1.5) -> DataFrame:
    """Rows beyond the fences: quartiles plus k times their distance, or k standard deviations from the mean."""
    m = df.select(key, metric.cast("double").alias("value"))
    if rule == "iqr":
        s = m.agg(F.percentile("value", F.lit(0.25)).alias("q1"), F.percentile("value", F.lit(0.75)).alias("q3")).select((F.col("q1") - k * (F.col("q3") - F.col("q1"))).alias("lo"), (F.col("q3") + k * (F.col("q3") - F.col("q1"))).alias("hi"))
    else:
        s = m.agg(F.avg("value").alias("m"), F.stddev_samp("value").alias("s")).select((F.col("m") - k * F.col("s")).alias("lo"), (F.col("m") + k * F.col("s")).alias("hi"))
    return m.crossJoin(F.broadcast(s)).where("value < lo or value > hi").select(key, F.round("value", 6).alias("value"))


def representatives(df: DataFrame, metric: Column, key: str, n: int, center: str = "median") -> DataFrame:
    m = df.select(key, metric.cast("double").alias("value"))
    c = m.agg((F.median("value") if center == "median" else F.avg("value")).alias("c"))
    return m.crossJoin(F.broadcast(c)).select(key, F.round("value", 6).alias("value"), F.abs(F.col("value") - F.col("c")).alias("off")).orderBy("off", key).limit(n).select(key, "value")


def describe(df: DataFrame, metric: Column, by: list[str]) -> DataFrame:
    v = df.select(*by, metric.cast("double").alias("value"))
    q = lambda p: F.round(F.percentile("value", F.lit(p)), 6)
    return v.groupBy(*by).agg(F.count("value").alias("n"), F.round(F.avg("value"), 6).alias("mean"), F.round(F.stddev_samp("value"), 6).alias("sd"), F.min("value").alias("least"), q(0.25).alias("q1"), q(0.5).alias("median"), q(0.75).alias("q3"), F.max("value").alias("most"))


def states(labelled: DataFrame) -> DataFrame:
    """Each pair in the state before filtering, and the valid ones also after it."""
    return labelled.withColumn("state", F.explode(F.when(F.col("verdict") == "valid", F.array(F.lit("unfiltered"), F.lit("filtered"))).otherwise(F.array(F.lit("unfiltered")))))


def violin(labelled: DataFrame) -> DataFrame:
    """Mean and quartiles of both lengths before and after."""
    long = states(labelled).select("split", "state", F.length("reference").alias("reference"), F.length("summary").alias("summary")).unpivot(["split", "state"], ["reference", "summary"], "side", "size")
    return describe(long, F.col("size"), ["split", "state", "side"])


def density(labelled: DataFrame, column: str = "reference", width: int = 200, bandwidth: float = 200.0, reach: int = 20) -> DataFrame:
    """Gaussian density on the bins' centres: bins are counted first, the kernel runs over pairs of near bins only."""
    bins = states(labelled).groupBy("state", F.floor(F.length(column) / width).alias("bin")).agg(F.count(F.lit(1)).alias("n"))
    total = bins.groupBy("state").agg(F.sum("n").alias("total"))
    spread = bins.withColumn("at", F.explode(F.sequence(F.col("bin") - reach, F.col("bin") + reach)))
    z = (F.col("at") - F.col("bin")) * width / bandwidth
    kernel = F.sum(F.col("n") * F.exp(-0.5 * z * z)) / (bandwidth * 2.5066282746310002)
    return spread.groupBy("state", "at").agg(kernel.alias("raw")).join(F.broadcast(total), "state").where("at >= 0").select("state", F.col("at").alias("bin"), F.round(F.col("raw") / F.col("total"), 9).alias("density"))


def shift(labelled: DataFrame, column: str = "reference", width: int = 100) -> DataFrame:
    """Greatest gap between the cumulative shares of the two states, and the change of the mean."""
    v = states(labelled).select("state", F.length(column).alias("size"))
    bins = v.groupBy(F.floor(F.col("size") / width).alias("bin")).agg(F.count_if(F.col("state") == "unfiltered").alias("a"), F.count_if(F.col("state") == "filtered").alias("b"))
    w, all_ = W.orderBy("bin"), W.partitionBy()
    gap = bins.select(F.abs(F.sum("a").over(w) / F.sum("a").over(all_) - F.sum("b").over(w) / F.sum("b").over(all_)).alias("gap"))  # a row per bin
    means = v.agg(F.avg(F.when(F.col("state") == "filtered", F.col("size"))).alias("f"), F.avg(F.when(F.col("state") == "unfiltered", F.col("size"))).alias("u"))
    return gap.agg(F.round(F.max("gap"), 6).alias("max_gap")).crossJoin(means.select(F.round(F.col("f") - F.col("u"), 6).alias("mean_change")))
