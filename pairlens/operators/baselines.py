"""Extractive baselines: lead sentences, sentences by estimated count, sentence centrality, greedy oracle."""

from __future__ import annotations

from collections.abc import Callable

import numpy as np
import pandas as pd
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.types import FloatType, LongType, StructField, StructType

from pairlens.functions import kernels as K
from pairlens.functions.text import n_units, sentences


def _joined(s: Column) -> Column:
    return F.array_join(s, " ")


def lead(pairs: DataFrame, k: int = 3) -> DataFrame:
    return pairs.withColumn("output", _joined(F.slice(sentences(F.col("reference")), 1, k)))


def lead_paragraph(pairs: DataFrame) -> DataFrame:
    return pairs.withColumn("output", F.substring_index("reference", "\n", 1))


def mean_ratio(pairs: DataFrame, split: str = "train", unit: str = "sentence") -> DataFrame:
    """One row: mean compression ratio of a split's pairs."""
    r = F.try_divide(n_units(F.col("reference"), unit).cast("double"), n_units(F.col("summary"), unit).cast("double"))
    return pairs.where(F.col("split") == split).agg(F.avg(r).alias("ratio"))


def with_k(pairs: DataFrame, ratio: DataFrame, rounding: str = "half_up") -> DataFrame:
    """k: sentences of the reference over the mean ratio, rounded half_up, down or up, at least 1 and at most all."""
    n = F.size(sentences(F.col("reference")))
    k = {"half_up": lambda x: F.floor(x + 0.5), "down": F.floor, "up": F.ceil}[rounding](n / F.col("ratio"))
    return pairs.crossJoin(F.broadcast(ratio)).withColumn("k", F.greatest(F.lit(1), F.least(F.coalesce(k, F.lit(1)), n)).cast("int")).drop("ratio")


def lead_k(pairs: DataFrame, ratio: DataFrame) -> DataFrame:
    p = with_k(pairs, ratio)
    return p.withColumn("output", _joined(F.slice(sentences(F.col("reference")), 1, F.col("k"))))


def random_k(pairs: DataFrame, ratio: DataFrame, seed: int = 0) -> DataFrame:
    """Control: k sentences with the least hashes, in document order."""
    p = with_k(pairs, ratio).withColumn("s", sentences(F.col("reference")))
    hashed = F.array_sort(F.transform("s", lambda x, i: F.struct(F.md5(F.concat(x, i.cast("string"), F.lit(str(seed)))).alias("h"), i.alias("i"))))
    order = F.array_sort(F.transform(F.slice(hashed, 1, F.col("k")), lambda x: x["i"]))
    return p.withColumn("output", _joined(F.transform(order, lambda i: F.get("s", i)))).drop("s")


def central(pairs: DataFrame, ratio: DataFrame, weights: str = "hashed", graph: str = "continuous", order: str = "document", encoder: Callable[[list[str]], np.ndarray] = K.hashed_vectors, **walk) -> DataFrame:
    """The k most central sentences of each reference's sentence graph, in document order or by rank. One document's
    graph is one row's work. encoder gives a unit vector per sentence; walk: threshold, damping, rounds, enough."""
    p = with_k(pairs, ratio)
    if weights == "tfidf":
        df = p.select("pair_id", F.explode(F.array_distinct(F.regexp_extract_all(F.lower("reference"), F.lit(r"[\p{L}\p{N}]+"), F.lit(0)))).alias("w"))
        total = p.agg(F.count(F.lit(1)).alias("total"))
        idf = df.groupBy("w").agg(F.count(F.lit(1)).alias("n")).crossJoin(F.broadcast(total)).select("w", F.log((F.col("total") + 1) / F.col("n")).alias("idf"))
        own = df.join(idf, "w").groupBy("pair_id").agg(F.map_from_entries(F.collect_list(F.struct("w", "idf"))).alias("idf"))
        p = p.join(own, "pair_id", "left")
    else:
        p = p.withColumn("idf", F.lit(None).cast("map<string,double>"))

    def pick(s: pd.Series, k: pd.Series, idf: pd.Series) -> pd.Series:
        rows = zip(s, k, idf, strict=True)
        return pd.Series([" ".join(x[i] for i in K.central_places(list(x), int(n), weights, graph, dict(w) if w is not None else None, order, encoder, **walk)) if x is not None else "" for x, n, w in rows])

    return p.withColumn("output", F.pandas_udf(pick, "string")(sentences(F.col("reference")), "k", "idf")).drop("idf")


def oracle_extract(pairs: DataFrame, most: int = 3) -> DataFrame:
    def pick(s: pd.Series, t: pd.Series) -> pd.Series:
        return pd.Series([" ".join(x[i] for i in K.oracle_places(list(x), y or "", most)) for x, y in zip(s, t, strict=True)])

    return pairs.withColumn("output", F.pandas_udf(pick, "string")(sentences(F.col("reference")), "summary"))


#: Numbers in a piece of a group's vectors: two pieces meet in one task.
PIECE_NUMBERS = 1 << 21
#: Tells vectors apart before they are compared.
vector_hash = F.xxhash64
#: Tasks that cells are dealt to, at least: cells differ in work.
CELL_TASKS = 256


def near_counts(rows: DataFrame, threshold: float) -> DataFrame:
    """g, d, h, u, near: for each distinct vector u, of d numbers and hash h, of a group g the rows of the group, its own
    included, whose product with u reaches the threshold; u is null where no other vector of g and d has that hash.
    Copies meet others once, with their number; each two pieces of a group meet in a cell."""
    kinds = rows.groupBy("h", "g", "u").agg(F.count(F.lit(1)).alias("n")).withColumn("d", F.size("u"))
    numbers = F.sum(F.when(F.col("n") > 0, 1)) * F.col("d")  # reads n, so that both sides of the join share an exchange
    pieces = F.greatest(F.lit(1), F.least(F.lit(3), F.ceil(numbers / (PIECE_NUMBERS >> 4))), F.ceil(numbers / PIECE_NUMBERS)).cast("int")
    dealt = kinds.join(kinds.groupBy("g", "d").agg(pieces.alias("pieces")), ["g", "d"]).withColumn("piece", F.pmod("h", F.col("pieces")).cast("int"))
    met = dealt.select("g", "d", "h", "u", "n", "piece", F.explode(F.sequence(F.lit(0), F.col("pieces") - 1)).alias("other"))
    cells = met.select("g", "d", F.least("piece", "other").alias("i"), F.greatest("piece", "other").alias("j"), "piece", "h", "u", "n")

    def meet(key: tuple[pa.Scalar, ...], cell: pa.Table) -> pa.Table:
        d, i, j = (k.as_py() for k in key[1:])
        sides = [cell.filter(pc.equal(cell["piece"], p)).combine_chunks() for p in dict.fromkeys((i, j))]
        values = [t["u"].combine_chunks().flatten().to_numpy(zero_copy_only=False).reshape(t.num_rows, d) for t in sides]
        sizes = [t["n"].to_numpy() for t in sides]
        near = K.near_counts(values[0], sizes[0], values[1], sizes[1], threshold) if i < j else (K.near_counts_within(values[0], sizes[0], threshold),)
        return pa.concat_tables(pa.table([t["g"], t["d"], t["h"], _where_shared(t["h"], t["u"]), pa.array(n)], names=["g", "d", "h", "u", "near"]) for t, n in zip(sides, near, strict=True))

    schema = StructType([*cells.select("g", "d", "h", "u").schema, StructField("near", LongType())])
    tasks = max(CELL_TASKS, int(rows.sparkSession.conf.get("spark.sql.shuffle.partitions")))  # cells are small, but much work: not to be coalesced
    found = cells.repartition(tasks, "g", "d", "i", "j").groupBy("g", "d", "i", "j").applyInArrow(meet, schema)
    return found.groupBy("h", "g", "d", "u").agg(F.sum("near").alias("near"))


def _where_shared(h: pa.ChunkedArray, u: pa.ChunkedArray) -> pa.ChunkedArray:
    """u where its hash isn't the only one in h, else null. All vectors of a hash are in one piece."""
    _, at, count = np.unique(h.to_numpy(), return_inverse=True, return_counts=True)
    return u.take(pa.array(np.arange(len(at)), mask=count[at] == 1))


def vector_degree(vectors: DataFrame, group: str = "label", key: str = "vec_id", vector: str = "embedding", threshold: float = 0.1) -> DataFrame:
    """Degree centrality of given unit vectors within their group: neighbours of another key at or above a cosine. Rows
    with a null key, group, vector or number have none and are nobody's; vectors of other lengths don't meet."""
    single = vectors.schema[vector].dataType.elementType == FloatType()
    v = vectors.select(F.col(group).alias("g"), F.col(key).alias("x"), (F.col(vector) if single else F.col(vector).cast("array<double>")).alias("u"))
    v = v.withColumn("h", F.when(~F.exists("u", lambda p: p.isNull()), vector_hash(F.col("u"))))
    rows = v.where("g is not null and x is not null and h is not null")
    own = F.aggregate("u", F.lit(0.0), lambda s, p: s + p.cast("double") * p.cast("double"))
    near = near_counts(rows.select("h", "g", "u"), threshold).toDF("near_h", "near_g", "near_d", "near_u", "near")
    twice = rows.groupBy("g", "x").agg(F.count(F.lit(1)).alias("rows")).where("rows > 1")
    again = rows.join(twice, ["g", "x"], "left_semi").select("h", F.struct("g", "x").alias("g"), "u")
    same = near_counts(again, threshold).select(F.col("h").alias("same_h"), F.col("g.g").alias("same_g"), "g.x", F.col("d").alias("same_d"), F.col("u").alias("same_u"), F.col("near").alias("same")).withColumnRenamed("x", "same_x")
    out = v.withColumn("own", (F.round(own, 6) >= threshold).cast("long")).withColumn("d", F.size("u"))
    out = out.join(near, F.expr("h = near_h and g = near_g and d = near_d and (near_u is null or near_u = u)"), "left")
    out = out.join(same, F.expr("h = same_h and g = same_g and x = same_x and d = same_d and (same_u is null or same_u = u)"), "left")
    return out.select(F.col("x").alias(key), F.col("g").alias(group), F.coalesce(F.when(F.col("x").isNotNull(), F.col("near") - F.coalesce("same", "own")), F.lit(0)).alias("degree"))
