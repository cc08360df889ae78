"""Stand-ins for trained systems: each turns pairs into outputs by a fixed rule, to exercise the probes."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from pairlens.functions.text import words


def _out(pairs: DataFrame, system: str, col) -> DataFrame:
    return pairs.withColumn("system", F.lit(system)).withColumn("output", col)


def prefix_copier(pairs: DataFrame, n: int = 48) -> DataFrame:
    return _out(pairs, "prefix_copier", F.array_join(F.slice(words(F.col("reference")), 1, n), " "))


def looper(pairs: DataFrame, phrase: int = 3, times: int = 16) -> DataFrame:
    return _out(pairs, "looper", F.array_join(F.flatten(F.array_repeat(F.slice(words(F.col("reference")), 1, phrase), times)), " "))


def truncating(pairs: DataFrame, limit: int = 512) -> DataFrame:
    return _out(pairs, "truncating", F.array_join(F.slice(words(F.col("reference")), 1, limit), " "))


def _dropped(c, every: int, seed: int):
    return F.array_join(F.filter(words(c), lambda w, i: F.pmod(F.conv(F.substring(F.md5(F.concat(w, i.cast("string"), F.lit(str(seed)))), 1, 6), 16, 10).cast("bigint"), F.lit(every)) != 0), " ")


def word_dropper(pairs: DataFrame, every: int = 5, seed: int = 1) -> DataFrame:
    return _out(pairs, "word_dropper", _dropped(F.substring_index("reference", "\n", 1), every, seed))


def number_swapper(pairs: DataFrame) -> DataFrame:
    """Facts reversed: digits are exchanged and the first two words change places."""
    w = words(F.translate(F.substring_index("reference", "\n", 1), "0123456789", "1032547698"))
    return _out(pairs, "number_swapper", F.array_join(F.concat(F.slice(w, 2, 1), F.slice(w, 1, 1), F.filter(w, lambda x, i: i >= 2)), " "))


def target_noiser(pairs: DataFrame, every: int = 4, seed: int = 2) -> DataFrame:
    """An abstractive system: the target with some words dropped."""
    return _out(pairs, "target_noiser", _dropped(F.col("summary"), every, seed))


def external(pairs: DataFrame, outputs: DataFrame, system: str) -> DataFrame:
    """Outputs of a real system, by pair_id; a pair without one has an empty output."""
    return _out(pairs.join(outputs.select("pair_id", F.col("output").alias("_o")), "pair_id", "left"), system, F.coalesce("_o", F.lit(""))).drop("_o")


SYSTEMS = (prefix_copier, looper, truncating, word_dropper, number_swapper, target_noiser)
