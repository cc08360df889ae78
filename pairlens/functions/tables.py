"""Table functions for SQL, as workers import them. Where a plan can use them, the built-in columns of text.py are faster."""

from __future__ import annotations

import re

from pyspark.sql import SparkSession
from pyspark.sql import functions as F
from pyspark.sql.functions import AnalyzeArgument, AnalyzeResult
from pyspark.sql.types import IntegerType, StringType, StructType

from pairlens.functions import kernels as K

_BREAK = re.compile(r"([.!?])[ \t]+")


class SentenceRows:
    """(pos, sentence) of a text; none of a null."""

    @staticmethod
    def analyze(text: AnalyzeArgument) -> AnalyzeResult:
        return AnalyzeResult(StructType().add("pos", IntegerType()).add("sentence", StringType()))

    def eval(self, text: str):
        parts = (p.strip(" \t") for p in _BREAK.sub(r"\1\n", text or "").split("\n"))
        yield from enumerate(p for p in parts if p)


class GramRows:
    """(pos, gram) of a text's tokens, n joined by a blank; none of a null."""

    @staticmethod
    def analyze(text: AnalyzeArgument, n: AnalyzeArgument) -> AnalyzeResult:
        return AnalyzeResult(StructType().add("pos", IntegerType()).add("gram", StringType()))

    def eval(self, text: str, n: int):
        toks = K.tokenize(text)
        for i in range(len(toks) - n + 1):
            yield i, " ".join(toks[i : i + n])


def register_tables(spark: SparkSession) -> None:
    """sentence_rows(text), gram_table(text, n) and novel_share(gram, known) in SQL."""
    from pairlens.functions.udfs import novel_share

    spark.udtf.register("sentence_rows", F.udtf(SentenceRows))
    spark.udtf.register("gram_table", F.udtf(GramRows))
    spark.udf.register("novel_share", novel_share)
