"""Pairs (reference, summary) from the given tables. Every mapping has pair_id, split, lang, origin, seq, reference, summary."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from pairlens.session import load

COLUMNS = ("pair_id", "split", "lang", "origin", "seq", "reference", "summary")


def split_of(c: Column) -> Column:
    return F.when(c % 10 == 9, "test").when(c % 10 == 8, "validation").otherwise("train")


def _pairs(df: DataFrame, key: str, reference: Column, summary: Column, lang: Column, origin: Column, seq: Column | None = None) -> DataFrame:
    k = F.col(key)
    return df.select(k.alias("pair_id"), split_of(k).alias("split"), lang.alias("lang"), origin.alias("origin"), (k if seq is None else seq).alias("seq"), reference.alias("reference"), summary.alias("summary"))


def headline_body(spark: SparkSession, sf: str) -> DataFrame:
    """The first line sums up the rest."""
    t = F.col("text")
    body = F.when(F.instr(t, "\n") > 0, F.substring(t, F.instr(t, F.lit("\n")) + 1, F.length(t))).otherwise("")
    return _pairs(load(spark, sf, "documents"), "doc_id", body, F.substring_index(t, "\n", 1), F.col("lang"), F.col("source"))


def lead_inclusive(spark: SparkSession, sf: str) -> DataFrame:
    """The first line sums up the whole text, itself included: nearly all extractive."""
    t = F.col("text")
    return _pairs(load(spark, sf, "documents"), "doc_id", t, F.substring_index(t, "\n", 1), F.col("lang"), F.col("source"))


def mixed_news(spark: SparkSession, sf: str) -> DataFrame:
    """Every other ten documents as lead_inclusive, the rest as headline_body: about half extractive."""
    even = F.floor(F.col("pair_id") / 10) % 2 == 0
    return lead_inclusive(spark, sf).where(even).unionByName(headline_body(spark, sf).where(~even))


def page_text(html: Column, title: bool = False) -> Column:
    """Text of the article element (or the title) without markup; the common entities are decoded once."""
    part = F.regexp_extract(html, r"(?s)<title>(.*?)</title>" if title else r"(?s)<article>(.*?)</article>", 1)
    part = F.regexp_replace(part, r"(?s)<h1>.*?</h1>", " ")
    part = F.regexp_replace(part, r"(?s)<[^>]*>", " ")
    for entity, plain in (("&lt;", "<"), ("&gt;", ">"), ("&quot;", '"'), ("&#39;", "'"), ("&amp;", "&")):
        part = F.replace(part, F.lit(entity), F.lit(plain))
    return F.regexp_replace(F.regexp_replace(part, r"\s+", " "), r"^ | $", "")


def page_title_body(spark: SparkSession, sf: str) -> DataFrame:
    h = F.col("html")
    return _pairs(load(spark, sf, "pages"), "page_id", page_text(h), page_text(h, True), F.regexp_extract(h, 'lang="([a-z]+)"', 1), F.lit("pages"))


def prompt_reply(spark: SparkSession, sf: str) -> DataFrame:
    """A reply is the reference of the question just before it."""
    w = W.partitionBy("conv_id").orderBy("turn")
    t = load(spark, sf, "conversations").select("*", F.lag("role").over(w).alias("before"), F.lag("text").over(w).alias("asked"))
    t = t.where((F.col("role") == "assistant") & (F.col("before") == "user"))
    return _pairs(t.withColumn("k", F.col("conv_id") * 100 + F.col("turn")), "conv_id", F.col("text"), F.col("asked"), F.lit("en"), F.lit("conversations"), F.col("k")).withColumn("pair_id", F.col("seq"))


def dialogue_digest(spark: SparkSession, sf: str) -> DataFrame:
    """All turns, summed up by the last assistant turn."""
    t = load(spark, sf, "conversations").groupBy("conv_id").agg(
        F.array_join(F.transform(F.array_sort(F.collect_list(F.struct("turn", "text"))), lambda x: x["text"]), "\n").alias("whole"), F.max_by("text", F.when(F.col("role") == "assistant", F.col("turn"))).alias("last")
    )
    return _pairs(t, "conv_id", F.col("whole"), F.col("last"), F.lit("en"), F.lit("conversations"))


def passage_host(spark: SparkSession, sf: str) -> DataFrame:
    """Documents that hold a benchmark passage, with that passage."""
    b = load(spark, sf, "benchmark").select("item_id", F.col("text").alias("passage"))
    t = load(spark, sf, "documents").join(b, F.contains("text", "passage"))
    return _pairs(t, "doc_id", F.col("text"), F.col("passage"), F.col("lang"), F.col("source"), F.col("doc_id") * 100_000 + F.col("item_id"))


def boilerplate_pairs(spark: SparkSession, sf: str) -> DataFrame:
    """Each document with that of its lines that most documents share (ties: the lesser line)."""
    lines = load(spark, sf, "documents").select("doc_id", "lang", "source", "text", F.explode(F.array_distinct(F.split("text", "\n"))).alias("line")).where("line <> ''")
    shared = lines.groupBy("line").agg(F.count(F.lit(1)).alias("n"))
    top = lines.select("doc_id", "line").join(shared, "line").groupBy("doc_id").agg(F.min(F.struct((-F.col("n")).alias("back"), "line")).alias("b"))
    return _pairs(load(spark, sf, "documents").join(top, "doc_id"), "doc_id", F.col("text"), F.col("b.line"), F.col("lang"), F.col("source"))


MAPPINGS = {"headline_body": headline_body, "lead_inclusive": lead_inclusive, "mixed_news": mixed_news, "page_title_body": page_title_body, "prompt_reply": prompt_reply, "dialogue_digest": dialogue_digest, "passage_host": passage_host, "boilerplate_pairs": boilerplate_pairs}
